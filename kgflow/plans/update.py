"""One step of the loop on functional state facts, and runs of steps over batches."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgflow.config import LoopConfig
from kgflow.extract import event_track
from kgflow.govern import intent
from kgflow.session import settled
from kgflow.store import graph

FACT = "head string, relation string, tail string, valid_time timestamp_ntz, ord array<bigint>, stmt_id string, batch_id int"
DOWN = "head string, relation string, tail string, stmt_id string, valid_time timestamp_ntz, by_stmt string, at timestamp_ntz, batch_id int"


@dataclass
class Run:
    adds: DataFrame  # facts added, with the batch
    downs: DataFrame  # facts retired, with their old evidence and what retired them
    active: DataFrame
    steps: list[dict] = field(default_factory=list)

    def log(self) -> DataFrame:
        """Status log: (head, relation, tail, status, batch_id, seq, stmt_id, at)."""
        down = self.downs.select(*graph.KEY, F.lit("DEPRECATED").alias("status"), "batch_id", F.lit(0).alias("seq"), F.col("by_stmt").alias("stmt_id"), "at")
        up = self.adds.select(*graph.KEY, F.lit("ACTIVE").alias("status"), "batch_id", F.lit(1).alias("seq"), "stmt_id", F.col("valid_time").alias("at"))
        return down.unionByName(up)


def step(active: DataFrame, facts: DataFrame, k: int, cfg: LoopConfig) -> tuple[DataFrame, DataFrame]:
    """(added, retired) of batch k, given the facts that its statements assert.

    With the intent check, the youngest assertion per head and relation decides; without it, or without
    events, whose times it needs, nothing is retired and every asserted value is added."""
    down_fields = [f.split()[0] for f in DOWN.split(", ")]
    known = active.select(*graph.KEY)
    if not (cfg.intent and cfg.events):
        first = facts.groupBy(*graph.KEY).agg(F.min_by(F.struct("valid_time", "ord", "stmt_id"), F.struct("valid_time", "ord")).alias("x")).select(*graph.KEY, "x.*")
        add = first.join(known, graph.KEY, "left_anti").withColumn("batch_id", F.lit(k))
        return add, active.sparkSession.createDataFrame([], DOWN)
    change = graph.latest(facts)
    down = intent.targets(change, active).withColumn("batch_id", F.lit(k)).select(*down_fields)
    stale = active.select("head", "relation", F.struct("valid_time", "ord").alias("_have"))
    newer = change.join(stale, ["head", "relation"], "left").where(F.col("_have").isNull() | (F.col("_have") <= F.struct("valid_time", "ord"))).drop("_have")
    add = newer.join(known, graph.KEY, "left_anti").withColumn("batch_id", F.lit(k))
    return add, down


def run(facts: DataFrame, cfg: LoopConfig, batches: list[int]) -> Run:
    """All batches in order; each batch's state is written to the shared folder before the next."""
    spark = facts.sparkSession
    cols = [f.split()[0] for f in FACT.split(", ")]
    active = spark.createDataFrame([], FACT)
    adds, downs = active, spark.createDataFrame([], DOWN)
    for k in batches:
        add, down = step(active, facts.where(F.col("batch_id") == k), k, cfg)
        add, down = settled(add.select(*cols)), settled(down)
        active = settled(graph.apply_edges(active, down, add))
        adds, downs = adds.unionByName(add), downs.unionByName(down)
    return Run(adds, downs, active)


def lifecycle_facts(stmts: DataFrame, cfg: LoopConfig) -> DataFrame:
    """State facts of statements that pass the intent check (or all, where that is off)."""
    ev = event_track.events(stmts)
    if cfg.intent and cfg.events:
        ev = ev.where(intent.intent("text") == "EVOLUTIONARY")
    return event_track.state_facts(ev, cfg.coref)


def lifecycle(stmts: DataFrame, cfg: LoopConfig | None = None, batches: list[int] | None = None) -> Run:
    cfg = cfg or LoopConfig()
    return run(lifecycle_facts(stmts, cfg), cfg, batches or list(range(cfg.windows)))


def rebuilt(facts: DataFrame) -> DataFrame:
    """Full reconstruction from all batches at once: the active state facts."""
    return graph.latest(facts).select(*graph.KEY)
