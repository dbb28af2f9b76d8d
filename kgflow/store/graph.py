"""The set algebra of graph states."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KEY = ["head", "relation", "tail"]


@dataclass
class Increment:
    nodes_add: DataFrame
    edges_add: DataFrame
    edges_down: DataFrame


def nodes_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("head", "tail")).alias("node")).distinct()


def apply_nodes(nodes: DataFrame, add: DataFrame) -> DataFrame:
    return nodes.unionByName(add.join(nodes, "node", "left_anti").dropDuplicates(["node"]))


def apply_edges(edges: DataFrame, down: DataFrame, add: DataFrame) -> DataFrame:
    """Edges without those that go down, with those that are added; an edge in both ends active."""
    kept = edges.join(down.select(*KEY).distinct(), KEY, "left_anti")
    return kept.unionByName(add.dropDuplicates(KEY).join(kept.select(*KEY), KEY, "left_anti"))


def latest(facts: DataFrame) -> DataFrame:
    """Per head and functional relation the youngest fact, by (valid_time, ord)."""
    cols = [c for c in facts.columns if c not in ("head", "relation")]
    return facts.groupBy("head", "relation").agg(F.max_by(F.struct(*cols), F.struct("valid_time", "ord")).alias("_x")).select("head", "relation", "_x.*")


def status_at(log: DataFrame, k: int | None = None) -> DataFrame:
    """Status of every edge ever committed, as of batch k: log (head, relation, tail, status, batch_id, seq)."""
    seen = log if k is None else log.where(F.col("batch_id") <= k)
    return seen.groupBy(*KEY).agg(F.max_by("status", F.struct("batch_id", "seq")).alias("status"), F.min("batch_id").alias("first_batch"), F.max("batch_id").alias("last_batch"))


def diff(log: DataFrame, a: int, b: int) -> DataFrame:
    """Edges whose status differs between batches a and b: (edge, before, after)."""
    x, y = status_at(log, a).select(*KEY, F.col("status").alias("before")), status_at(log, b).select(*KEY, F.col("status").alias("after"))
    return x.join(y, KEY, "full_outer").where(~F.col("before").eqNullSafe(F.col("after")))


def intervals(log: DataFrame) -> DataFrame:
    """Validity of each edge: (edge, from_batch, to_batch) of every active spell; to_batch null while it lasts."""
    from pyspark.sql import Window

    w = Window.partitionBy(*KEY).orderBy("batch_id", "seq")
    nxt = log.withColumn("to_batch", F.lead("batch_id").over(w))
    return nxt.where("status = 'ACTIVE'").select(*KEY, F.col("batch_id").alias("from_batch"), "to_batch")


def revived(log: DataFrame) -> DataFrame:
    """Edges that became active again after a deprecation: (edge, spells)."""
    return intervals(log).groupBy(*KEY).agg(F.count("*").alias("spells")).where("spells > 1")
