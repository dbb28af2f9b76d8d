"""A stored graph for users: add, modify, retire, as-of reads, compaction and SQL views.

Every write is one commit of a status log; nothing is deleted. A modification is a retirement and an
addition in the same commit.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgflow.store import graph
from kgflow.store.commit import Store

LOG = "head string, relation string, tail string, status string, batch_id int, seq int, evidence string"


@dataclass
class Graph:
    spark: SparkSession
    root: str

    @property
    def store(self) -> Store:
        return Store(self.spark, self.root)

    def log(self, k: int | None = None) -> DataFrame:
        rows = self.store.read("log", k)
        return self.spark.createDataFrame([], LOG) if rows is None else rows

    def _write(self, rows: DataFrame, k: int | None) -> dict:
        k = self.store.last() + 1 if k is None else k
        return self.store.commit(k, {"log": rows.withColumn("batch_id", F.lit(k)).select(*(c.split()[0] for c in LOG.split(", ")))})

    def add(self, facts: DataFrame, k: int | None = None) -> dict:
        """facts (head, relation, tail, evidence): those that are not active become so, again or for the first time."""
        new = facts.dropDuplicates(graph.KEY).join(self.active().select(*graph.KEY), graph.KEY, "left_anti")
        return self._write(new.withColumn("status", F.lit("ACTIVE")).withColumn("seq", F.lit(1)), k)

    def retire(self, facts: DataFrame, k: int | None = None) -> dict:
        """facts (head, relation, tail, evidence): those that are active are deprecated, with the evidence."""
        return self._write(self._down(facts), k)

    def _down(self, facts: DataFrame) -> DataFrame:
        old = facts.dropDuplicates(graph.KEY).join(self.active().select(*graph.KEY), graph.KEY, "left_semi")
        return old.withColumn("status", F.lit("DEPRECATED")).withColumn("seq", F.lit(0))

    def modify(self, changes: DataFrame, k: int | None = None) -> dict:
        """changes (head, relation, tail, new_tail, evidence)."""
        up = changes.select("head", "relation", F.col("new_tail").alias("tail"), "evidence").dropDuplicates(graph.KEY)
        up = up.withColumn("status", F.lit("ACTIVE")).withColumn("seq", F.lit(1))
        return self._write(self._down(changes.drop("new_tail")).unionByName(up), k)

    def status(self, k: int | None = None) -> DataFrame:
        return graph.status_at(self.log(k))

    def active(self, k: int | None = None) -> DataFrame:
        return self.status(k).where("status = 'ACTIVE'")

    def explain(self, head: str) -> DataFrame:
        """Every change of the facts about a head, with evidence."""
        return self.log().where(F.col("head") == head).orderBy("batch_id", "seq")

    def compact(self) -> dict:
        """The log so far as one table of a new batch that has no parent; older batches stay readable by number."""
        k = self.store.last() + 1
        return self.store.commit(k, {"log": self.log()}, note="compacted", parent=-1)

    def rollback(self, k: int) -> dict:
        return self.store.rollback(k)

    def views(self) -> None:
        """Temp views kg_log, kg_edges (with status), kg_active, kg_nodes, kg_deprecations."""
        self.log().createOrReplaceTempView("kg_log")
        self.status().createOrReplaceTempView("kg_edges")
        self.active().createOrReplaceTempView("kg_active")
        graph.nodes_of(self.active()).createOrReplaceTempView("kg_nodes")
        self.log().where("status = 'DEPRECATED'").createOrReplaceTempView("kg_deprecations")
