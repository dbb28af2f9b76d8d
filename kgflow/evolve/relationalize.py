"""Events as edges: a type fact and one fact per role."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def facts(ev: DataFrame) -> DataFrame:
    """(head, relation, tail, batch_id) of events (event_id, trigger, roles, time, batch_id)."""
    roles = F.transform(F.map_entries("roles"), lambda e: F.transform(e["value"], lambda v: F.struct(e["key"].alias("relation"), v.alias("tail"))))
    own = F.array(F.struct(F.lit("type").alias("relation"), F.col("trigger").alias("tail")), F.struct(F.lit("time").alias("relation"), F.col("time.start").cast("string").alias("tail")))
    return ev.select(F.col("event_id").alias("head"), "batch_id", F.explode(F.concat(own, F.flatten(roles))).alias("f")).select("head", "f.relation", "f.tail", "batch_id")
