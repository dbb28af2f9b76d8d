"""Event schemas: role sets per trigger, required roles by presence."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgflow.config import LoopConfig


def role_presence(ev: DataFrame) -> DataFrame:
    """(trigger, role, events, share) of events (trigger, roles map)."""
    total = ev.groupBy("trigger").agg(F.count("*").alias("total"))
    rows = ev.select("trigger", F.explode(F.map_keys("roles")).alias("role")).groupBy("trigger", "role").agg(F.count("*").alias("events"))
    return rows.join(total, "trigger").select("trigger", "role", "events", F.round(F.col("events") / F.col("total"), 6).alias("share"))


def coherence(ev: DataFrame) -> DataFrame:
    """(trigger, coherence): mean over the events of the share of the type's roles that an event has; computed from counts."""
    shares = role_presence(ev)
    return shares.groupBy("trigger").agg(F.round(F.avg("share"), 6).alias("coherence"))


def clusters(ev: DataFrame) -> DataFrame:
    """(trigger, roles, events, cluster): signatures of events by trigger and set of roles; signatures of one trigger cluster, as one's
    roles are among the other's or they share most of them."""
    rows = ev.groupBy("trigger", F.array_sort(F.map_keys("roles")).alias("roles")).agg(F.count("*").alias("events"))
    lead = Window.partitionBy("trigger").orderBy(F.desc("events"), F.array_join("roles", ","))
    most = F.first("roles").over(lead)
    near = F.size(F.array_intersect("roles", most)) >= 0.5 * F.size(F.array_union("roles", most))
    return rows.withColumn("near", near).withColumn("cluster", F.when(F.col("near"), F.col("trigger")).otherwise(F.concat_ws(":", "trigger", F.array_join("roles", ",")))).drop("near")


def register(ev: DataFrame, cfg: LoopConfig, required_share: float = 0.95) -> DataFrame:
    """(trigger, support, required, allowed, coherence, verdict)."""
    shares = role_presence(ev)
    n = ev.groupBy("trigger").agg(F.count("*").alias("support"))
    sets = shares.groupBy("trigger").agg(F.array_sort(F.collect_set(F.when(F.col("share") >= required_share, F.col("role")))).alias("required"), F.array_sort(F.collect_set("role")).alias("allowed"))
    ok = (F.col("support") > cfg.theta_event) & (F.col("coherence") >= cfg.coherence_min)
    return n.join(sets, "trigger").join(coherence(ev), "trigger").withColumn("verdict", F.when(ok, "PASS").otherwise("POOL"))
