"""Logical checks. Each returns the candidates that fail, with a reason."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgflow.session import stored

IRREFLEXIVE = ("precedes", "placed_by", "based_in", "in_region")
ANTISYMMETRIC = ("precedes", "placed_by", "in_region")


def self_loops(cands: DataFrame, irreflexive=IRREFLEXIVE) -> DataFrame:
    return cands.where(F.col("relation").isin(*irreflexive) & (F.col("head") == F.col("tail"))).withColumn("reason", F.lit("self_loop"))


def mutual_pairs(cands: DataFrame, active: DataFrame | None = None, antisymmetric=ANTISYMMETRIC) -> DataFrame:
    """In-batch pairs in both directions are both rejected; against the graph only the candidate is. One aggregation per unordered pair finds
    both: it keeps which ways the batch and the graph tell the pair."""
    pairs = lambda d: d.where(F.col("relation").isin(*antisymmetric) & (F.col("head") != F.col("tail"))).withColumn("lo", F.least("head", "tail")).withColumn("hi", F.greatest("head", "tail")).withColumn("up", F.col("head") < F.col("tail"))
    key = ["relation", "lo", "hi"]
    own = pairs(cands)
    told = own.select(*key, "up", F.lit(True).alias("mine"))
    if active is not None:
        told = told.unionByName(pairs(active.select("head", "relation", "tail")).select(*key, "up", F.lit(False).alias("mine")))
    up, mine = F.col("up"), F.col("mine")
    ways = told.groupBy(*key).agg(F.bool_or(mine & up).alias("_up"), F.bool_or(mine & ~up).alias("_down"), F.bool_or(~mine & up).alias("_graph_up"), F.bool_or(~mine & ~up).alias("_graph_down"))
    hit = own.join(stored(ways.where("_up and _down or _up and _graph_down or _down and _graph_up")), key)
    why = lambda rows, reason: rows.select(*cands.columns).withColumn("reason", F.lit(reason))
    out = why(hit.where("_up and _down"), "mutual_pair")
    return out if active is None else out.unionByName(why(hit.where("up and _graph_down or not up and _graph_up"), "mutual_with_graph"))


def cycles(cands: DataFrame, relation: str, max_hops: int = 4) -> DataFrame:
    """Edges of relation that lie on a directed cycle of at most max_hops edges."""
    edges = cands.where(F.col("relation") == relation).select("head", "tail").distinct()
    path = edges.select(F.col("head").alias("start"), F.col("tail").alias("first"), F.col("tail").alias("at"))
    found = path.where("start = at").select("start", "first")
    for _ in range(max_hops - 1):
        path = path.where("start <> at").join(edges, F.col("at") == F.col("head")).select("start", "first", F.col("tail").alias("at")).distinct()
        found = found.unionByName(path.where("start = at").select("start", "first"))
    bad = found.distinct().select(F.col("start").alias("head"), F.col("first").alias("tail"))
    return cands.where(F.col("relation") == relation).join(bad, ["head", "tail"], "left_semi").withColumn("reason", F.lit("cycle"))


def signatures(cands: DataFrame, schemas: DataFrame) -> DataFrame:
    """cands (relation, head_type, tail_type) with unseen and fits; schemas: (relation, domain, range) arrays.
    A relation without schema passes as unseen."""
    known = cands.join(F.broadcast(schemas.select("relation", "domain", "range")), "relation", "left")
    unseen = F.col("domain").isNull()
    fits = unseen | (F.array_contains("domain", F.col("head_type")) & F.array_contains("range", F.col("tail_type")))
    return known.withColumn("unseen", unseen).withColumn("fits", fits).drop("domain", "range")


def roles(events: DataFrame, schemas: DataFrame) -> DataFrame:
    """events (trigger, roles map) with unseen and fits: every required role of the trigger's schema is filled,
    and no unknown role is. schemas: (trigger, required array, allowed array)."""
    known = events.join(F.broadcast(schemas.select("trigger", "required", "allowed")), "trigger", "left")
    have = F.map_keys("roles")
    fits = F.col("required").isNull() | (F.forall("required", lambda r: F.array_contains(have, r)) & F.forall(have, lambda r: F.array_contains("allowed", r)))
    return known.withColumn("unseen", F.col("required").isNull()).withColumn("fits", fits).drop("required", "allowed")
