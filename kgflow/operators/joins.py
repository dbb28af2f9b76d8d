"""Operators around the methods: as-of, interval and range joins, top-k, set difference, validity."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, by: list[str], left_ts: str, right_ts: str, values: list[str], tolerance: Column | None = None) -> DataFrame:
    """left with the values of the last right row at or before its time. One union and one sorted window
    per key, no pairs; equal times count as before."""
    none = {v: right.schema[v].dataType for v in values}
    a = left.select("*", F.col(left_ts).alias("_t"), F.lit(1).alias("_side"), F.lit(None).cast("timestamp_ntz").alias("_rt"), *(F.lit(None).cast(t).alias(f"_v_{v}") for v, t in none.items()))
    keep = [c for c in left.columns if c not in by]
    b = right.select(*by, F.col(right_ts).alias("_t"), F.lit(0).alias("_side"), F.col(right_ts).alias("_rt"), *(F.col(v).alias(f"_v_{v}") for v in values), *(F.lit(None).cast(left.schema[c].dataType).alias(c) for c in keep))
    w = Window.partitionBy(*by).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("_side") == 0, F.struct("_rt", *(F.col(f"_v_{v}") for v in values))), ignorenulls=True).over(w)
    out = a.unionByName(b).withColumn("_hit", last).where("_side = 1")
    if tolerance is not None:
        out = out.withColumn("_hit", F.when(F.col("_t") - F.col("_hit._rt") <= tolerance, F.col("_hit")))
    return out.select(*left.columns, *(F.col(f"_hit._v_{v}").alias(v) for v in values))


def overlap(left: DataFrame, right: DataFrame, by: list[str], l_bounds: tuple[str, str], r_bounds: tuple[str, str], width: int) -> DataFrame:
    """Pairs whose [from, to] number intervals meet: equal buckets first, each pair once (in the later start's bucket)."""
    cut = lambda c: F.floor(F.col(c) / width)
    a = left.withColumn("_b", F.explode(F.sequence(cut(l_bounds[0]), cut(l_bounds[1]))))
    b = right.withColumn("_b", F.explode(F.sequence(cut(r_bounds[0]), cut(r_bounds[1]))))
    meet = (F.col(l_bounds[0]) <= F.col(r_bounds[1])) & (F.col(r_bounds[0]) <= F.col(l_bounds[1]))
    once = F.col("_b") == F.floor(F.greatest(l_bounds[0], r_bounds[0]) / width)
    return a.join(b, [*by, "_b"]).where(meet & once).drop("_b")


def topk(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """k first rows per key; the rank filter is pushed below the exchange as a group limit."""
    return df.withColumn("_r", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("_r") <= k).drop("_r")


def minus(df: DataFrame, other: DataFrame, key: list[str]) -> DataFrame:
    return df.join(other.select(*key).distinct(), key, "left_anti")


def intervals(log: DataFrame, key: list[str], ts: str) -> DataFrame:
    """log with valid_from and valid_to, the next row's time of the same key."""
    return log.withColumn("valid_from", F.col(ts)).withColumn("valid_to", F.lead(ts).over(Window.partitionBy(*key).orderBy(ts)))


def salted_join(left: DataFrame, right: DataFrame, key: list[str], salts: int, how: str = "inner") -> DataFrame:
    """Equi-join whose hot left keys are dealt over so many tasks; right rows are repeated per salt."""
    a = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [*key, "_salt"], how).drop("_salt")


def sketch_count(df: DataFrame, by: list[str], col: str) -> DataFrame:
    """Mergeable distinct-count sketches per group."""
    return df.groupBy(*by).agg(F.hll_sketch_agg(col).alias("sketch"))


def sketch_merge(sketches: DataFrame, by: list[str]) -> DataFrame:
    return sketches.groupBy(*by).agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("estimate"))
