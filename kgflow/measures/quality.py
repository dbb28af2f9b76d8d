"""Accuracy and schema measures. They read gold rows and results, and share no code with the gates."""

from __future__ import annotations

from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def ratio(a: Column, b: Column) -> Column:
    return F.round(F.try_divide(a.cast("double"), b.cast("double")), 6)


def prf(pred: DataFrame, gold: DataFrame, by: list[str], key: list[str], weight: str | None = None) -> DataFrame:
    """Counts and precision, recall and harmonic mean of distinct rows per group; null where undefined. Rows with a null are never the same. weight:
    a column of both sides, how many rows a row stands for. One aggregation of both sides, without a join."""
    n = F.col(weight) if weight else F.lit(1)
    side = lambda d, p: d.select(*by, *key, n.cast("long").alias("_n"), F.lit(p).alias("_p"), F.lit(not p).alias("_g"))
    one = side(pred, True).unionByName(side(gold, False)).groupBy(*by, *key).agg(F.max("_n").alias("_n"), F.bool_or("_p").alias("_p"), F.bool_or("_g").alias("_g"))
    whole = reduce(and_, (F.col(c).isNotNull() for c in [*by, *key]))
    total = lambda c: F.sum(F.when(c, F.col("_n")).otherwise(F.lit(0)))
    agg = one.groupBy(*by).agg(total(F.col("_p") & F.col("_g") & whole).alias("tp"), total(F.col("_p")).alias("n_pred"), total(F.col("_g")).alias("n_gold"))
    return with_prf(agg)


def with_prf(counts: DataFrame) -> DataFrame:
    p, r = F.try_divide(F.col("tp").cast("double"), F.col("n_pred").cast("double")), F.try_divide(F.col("tp").cast("double"), F.col("n_gold").cast("double"))
    return counts.withColumn("precision", F.round(p, 6)).withColumn("recall", F.round(r, 6)).withColumn("f1", F.round(F.try_divide(2 * p * r, p + r), 6))


def delta_precision(additions: DataFrame, window: str = "batch_id", ok: str = "supported") -> DataFrame:
    """Additions judged fully supported over all additions, per window."""
    return additions.groupBy(window).agg(F.count("*").alias("additions"), F.sum(F.col(ok).cast("int")).alias("supported")).withColumn("delta_precision", ratio(F.col("supported"), F.col("additions")))


def dhp(deprecations: DataFrame, windows: DataFrame, window: str = "batch_id", ok: str = "justified") -> DataFrame:
    """Justified deprecations over all, per window; null where nothing was deprecated."""
    got = deprecations.groupBy(window).agg(F.count("*").alias("d"), F.sum(F.col(ok).cast("int")).alias("j"))
    return windows.join(got, window, "left").select(window, F.coalesce("d", F.lit(0)).alias("deprecations"), F.coalesce("j", F.lit(0)).alias("justified")).withColumn("dhp", ratio(F.col("justified"), F.nullif(F.col("deprecations"), F.lit(0))))


def bcubed(mentions: DataFrame, by: list[str], cluster: str = "cluster", entity: str = "entity") -> DataFrame:
    """B-cubed precision and recall: from counts per (cluster, entity), never from pairs of mentions."""
    cell = mentions.groupBy(*by, cluster, entity).agg(F.count("*").alias("n"))
    c = mentions.groupBy(*by, cluster).agg(F.count("*").alias("nc"))
    e = mentions.groupBy(*by, entity).agg(F.count("*").alias("ne"))
    j = cell.join(c, [*by, cluster]).join(e, [*by, entity])
    agg = j.groupBy(*by).agg(F.sum("n").alias("mentions"), F.sum(F.col("n") * F.col("n") / F.col("nc")).alias("p"), F.sum(F.col("n") * F.col("n") / F.col("ne")).alias("r"))
    return agg.select(*by, "mentions", F.round(F.col("p") / F.col("mentions"), 6).alias("precision"), F.round(F.col("r") / F.col("mentions"), 6).alias("recall"))


def kappa(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """(n, accuracy, kappa) of two boolean judges."""
    x, y = F.col(a).cast("double"), F.col(b).cast("double")
    agg = pairs.agg(F.count("*").alias("n"), F.avg((F.col(a) == F.col(b)).cast("double")).alias("po"), F.avg(x).alias("px"), F.avg(y).alias("py"))
    pe = F.col("px") * F.col("py") + (1 - F.col("px")) * (1 - F.col("py"))
    return agg.select("n", F.round("po", 6).alias("accuracy"), F.round(F.try_divide(F.col("po") - pe, 1 - pe), 6).alias("kappa"))


def schema_quality(mapping: DataFrame, gold: DataFrame) -> DataFrame:
    """(types, matched, schema_precision, redundant, redundancy): mapping (alias, relation), gold (alias, gold).

    A type matches the gold relation that most of its aliases have, if no other type took it before by
    name; a type is redundant if another type matches the same gold relation."""
    votes = mapping.join(gold, "alias").groupBy("relation", "gold").agg(F.count("*").alias("n"))
    top = votes.groupBy("relation").agg(F.max_by("gold", F.struct("n", "gold")).alias("gold"))
    per = top.groupBy("gold").agg(F.count("*").alias("k"))
    return per.agg(F.sum("k").alias("types"), F.count("*").alias("matched"), F.sum(F.when(F.col("k") > 1, F.col("k")).otherwise(0)).alias("redundant")).select("types", "matched", ratio(F.col("matched"), F.col("types")).alias("schema_precision"), "redundant", ratio(F.col("redundant"), F.col("types")).alias("redundancy"))


def graph_size(log: DataFrame) -> DataFrame:
    """Log rows by batch and status with subtotals: (batch_id, status, edges)."""
    return log.rollup("batch_id", "status").agg(F.count("*").alias("edges"))
