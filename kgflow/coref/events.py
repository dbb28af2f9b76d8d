"""Event coreference: similar events of a batch, and alignment with an index of earlier ones."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgflow.coref.cluster import components
from kgflow.functions.text import jaccard


def similarity(trigger_a, trigger_b, args_a, args_b, seconds: Column, slack: int) -> Column:
    """Weighted agreement of trigger, arguments and time, 0 to 1."""
    same = (F.col(trigger_a) == F.col(trigger_b)).cast("double")
    near = F.greatest(F.lit(0.0), 1 - F.abs(seconds).cast("double") / slack)
    return F.round(0.4 * same + 0.4 * F.coalesce(jaccard(args_a, args_b), F.lit(0.0)) + 0.2 * near, 6)


def within(left: DataFrame, right: DataFrame, by: list[str], at: str, slack: int, keep: str = "id") -> DataFrame:
    """Pairs (a, b, seconds) with equal keys and times no more than slack seconds apart.

    Times fall into slack-wide buckets; right rows go to their own and both neighbouring ones, so that
    the join is an equi-join on key and bucket with a residual, whatever the size of a key."""
    second = lambda c: F.unix_timestamp(F.col(c).cast("timestamp"))
    micros = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    a = left.select(*by, F.col(keep).alias("a"), micros(at).alias("ta"), F.floor(second(at) / slack).alias("_bucket"))
    b = right.select(*by, F.col(keep).alias("b"), micros(at).alias("tb"), F.explode(F.transform(F.array(*map(F.lit, (-1, 0, 1))), lambda d: F.floor(second(at) / slack) + d)).alias("_bucket"))
    return a.join(b, [*by, "_bucket"]).where(F.abs(F.col("ta") - F.col("tb")) <= slack * 1_000_000).select(*by, "a", "b", ((F.col("tb") - F.col("ta")) / 1e6).alias("seconds"))


def scored(left: DataFrame, right: DataFrame, cfg) -> DataFrame:
    """(a, b, seconds, score) of events (id, trigger, subject, object, at) of one subject that are at most the slack apart."""
    form = lambda x: x.select(F.col("id"), "trigger", "subject", F.array_compact(F.array("subject", "object")).alias("args"), "at")
    x, y = form(left), form(right)
    near = within(x, y, ["subject"], "at", cfg.event_time_slack_seconds).where("a <> b")
    side = lambda d, c: d.select(F.col("id").alias(c), F.col("trigger").alias(f"t{c}"), F.col("args").alias(f"g{c}"))
    both = near.join(side(x, "a"), "a").join(side(y, "b"), "b")
    return both.select("a", "b", "seconds", similarity("ta", "tb", "ga", "gb", F.col("seconds"), cfg.event_time_slack_seconds).alias("score"))


def doubles(events: DataFrame, cfg) -> DataFrame:
    """(id, of): events of a batch that tell an earlier one's again: groups of pairs that are similar enough and told for one
    instant with the same trigger and arguments (a score of 1), under their least id."""
    same = scored(events, events, cfg).where((F.col("a") < F.col("b")) & (F.col("score") >= cfg.event_sim_min) & (F.col("score") == 1.0) & (F.col("seconds") == 0))
    groups = components(same)
    return groups.where("node <> label").select(F.col("node").alias("id"), F.col("label").alias("of"))


def clustered(events: DataFrame, cfg) -> DataFrame:
    """(id, cluster): events of a batch grouped by pairs that are similar enough; candidates for one happening."""
    pairs = scored(events, events, cfg).where((F.col("a") < F.col("b")) & (F.col("score") >= cfg.event_sim_min))
    return events.select("id").join(components(pairs), F.col("id") == F.col("node"), "left").select("id", F.coalesce("label", "id").alias("cluster"))


def matches(batch: DataFrame, index: DataFrame, cfg) -> DataFrame:
    """(id, match, score, aligned): for every event of a batch the best event of the index, by score, then nearness, then id; aligned if the
    score is high enough and trigger, arguments and time agree."""
    pairs = scored(batch, index, cfg).where(F.col("score") >= cfg.event_sim_min)
    best = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("score"), F.abs("seconds"), "b"))
    return pairs.withColumn("r", best).where("r = 1").select(F.col("a").alias("id"), F.col("b").alias("match"), "score", ((F.col("score") == 1.0) & (F.col("seconds") == 0)).alias("aligned"))
