"""Entity profiles, merged from facts and mentions batch by batch."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def from_mentions(mentions: DataFrame) -> DataFrame:
    """(entity, type, aliases, support, first_batch, last_batch) of mentions (entity, type, surface, batch_id)."""
    return mentions.groupBy("entity", "type").agg(F.array_sort(F.collect_set("surface")).alias("aliases"), F.count("*").alias("support"), F.min("batch_id").alias("first_batch"), F.max("batch_id").alias("last_batch"))


def update(profiles: DataFrame, batch: DataFrame) -> DataFrame:
    """Profiles with a batch's profiles merged in; the result does not depend on the order of batches."""
    old, new = (df.select("entity", "type", *(F.col(c).alias(f"{p}_{c}") for c in ("aliases", "support", "first_batch", "last_batch"))) for p, df in (("o", profiles), ("n", batch)))
    none = F.array().cast("array<string>")
    return old.join(new, ["entity", "type"], "full_outer").select(
        "entity", "type", F.array_sort(F.array_union(F.coalesce("o_aliases", none), F.coalesce("n_aliases", none))).alias("aliases"), (F.coalesce("o_support", F.lit(0)) + F.coalesce("n_support", F.lit(0))).alias("support"),
        F.least("o_first_batch", "n_first_batch").alias("first_batch"), F.greatest("o_last_batch", "n_last_batch").alias("last_batch"),
    )
