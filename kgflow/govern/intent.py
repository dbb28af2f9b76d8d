"""Intent check: which events announce that earlier facts no longer hold, and which facts those are."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgflow.extract.event_track import EVOLUTIONARY

GUARD = r"(?i)\b(not|never|may|might|could|would)\b( be)?( later)?"


def intent(text: Column | str = "text", triggers: tuple[str, ...] = EVOLUTIONARY) -> Column:
    """EVOLUTIONARY if a trigger word stands in the text outside denied or hypothetical use."""
    text = F.col(text) if isinstance(text, str) else text
    words = "|".join(triggers)
    plain = F.regexp_replace(text, rf"{GUARD} ({words})\b", "")
    return F.when(plain.rlike(rf"(?i)\b({words})\b"), "EVOLUTIONARY").otherwise("INFORMATIONAL")


def targets(changes: DataFrame, active: DataFrame) -> DataFrame:
    """Active edges that the changes retire: same head and functional relation, another value, not younger than
    the change. Columns: edge, plus by_stmt (evidence) and at (time)."""
    new = changes.select("head", "relation", F.col("tail").alias("_new"), F.col("valid_time").alias("at"), F.col("ord").alias("_ord"), F.col("stmt_id").alias("by_stmt"))
    hit = active.join(new, ["head", "relation"]).where(F.col("tail") != F.col("_new"))
    return hit.where(F.struct("valid_time", "ord") <= F.struct("at", "_ord")).drop("_new", "_ord")
