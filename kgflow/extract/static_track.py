"""Static track: triples out of plain statements by a table of patterns, in one projection."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Phrase between two names and the relation name that it suggests; longer phrases first.
PHRASES = (
    (" was placed by ", "was_placed_by"),
    (" placed by ", "placed_by"),
    (" placed ", "placed"),
    (" has status ", "has_status"),
    (" with status ", "with_status"),
    (" has priority ", "has_priority"),
    (" is of priority ", "is_of_priority"),
    (" is based in ", "is_based_in"),
    (" based in ", "based_in"),
    (" in region ", "in_region"),
    (" contains ", "contains"),
    (" has brand ", "has_brand"),
    (" in segment ", "in_segment"),
)
NEGATED = r"(?i)\b(is|was|has|does|did|are|were) +(not|never|no longer)\b"


def triples(stmts: DataFrame) -> DataFrame:
    """Rows of stmts with h_name, phrase and t_name as the text has them; negated statements give none."""
    at = F.coalesce(*(F.when(F.contains(F.col("text"), F.lit(p)), F.lit(i)) for i, (p, _) in enumerate(PHRASES)))
    of = lambda j: F.get(F.array(*(F.lit(x[j]) for x in PHRASES)), F.col("_at"))
    no = F.lower("text")
    negated = (F.contains(no, F.lit(" no")) | F.contains(no, F.lit(" never"))) & F.col("text").rlike(NEGATED)  # the pattern only where one of its words may stand
    found = stmts.where(~negated).withColumn("_at", at).where("_at is not null").withColumn("phrase", of(1)).withColumn("_b", of(0)).drop("_at")
    after = found.withColumn("h_name", F.expr("substring_index(text, _b, 1)")).withColumn("_t", F.expr("substr(text, instr(text, _b) + length(_b))"))
    return after.withColumn("t_name", F.when(F.endswith("_t", F.lit(".")), F.expr("left(_t, length(_t) - 1)")).otherwise(F.regexp_replace("_t", r"\.$", ""))).drop("_b", "_t")
