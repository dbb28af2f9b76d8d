"""Evidence gate: a candidate is rejected only if its own evidence contradicts it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


#: What a candidate's own statement says, beside the candidate while an extractor works on it.
TOLD = ("stmt_id", "head", "relation", "tail")


def as_said() -> Column:
    """Whether a candidate still is what its statement says; nothing that the statement says can contradict it then."""
    return F.struct(*TOLD).eqNullSafe(F.col("told"))


def verify(cands: DataFrame, asserted: DataFrame, functional: tuple[str, ...] | None) -> DataFrame:
    """cands (stmt_id, head, relation, tail) with verdict. asserted: what the statements say themselves, in
    the same columns. A different value for the same head and functional relation contradicts; a statement
    that says nothing on the matter does not. functional None: a statement that pairs one end with something else
    under the relation contradicts, whichever end that is."""
    rows = asserted if functional is None else asserted.where(F.col("relation").isin(*functional))
    said = rows.groupBy("stmt_id").agg(F.collect_set(F.struct("head", "relation", "tail")).alias("_said"))  # one look at each statement, whatever is asked of it
    against = F.lit(False)
    for end, other in (("head", "tail"), ("tail", "head"))[: 2 if functional is None else 1]:
        told = F.filter("_said", lambda s: F.coalesce((s[end] == F.col(end)) & (s["relation"] == F.col("relation")), F.lit(False)))  # noqa: B023
        agreed = F.exists(told, lambda s: F.coalesce(s[other] == F.col(other), F.lit(False)))  # noqa: B023
        against = against | F.coalesce((F.size(told) > 0) & F.col(other).isNotNull() & ~agreed, F.lit(False))
    return cands.join(said, "stmt_id", "left").withColumn("verdict", F.when(against, "REJECTED").otherwise("ACCEPTED")).drop("_said")
