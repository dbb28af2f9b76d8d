"""Stand-ins for the compared extractors; interpretations, as their internals are not described."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgflow.coref.cluster import components
from kgflow.coref.entities import canonical
from kgflow.extract.static_track import PHRASES
from kgflow.functions.text import cosine, hashed_ngrams


def canonical_names(signed: DataFrame, least: float) -> DataFrame:
    """(alias, relation): phrases whose name vectors are near each other, once over the corpus, under their
    least name; directions are never turned."""
    v = signed.select(F.col("phrase").alias("alias"), hashed_ngrams("phrase").alias("v"))
    near = v.alias("x").join(v.alias("y"), F.col("x.alias") < F.col("y.alias")).where(cosine("x.v", "y.v") >= least)  # distinct phrases only: a vocabulary, not rows
    labels = components(near.select(F.col("x.alias").alias("a"), F.col("y.alias").alias("b")))
    return signed.select(F.col("phrase").alias("alias")).join(labels, F.col("alias") == F.col("node"), "left").select("alias", F.coalesce("label", "alias").alias("relation"))


def define_canonicalise(cands: DataFrame, names: DataFrame) -> DataFrame:
    """Open triples (h, phrase, t) under the gold name of their phrase, head and tail as the text has them."""
    known = cands.join(F.broadcast(names.select(F.col("alias").alias("phrase"), "relation")), "phrase", "left")
    return known.select(F.col("h").alias("head"), F.coalesce("relation", "phrase").alias("relation"), F.col("t").alias("tail"))


def cooccurrence(stmts: DataFrame) -> DataFrame:
    """One relation per statement's first and last name, named by the words between; nothing is denied,
    merged or turned."""
    known = F.array(*(F.lit(p) for p, _ in PHRASES), *(F.lit(p.replace("was ", "was not ")) for p, _ in PHRASES if "was " in p))
    between = F.get(F.filter(known, lambda p: F.contains(F.col("text"), p)), 0)
    out = stmts.withColumn("_b", between).where("_b is not null")
    head = canonical(F.expr("substring_index(text, _b, 1)"))
    tail = canonical(F.regexp_replace(F.expr("substr(text, instr(text, _b) + length(_b))"), r"\.$", ""))
    return out.select(head.alias("head"), F.replace(F.trim("_b"), F.lit(" "), F.lit("_")).alias("relation"), tail.alias("tail"))


def fixed_schema(cands: DataFrame, relations: tuple[str, ...]) -> DataFrame:
    """Only the listed relations; the last statement per head and relation wins."""
    own = cands.where(F.col("phrase").isin(*relations))
    return own.groupBy(F.col("h").alias("head"), F.col("phrase").alias("relation")).agg(F.max_by("t", F.struct("batch_id", "stmt_id")).alias("tail"))
