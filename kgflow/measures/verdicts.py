"""Judges of additions and deprecations as decision points. They read gold facts and statements, and share no code with the gates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgflow.judge.base import DecisionPoint

FACT = ["head", "relation", "tail"]


def support(additions: DataFrame, gold: DataFrame, statements: DataFrame, wording: Column | None = None, replay: DataFrame | None = None) -> DataFrame:
    """additions (head, relation, tail, batch_id, stmt_id) with request and verdict. gold: (head, relation, tail, batch_id), statements: (stmt_id, text).

    Fully supported: gold has the fact in its window and the statement holds both names. Partially: gold has it in other windows only,
    or the statement holds one name of two. wording: how the tail stands in a text, where that is not its name."""
    here = gold.select(*FACT, "batch_id").distinct().withColumn("in_window", F.lit(True))
    ever = gold.select(*FACT).distinct().withColumn("in_gold", F.lit(True))
    rows = additions.join(here, [*FACT, "batch_id"], "left").join(ever, FACT, "left").join(statements.select("stmt_id", "text"), "stmt_id", "left")
    told = lambda name: F.coalesce(F.contains("text", name), F.lit(False)).cast("int")
    rows = rows.withColumn("names", told(F.col("head")) + told(F.col("tail") if wording is None else wording)).fillna(False, ["in_window", "in_gold"])
    full = F.col("in_window") & (F.col("names") == 2)
    part = (F.col("in_gold") & ~F.col("in_window")) | (F.col("names") == 1)
    rule = F.when(full, "fully_supported").when(part, "partially_supported").otherwise("not_supported")
    point = DecisionPoint("support", (*FACT, "batch_id", "stmt_id"), rule)
    return point.decide(rows, replay).select(*additions.columns, "request", "verdict")


def deletion(deprecations: DataFrame, about: DataFrame, replay: DataFrame | None = None) -> DataFrame:
    """deprecations (batch_id, stmt_id, by_stmt, ...) with request and verdict. about: (stmt_id, subject), what a statement speaks of in
    gold. Justified: the statement that retired the fact speaks of the subject that the fact came from."""
    mine, other = about.select("stmt_id", F.col("subject").alias("of")), about.select(F.col("stmt_id").alias("by_stmt"), F.col("subject").alias("by"))
    rows = deprecations.join(mine, "stmt_id", "left").join(other, "by_stmt", "left")
    point = DecisionPoint("deletion", ("stmt_id", "by_stmt", "batch_id"), F.when(F.col("of") == F.col("by"), "justified").otherwise("unjustified"))
    return point.decide(rows, replay).select(*deprecations.columns, "request", "verdict")
