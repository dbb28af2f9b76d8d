"""Retrieval of the K schemas nearest to a statement, and their use as constraints."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgflow.evolve.relation_schema import stem
from kgflow.functions.text import dot, hashed_ngrams
from kgflow.session import settled, ship


#: Rows of either side that meet in one task: a matrix product of this size, in pieces of PIECE scores. Every block of one side is sent once for each of the other's.
BLOCK, PIECE = 32768, 1 << 22
#: A pair that is met in a bucket, made distinct and joined with its vectors costs as much as so many that are multiplied in blocks, or more.
PAIR = 256


def best_of_blocks(k: int):
    """k nearest of every left row among the right rows of a block, by one matrix product."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        if left.num_rows and right.num_rows:
            a, b = np.asarray(left.column("a")), np.asarray(right.column("b"))
            x, y = (np.asarray(t.column("vec").combine_chunks().flatten()).reshape(t.num_rows, -1).astype(np.float64) for t in (left, right))
            order = np.argsort(b, kind="stable")
            b, y = b[order], y[order]
            size = max(1, min(512, PIECE // len(b)))
            for lo in range(0, len(a), size):
                raw = x[lo : lo + size] @ y.T
                score = np.sign(raw) * np.floor(np.abs(raw) * 1e6 + 0.5) / 1e6
                score[(a[lo : lo + size, None] == b[None]) | ~np.isfinite(score)] = -np.inf
                least = np.partition(score, -k, axis=1)[:, -k, None] if k < len(b) else -np.inf
                r, c = np.nonzero((score >= least) & (score > -np.inf))
                order = np.lexsort((c, -score[r, c], r))  # ties to the smaller id, as b is sorted
                r, c = r[order], c[order]
                kept = np.arange(len(r)) - np.searchsorted(r, r) < k
                r, c = r[kept], c[kept]
                rows.append((a[lo + r], b[c], score[r, c]))
        cols = [np.concatenate(c) for c in zip(*rows, strict=True)] if rows else [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        return pa.table([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.float64())], ["a", "b", "score"])

    return run


def topk_exact(left: DataFrame, right: DataFrame, k: int = 30, left_id="id", right_id="id", vec="vec", block: int = BLOCK) -> DataFrame:
    """(a, b, score, rank): the k nearest of every left row by dot product rounded to 6 digits, ties to the smaller id, the
    row itself left out. Ids are bigints.

    Both sides are cut into blocks of about the same number of rows, whatever the size of the table; every pair of blocks
    is one matrix product that keeps k per left row, so what is merged is left x right blocks x k."""
    ship(left.sparkSession)
    a = left.select(F.col(left_id).cast("long").alias("a"), F.col(vec).alias("vec")).where("vec is not null")
    b = right.select(F.col(right_id).cast("long").alias("b"), F.col(vec).alias("vec")).where("vec is not null")
    n, m = (max(1, -(-x.count() // block)) for x in (a, b))
    cut = lambda c, parts: F.pmod(F.xxhash64(c), F.lit(parts)).cast("int")
    a = a.withColumn("i", cut("a", n)).withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(m - 1))))
    b = b.withColumn("j", cut("b", m)).withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    found = a.groupBy("i", "j").cogroup(b.groupBy("i", "j")).applyInArrow(best_of_blocks(k), "a long, b long, score double")
    return ranked(found, k)


def ranked(scored: DataFrame, k: int) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("score"), "b"))
    return scored.withColumn("rank", rank).where(F.col("rank") <= k).select("a", "b", "score", "rank")


def planes(dim: int, bits: int, table: int) -> list[list[float]]:
    """Hyperplanes of a table, from a fixed rule."""
    return np.random.default_rng(97 + table).standard_normal((bits, dim)).round(4).tolist()


def signs(df: DataFrame, name: str, dim: int, tables: int, bits: int) -> DataFrame:
    """(name, key): a row's bucket in every table."""
    stacked = np.concatenate([np.array(planes(dim, bits, t)) for t in range(tables)])
    weight = (1 << np.arange(bits)).astype(np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x = np.asarray(b.column(1).flatten()).reshape(b.num_rows, -1)
                side = (x @ stacked.T >= 0).reshape(len(x), tables, bits) @ weight
                key = side + (np.arange(tables, dtype=np.int64) << bits)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.asarray(b.column(0)), tables)), pa.array(key.reshape(-1))], [name, "key"])

    return df.select(name, "vec").mapInArrow(run, f"{name} long, key long")


def topk_lsh(left: DataFrame, right: DataFrame, k: int = 30, dim: int = 64, tables: int = 24, recall: float = 0.9, left_id="id", right_id="id", vec="vec") -> DataFrame:
    """As topk_exact(), over pairs that share the signs of some table's hyperplanes.

    Buckets are as small as the table asks for, as long as a sample of the left rows, also searched exactly, finds this
    share of its true nearest; below that a bit is taken away. Where the buckets hold so many pairs that to multiply everything is cheaper, or no
    bits are left, the search is exact. Left rows that get fewer than k are searched exactly. Pairs are made distinct as ids, before their vectors are joined."""
    ship(left.sparkSession)
    a = left.select(F.col(left_id).cast("long").alias("a"), F.col(vec).alias("vec")).where("vec is not null")
    b = right.select(F.col(right_id).cast("long").alias("b"), F.col(vec).alias("vec")).where("vec is not null")
    m = b.count()
    every, bits = a.count() * m, max(4, int(math.log2(max(m, 2))) - 7)

    def met() -> int:
        """Pairs that the buckets hold, from their sizes."""
        sizes = lambda d, c: signs(d, c, dim, tables, bits).groupBy("key").agg(F.count("*").alias(f"n{c}"))
        return sizes(a, "a").join(sizes(b, "b"), "key").agg(F.coalesce(F.sum(F.col("na") * F.col("nb")), F.lit(0))).first()[0]

    if met() * PAIR >= every:  # and fewer bits hold more
        return topk_exact(a, b, k, "a", "b")
    some = settled(a.orderBy(F.xxhash64("a"), "a").limit(SAMPLED))
    sure = settled(topk_exact(some, b, k, "a", "b").select("a", "b"))
    due = sure.count()

    def near(rows: DataFrame) -> DataFrame:
        pairs = signs(rows, "a", dim, tables, bits).join(signs(b, "b", dim, tables, bits), "key").where("a <> b").select("a", "b").distinct()
        scored = pairs.join(rows.withColumnRenamed("vec", "va"), "a").join(b.withColumnRenamed("vec", "vb"), "b").select("a", "b", F.round(dot("va", "vb"), 6).alias("score"))
        return ranked(scored, k)

    while bits and near(some).join(sure, ["a", "b"], "left_semi").count() < recall * due:
        bits -= 1
        if bits and met() * PAIR >= every:
            bits = 0
    if not bits:
        return topk_exact(a, b, k, "a", "b")
    found = settled(near(a))
    full = found.where(F.col("rank") == k).select("a")
    rest = topk_exact(a.join(full, "a", "left_anti"), b, k, "a", "b")
    return found.join(full, "a", "left_semi").unionByName(rest)


#: Left rows of which the recall of the buckets is measured.
SAMPLED = 64


def retrieve(names: DataFrame, schemas: DataFrame, k: int = 30) -> DataFrame:
    """(phrase, alias, score, rank): the k registered aliases nearest to each distinct name (phrase), by the cosine of their
    vectors; an equal name comes first. Both sides are vocabularies of relation names, not rows of a batch."""
    vec = lambda c: hashed_ngrams(stem(c))
    a, b = settled(names.select("phrase", vec("phrase").alias("va"))), settled(schemas.select("alias", vec("alias").alias("vb")))
    score = F.when(F.col("phrase") == F.col("alias"), 1.0).otherwise(F.least(F.round(dot("va", "vb"), 6), F.lit(0.999999)))
    rank = F.row_number().over(Window.partitionBy("phrase").orderBy(F.desc("score"), "alias"))
    return a.join(b).withColumn("score", score).withColumn("rank", rank).where(F.col("rank") <= k).select("phrase", "alias", "score", "rank")


def constrain(cands: DataFrame, schemas: DataFrame) -> DataFrame:
    """Candidates (h, phrase, t) under the canonical relation of their schema, heads and tails swapped
    where the schema's alias is its inverse; unseen names pass untouched. schemas: (alias, relation, swapped)."""
    known = cands.join(F.broadcast(schemas.select(F.col("alias").alias("phrase"), "relation", "swapped")), "phrase", "left")
    swap = F.coalesce("swapped", F.lit(False))
    return known.withColumn("relation", F.coalesce("relation", "phrase")).withColumn("head", F.when(swap, F.col("t")).otherwise(F.col("h"))).withColumn("tail", F.when(swap, F.col("h")).otherwise(F.col("t"))).withColumn("unseen", F.col("swapped").isNull())


def budget(retrieved: DataFrame, by: str, text: str, order: str, most: int) -> DataFrame:
    """Retrieved rows whose texts, in order, fit into so many characters per statement."""
    used = F.sum(F.length(text)).over(Window.partitionBy(by).orderBy(order).rowsBetween(Window.unboundedPreceding, 0))
    return retrieved.withColumn("_used", used).where(F.col("_used") <= most).drop("_used")
