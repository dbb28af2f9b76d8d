"""Reads of a graph given as edges (head, tail)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgflow.coref.cluster import components
from kgflow.session import settled

__all__ = ["components", "degree", "hop", "paths2", "reach", "triangles"]


def hop(edges: DataFrame, seeds: DataFrame) -> DataFrame:
    """(node) one edge away from the seeds (node)."""
    return edges.join(seeds.select(F.col("node").alias("head")).distinct(), "head", "left_semi").select(F.col("tail").alias("node")).distinct()


def paths2(edges: DataFrame) -> DataFrame:
    """(a, b, c) over two different edges a-b, b-c."""
    e = edges.select("head", "tail").distinct()
    return e.alias("x").join(e.alias("y"), F.col("x.tail") == F.col("y.head")).select(F.col("x.head").alias("a"), F.col("x.tail").alias("b"), F.col("y.tail").alias("c"))


def reach(edges: DataFrame, seeds: DataFrame, max_hops: int) -> DataFrame:
    """(node, hops) reachable within max_hops; only the frontier is joined."""
    e = edges.select("head", "tail").distinct()
    front = seeds.select("node").distinct().withColumn("hops", F.lit(0))
    seen = front
    for k in range(1, max_hops + 1):
        nxt = e.join(front.select(F.col("node").alias("head")), "head", "left_semi").select(F.col("tail").alias("node")).distinct()
        front = settled(nxt.join(seen, "node", "left_anti").withColumn("hops", F.lit(k)))
        seen = seen.unionByName(front)
    return seen


def degree(edges: DataFrame) -> DataFrame:
    rows = edges.select(F.explode(F.array(F.struct(F.col("head").alias("node"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("tail").alias("node"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("x"))
    return rows.groupBy("x.node").agg(F.sum("x.o").alias("out_degree"), F.sum("x.i").alias("in_degree"))


def triangles(edges: DataFrame) -> DataFrame:
    """(a, b, c) of undirected triangles, each once. Edges are turned from the lower to the higher degree,
    which bounds the wedges at a hub."""
    und = edges.where("head <> tail").select(F.least("head", "tail").alias("u"), F.greatest("head", "tail").alias("v")).distinct()
    deg = und.select(F.explode(F.array("u", "v")).alias("n")).groupBy("n").agg(F.count("*").alias("d"))
    w = und.join(deg.select(F.col("n").alias("u"), F.col("d").alias("du")), "u").join(deg.select(F.col("n").alias("v"), F.col("d").alias("dv")), "v")
    up = F.struct("du", "u") < F.struct("dv", "v")
    o = w.select(F.when(up, F.col("u")).otherwise(F.col("v")).alias("x"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("y"))
    wedge = o.alias("p").join(o.alias("q"), F.col("p.x") == F.col("q.x")).where("p.y < q.y").select(F.col("p.x").alias("a"), F.col("p.y").alias("b"), F.col("q.y").alias("c"))
    closed = wedge.join(und.select(F.col("u").alias("b"), F.col("v").alias("c")), ["b", "c"], "left_semi")
    return closed.select(F.array_sort(F.array("a", "b", "c")).alias("t")).select(F.col("t")[0].alias("a"), F.col("t")[1].alias("b"), F.col("t")[2].alias("c"))
