"""Merkle fixity audit of archived records.

Records of both replicas share a layout: they are matched by id and, among records of one id, by
rank, and numbered in the order of ids; a missing record leaves an empty slot, so it shifts no
others. A leaf is the hash of a record with its header. A node hashes its children in order, each
with its digest and its length: the lengths in order are the ranges of offsets relative to the
node. So a record that changes, or grows, changes one path of nodes to the root and nothing
beside it. Nodes of level ``FILE_LEVEL`` are the files; a record's offset counts from its file's start.

Two replicas are compared from the root down: only the children of nodes that differ are read on
the next level, and the differing leaves are the damage. All levels are written to the shared folder
as they are built; they shrink by the fanout. Only the leaves touch contents.

Nothing is grouped by id or file alone: numbers come from a range sort and per-partition counts, and
nodes have at most ``fanout`` children, so a null id or a repeated one that a third of all records has
is spread like any other.

Edge cases: null ids and contents are hashed as marked nulls; records with equal ids are paired in the
order of their digests; records that only one replica has are reported as missing or extra; two
empty replicas agree; columns beside those named are ignored, and names match in any case.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgflow.llm.frames import by_position, column
from kgflow.session import settled

FANOUT, FILE_LEVEL = 16, 2


def record(fields: list[Column]) -> Column:
    """The bytes of a record: each field with its length, null apart from empty."""
    parts = []
    for text in fields:
        parts.append(F.when(text.isNull(), F.lit("-\n")).otherwise(F.concat(F.octet_length(text).cast("string"), F.lit("\n"), text)))
    return F.concat(F.lit("WARC/1.1\n"), *parts)


def numbered(rows: DataFrame, order: list[str], out: str) -> DataFrame:
    """rows, written once, with their number in this order, from 0. Sorted by range; the driver gets one count
    per partition. Rows that are equal in the order are told apart by where they were read."""
    src = rows.withColumn("_read", F.monotonically_increasing_id())
    sorted_ = src.repartitionByRange(*order, "_read").sortWithinPartitions(*order, "_read").drop("_read")
    placed = settled(sorted_.withColumn("_at", F.monotonically_increasing_id()))
    part = F.shiftright("_at", 33)
    counts = sorted((r["p"], r["n"]) for r in placed.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect())
    before, total = [], 0
    for p, n in counts:
        before.append((p, total))
        total += n
    starts = rows.sparkSession.createDataFrame(before, "_p long, _before long")  # one row per partition
    joined = placed.join(F.broadcast(starts), part == F.col("_p"))
    return joined.withColumn(out, F.col("_before") + F.col("_at").bitwiseAND((1 << 33) - 1)).drop("_at", "_p", "_before")


def leaves(records: DataFrame, id_col: str, columns: list[str]) -> DataFrame:
    """(key, copy, id, digest, length): key is the id as text, null apart from empty; copy tells the records of one id apart."""
    names = [column(records, c).cast("string") for c in (id_col, *columns)]
    body = record(names)
    hashed = settled(by_position(records).select(names[0].alias("id"), F.sha2(body, 256).alias("digest"), F.octet_length(body).cast("long").alias("length")).withColumn("key", F.coalesce(F.concat(F.lit("="), "id"), F.lit("-"))))
    repeated = hashed.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key")
    ones = hashed.join(repeated, "key", "left_anti").withColumn("copy", F.lit(0).cast("long"))
    many = settled(numbered(hashed.join(repeated, "key", "left_semi"), ["key", "digest"], "at"))
    first = many.groupBy("key").agg(F.min("at").alias("first"))
    ranked = many.join(first, "key").withColumn("copy", F.col("at") - F.col("first")).drop("at", "first")
    return ones.unionByName(ranked).select("key", "copy", "id", "digest", "length")


def layout(own: DataFrame, other: DataFrame) -> DataFrame:
    """(slot, id, and digest and length of either replica): the leaves of both in the common order."""
    side = lambda x, p: x.select("key", "copy", F.col("id").alias(f"{p}_id"), F.col("digest").alias(f"{p}_digest"), F.col("length").alias(f"{p}_length"))
    both = side(own, "a").join(side(other, "b"), ["key", "copy"], "full_outer").withColumn("id", F.coalesce("a_id", "b_id")).drop("a_id", "b_id")
    return settled(numbered(both, ["key", "copy"], "slot").drop("key", "copy"))


def parents(nodes: DataFrame, fanout: int) -> DataFrame:
    """Nodes (node, and digest and length of either replica) one level up; a replica without children has none."""
    kids = F.array_sort(F.collect_list(F.struct("node", "a_digest", "a_length", "b_digest", "b_length")))

    def hashed(p: str) -> Column:
        there = F.filter("kids", lambda k: k[f"{p}_digest"].isNotNull())
        line = F.array_join(F.transform(there, lambda k: F.concat_ws(":", k[f"{p}_length"].cast("string"), k[f"{p}_digest"])), ";")
        return F.when(F.size(there) > 0, F.sha2(line, 256)).alias(f"{p}_digest")

    up = nodes.groupBy(F.floor(F.col("node") / fanout).alias("node")).agg(kids.alias("kids"), F.sum("a_length").alias("a_length"), F.sum("b_length").alias("b_length"))
    return up.select("node", hashed("a"), "a_length", hashed("b"), "b_length")


@dataclass
class Trees:
    """Levels of the trees of both replicas, leaves first, the root last; each level is stored."""

    levels: list[DataFrame]
    fanout: int

    def damaged(self) -> tuple[DataFrame, list[int]]:
        """(node) of the leaves that differ, and how many nodes were read per level, root first."""
        bad, read = None, []
        for level in reversed(self.levels):
            if bad is not None:
                level = level.withColumn("up", F.floor(F.col("node") / self.fanout)).join(bad.withColumnRenamed("node", "up"), "up", "left_semi").drop("up")
            seen = settled(level.select("node", F.col("a_digest").eqNullSafe(F.col("b_digest")).alias("same")))
            n, differ = seen.agg(F.count("*"), F.count_if(~F.col("same"))).first()
            bad = seen.where("not same").select("node")
            read.append(n)
            if not differ:
                break
        return bad, read


def trees(slots: DataFrame, fanout: int = FANOUT) -> Trees:
    levels = [slots.select(F.col("slot").alias("node"), "a_digest", "a_length", "b_digest", "b_length")]
    widest = slots.agg(F.max("slot")).first()[0] or 0
    while widest or len(levels) == 1:
        levels.append(settled(parents(levels[-1], fanout)))
        widest //= fanout
    return Trees(levels, fanout)


def offsets(slots: DataFrame, p: str, fanout: int, file_level: int) -> Column:
    """Where a record starts in its file: a window over one file's slots, at most fanout ** file_level of them."""
    from pyspark.sql import Window

    before = Window.partitionBy(F.floor(F.col("slot") / fanout**file_level)).orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    return F.coalesce(F.sum(f"{p}_length").over(before), F.lit(0))


def audit(manifest: DataFrame, replica: DataFrame, id_col: str, columns: list[str], fanout: int = FANOUT, file_level: int = FILE_LEVEL) -> DataFrame:
    """(id, file, start, length, expected, found, status) for every record of either replica;
    status: intact, corrupt, missing or extra. start and length are the manifest's, or the replica's where only it has the record."""
    slots = layout(*(leaves(x, id_col, columns) for x in (manifest, replica)))
    bad, _ = trees(slots, fanout).damaged()
    marked = slots.withColumn("a_start", offsets(slots, "a", fanout, file_level)).withColumn("b_start", offsets(slots, "b", fanout, file_level)).join(bad.select(F.col("node").alias("slot"), F.lit(True).alias("bad")), "slot", "left")
    status = F.when(F.col("bad").isNull(), "intact").when(F.col("a_digest").isNull(), "extra").when(F.col("b_digest").isNull(), "missing").otherwise("corrupt")
    there = F.col("a_digest").isNotNull()
    return marked.select(
        "id", F.floor(F.col("slot") / fanout**file_level).alias("file"), F.when(there, F.col("a_start")).otherwise(F.col("b_start")).alias("start"),
        F.when(there, F.col("a_length")).otherwise(F.col("b_length")).alias("length"), F.col("a_digest").alias("expected"),
        # the digests of intact subtrees are the manifest's; they are not compared one by one
        F.when(F.col("bad").isNull(), F.col("a_digest")).otherwise(F.col("b_digest")).alias("found"), status.alias("status"),
    )
