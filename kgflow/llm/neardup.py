"""Near-duplicate documents: MinHash with tensored banding, and exact confirmation.

Two small collections of ``m`` half keys per document, each of ``HALF`` minhashes, are combined
to m * m table keys: the minhashes computed grow with the square root of what as many
independent tables would take. m follows from the threshold t and the share of links that may
be missed at exactly t: a pair with similarity J shares a key with probability
(1 - (1 - J**HALF)**m)**2.

1. Texts are reduced to marks: size and 128-bit digest of the shingle set, the half keys, and
   the parities of the shingles over 1024 places. The parities of two sets differ in no more
   places than their symmetric difference has shingles, so pairs that differ in more than the
   threshold allows are dropped without error.
2. Equal sets form classes, represented by their least id.
3. In every table group, members are paired with the least member only (first_occurrences);
   surviving pairs are confirmed on full sets; confirmed links give components.
4. Groups that still hold several components are compared in full between components, in blocks
   of bounded size, by the parities, in the task; only survivors leave it, and are confirmed.
   So no link between members of a group is lost, and no group is expanded to rows.

Edge cases: null or empty texts have an empty set and are linked with nothing; texts with fewer
than five words are one shingle; null ids stand alone; repeated rows fall into one class.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgflow.coref.cluster import components
from kgflow.llm.frames import id_and_text
from kgflow.llm import packs, words
from kgflow.llm.words import U, mix
from kgflow.session import settled, width

SHINGLE, HALF, PLACES = 5, 2, 1024
#: Share of links at exactly the threshold that banding may miss.
MISS = 1e-4
#: Members of a group that are compared in one block.
BLOCK = 2048
MARKS = "id long, n_shingles long, s1 long, s2 long, halves binary, parity binary"


def half_keys(threshold: float, miss: float = MISS) -> int:
    """Size m of either collection."""
    return math.ceil(math.log(miss / 2) / math.log(1 - threshold**HALF))


def multipliers(n: int) -> np.ndarray:
    return np.random.default_rng(5051).integers(1, 2**63, n, dtype=np.uint64) | U(1)


def shingle_sets(col: pa.Array) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of every text."""
    for c in words.chunks(col, lower=True):
        h = c.hashes()
        key, own, _ = words.windows(c, SHINGLE, h)
        cuts = np.searchsorted(own, np.arange(c.hi - c.lo + 1))
        for i in range(c.hi - c.lo):
            n = int(c.first[i + 1] - c.first[i])
            if n >= SHINGLE:
                yield np.unique(key[cuts[i] : cuts[i + 1]])
            elif n:
                yield words.window_hashes(h[c.first[i] : c.first[i + 1]], n) ^ U(n)
            else:
                yield np.zeros(0, np.uint64)


def marks(docs: DataFrame, threshold: float, id_col: str, text_col: str) -> DataFrame:
    m = half_keys(threshold)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by = multipliers(2 * m * HALF)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1024):
                b = batch.slice(lo, 1024)
                sets = list(shingle_sets(b.column(1)))
                sizes = np.array([len(s) for s in sets])
                full = np.flatnonzero(sizes)
                halves: list[bytes | None] = [None] * len(sets)
                sums = np.zeros((2, len(sets)), np.int64)
                if len(full):
                    flat = np.concatenate([sets[i] for i in full])
                    at = np.concatenate(([0], np.cumsum(sizes[full])[:-1]))
                    least = np.stack([np.minimum.reduceat(flat * a, at) for a in by]).reshape(2 * m, HALF, len(full))
                    key = np.zeros((2 * m, len(full)), np.uint64)
                    for j in range(HALF):
                        key = mix(key * words.WORD_BASE + least[:, j] + U(1))
                    key = np.ascontiguousarray(key.T)
                    for r, i in enumerate(full):
                        halves[i] = key[r].tobytes()
                    sums[0, full] = np.add.reduceat(mix(flat ^ words.MIX_A), at).view(np.int64)
                    sums[1, full] = np.add.reduceat(mix(flat ^ words.MIX_B), at).view(np.int64)
                parity = [np.packbits((np.bincount((s & U(PLACES - 1)).astype(np.int64), minlength=PLACES) & 1).astype(np.uint8)).tobytes() if len(s) else None for s in sets]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sizes, pa.int64()), pa.array(sums[0]), pa.array(sums[1]), pa.array(halves, pa.binary()), pa.array(parity, pa.binary())], ["id", "n_shingles", "s1", "s2", "halves", "parity"])

    return id_and_text(docs, id_col, text_col).mapInArrow(run, MARKS)


def table_keys(halves: pa.Array) -> np.ndarray:
    """(rows, m * m) table keys."""
    h = np.frombuffer(b"".join(halves.to_pylist()), np.uint64).reshape(len(halves), -1)
    m = h.shape[1] // 2
    pairs = h[:, :m, None] * words.BYTE_BASE + h[:, None, m:]
    return mix(pairs.reshape(len(h), m * m) + np.arange(m * m, dtype=np.uint64) * words.MIX_B)


def band_items(batches: Iterator[pa.RecordBatch]) -> packs.Items:
    """Items (table key, id) of batches (id, halves)."""
    for batch in batches:
        for lo in range(0, batch.num_rows, 4096):
            b = batch.slice(lo, 4096)
            key = table_keys(b.column(1))
            doc = np.repeat(np.asarray(b.column(0)).astype(np.int64), key.shape[1])
            yield key.reshape(-1), doc, np.zeros(len(doc), np.int64)


def hit_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        if b.num_rows:
            doc, _, src, _, _ = packs.hits_of(b.column(2).to_pylist())
            pair = np.unique(np.stack([src, doc], 1), axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(pair[:, 0]), pa.array(pair[:, 1])], ["a", "b"])


def may_link(na: np.ndarray, nb: np.ndarray, differ: np.ndarray, percent: int) -> np.ndarray:
    """Whether sets of these sizes that differ in at least so many shingles can reach the threshold."""
    common = (na + nb - differ) // 2
    return (100 * common >= percent * (na + nb - common)) & (100 * np.minimum(na, nb) >= percent * np.maximum(na, nb))


def parities(col: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(col.to_pylist()), np.uint64).reshape(len(col), PLACES // 64)


def plausible(pairs: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) that their sizes and parities don't rule out."""
    side = lambda x: classes.select(F.col("id").alias(x), F.col("n_shingles").alias(f"n{x}"), F.col("parity").alias(f"p{x}"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                differ = np.bitwise_count(parities(b.column(4)) ^ parities(b.column(5))).sum(1).astype(np.int64)
                ok = may_link(np.asarray(b.column(2)), np.asarray(b.column(3)), differ, percent)
                yield b.select([0, 1]).filter(pa.array(ok))

    return pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "na", "nb", "pa", "pb").mapInArrow(run, "a long, b long")


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) that meet the threshold on full sets."""
    side = lambda x: sets.select(F.col("id").alias(x), F.col("shingles").alias(f"s{x}"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = []
            for x, y in zip(b.column(2), b.column(3), strict=True):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                z = np.sort(np.concatenate((x, y)), kind="stable")
                common = int((z[1:] == z[:-1]).sum())
                ok.append(100 * common >= percent * (len(x) + len(y) - common))
            yield b.select([0, 1]).filter(pa.array(ok, pa.bool_()))

    return pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long")


def full_sets(docs: DataFrame, wanted: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, shingles) of the documents whose id is wanted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                b = batch.slice(lo, 256)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([s.tobytes() for s in shingle_sets(b.column(1))], pa.binary())], ["id", "shingles"])

    src = id_and_text(docs, id_col, text_col).join(wanted, "id", "left_semi")
    return src.mapInArrow(run, "id long, shingles binary")


def crossing(members: DataFrame, classes: DataFrame, percent: int, tasks: int) -> DataFrame:
    """Plausible pairs between different components of one group; members: (key, t, id, label). Marks
    of the classes are joined once only the rows of mixed groups are left.

    A pair that shares several tables t is given by the first of them only."""
    mixed = members.groupBy("key").agg(F.count("*").alias("size"), F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo < hi").select("key", F.ceil(F.col("size") / BLOCK).cast("int").alias("parts"))
    own = F.pmod(F.xxhash64("id"), F.col("parts")).cast("int")
    dealt = (
        members.join(mixed, "key")
        .join(classes.select("id", "n_shingles", "halves", "parity"), "id")
        .withColumn("own", own)
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
        .select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "t", "id", "label", "n_shingles", "halves", "parity")
    )

    def compare(t: pa.Table) -> pa.RecordBatch:
        key, i, j, own, table, doc, label, n = (np.asarray(t.column(x)) for x in ("key", "i", "j", "own", "t", "id", "label", "n_shingles"))
        bits, half = parities(t.column("parity")), np.frombuffer(b"".join(t.column("halves").to_pylist()), np.uint64).reshape(len(key), -1)
        m = half.shape[1] // 2
        out, d = [], 1
        at = np.arange(len(key) - 1)
        while len(at):
            at = at[at + d < len(key)]
            at = at[(key[at] == key[at + d]) & (i[at] == i[at + d]) & (j[at] == j[at + d])]
            # a block pair i < j compares only across; the blocks i, i compare inside
            x = at[(label[at] != label[at + d]) & ((own[at] != own[at + d]) | (i[at] == j[at]))]
            if len(x):
                differ = np.bitwise_count(bits[x] ^ bits[x + d]).sum(1).astype(np.int64)
                x = x[may_link(n[x], n[x + d], differ, percent)]
                same = half[x] == half[x + d]
                x = x[same[:, :m].argmax(1) * m + same[:, m:].argmax(1) == table[x]]
                out.append(np.stack([np.minimum(doc[x], doc[x + d]), np.maximum(doc[x], doc[x + d])], 1))
            d += 1
        pair = np.unique(np.concatenate(out), axis=0) if out else np.zeros((0, 2), np.int64)
        return pa.RecordBatch.from_arrays([pa.array(pair[:, 0], pa.int64()), pa.array(pair[:, 1], pa.int64())], ["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for b in batches:
            for lo in range(0, b.num_rows, 8192):
                held.append(b.slice(lo, 8192))
                t = pa.Table.from_batches(held).combine_chunks()
                k, i, j = (np.asarray(t.column(x)) for x in ("key", "i", "j"))
                same = (k == k[-1]) & (i == i[-1]) & (j == j[-1])
                done = len(k) - int(same.sum())
                if done >= 4 * 8192 or done and len(k) > 8 * 8192:
                    yield compare(t.slice(0, done).combine_chunks())
                    held = t.slice(done).combine_chunks().to_batches()
        if held:
            yield compare(pa.Table.from_batches(held).combine_chunks())

    return dealt.repartition(tasks, "key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(run, "a long, b long").distinct()


def explode_keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, t, id, label) of batches (id, label, halves), t the number of the table."""
    for batch in batches:
        for lo in range(0, batch.num_rows, 1024):
            b = batch.slice(lo, 1024)
            key = table_keys(b.column(2)).view(np.int64)
            n = key.shape[1]
            yield pa.RecordBatch.from_arrays([pa.array(key.reshape(-1)), pa.array(np.tile(np.arange(n, dtype=np.int32), b.num_rows)), pa.array(np.repeat(np.asarray(b.column(0)), n)), pa.array(np.repeat(np.asarray(b.column(1)), n))], ["key", "t", "id", "label"])


def label_documents(docs: DataFrame, percent: int = 85, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_shingles, component_id, kept) for every row of docs: documents whose shingle sets
    have a Jaccard similarity of at least percent / 100 are linked; kept is the least id of each component."""
    spark = docs.sparkSession
    tasks, buckets, _ = packs.spread(spark)
    seen = settled(marks(docs, percent / 100, id_col, text_col))
    known = seen.where("id is not null and n_shingles > 0")
    classes = settled(known.groupBy("n_shingles", "s1", "s2").agg(F.min("id").alias("id"), F.min_by(F.struct("halves", "parity"), "id").alias("m")).select("id", "n_shingles", "s1", "s2", "m.halves", "m.parity"))
    hits = packs.first_occurrences(classes.select("id", "halves"), band_items, tasks, buckets, tasks)
    stars = settled(hits.mapInArrow(hit_pairs, "a long, b long").distinct())
    near = settled(stars.select(F.col("a").alias("id")).unionByName(stars.select(F.col("b").alias("id"))).distinct())
    sets = settled(full_sets(docs, near, id_col, text_col))
    links = settled(confirmed(plausible(stars, classes, percent), sets, percent))
    first = components(links)
    grouped = classes.join(near, "id").join(first, F.col("id") == F.col("node"), "left").select("id", F.coalesce("label", "id").alias("label"), "halves")
    members = grouped.mapInArrow(explode_keys, "key long, t int, id long, label long")
    more = settled(confirmed(crossing(members, classes, percent, tasks), sets, percent))
    # only labels meet in the last step: links between components, not between documents
    joined = more.join(first.select(F.col("node").alias("a"), F.col("label").alias("la")), "a", "left").join(first.select(F.col("node").alias("b"), F.col("label").alias("lb")), "b", "left")
    upper = components(joined.select(F.coalesce("la", "a").alias("a"), F.coalesce("lb", "b").alias("b")))
    of_class = (
        classes.select("n_shingles", "s1", "s2", "id")
        .join(first.withColumnRenamed("label", "l1"), F.col("id") == F.col("node"), "left").drop("node")
        .withColumn("l1", F.coalesce("l1", "id"))
        .join(upper.withColumnRenamed("label", "l2"), F.col("l1") == F.col("node"), "left")
        .select("n_shingles", "s1", "s2", F.coalesce("l2", "l1").alias("component_id"))
    )
    out = seen.select("id", "n_shingles", "s1", "s2").join(of_class, ["n_shingles", "s1", "s2"], "left")
    alone = F.col("id").isNull() | (F.col("n_shingles") == 0)
    component = F.when(alone, F.col("id")).otherwise(F.col("component_id"))
    return out.select(F.col("id").alias(id_col), "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("id"), F.lit(True)).alias("kept"))


ORACLE = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (
  SELECT doc_id, list_distinct(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')] ELSE list_transform(range(1, len(ws) - 3), lambda p: array_to_string(ws[p:p + 4], ' ')) END) AS sh FROM w),
e AS (SELECT doc_id, len(sh) AS n, unnest(sh) AS x FROM s),
p AS (
  SELECT a.doc_id AS a, b.doc_id AS b FROM e a JOIN e b ON a.x = b.x AND a.doc_id <> b.doc_id
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 85 * (a.n + b.n - count(*))),
r(d, c) AS (SELECT doc_id, doc_id FROM s UNION SELECT r.d, p.b FROM r JOIN p ON r.c = p.a)
SELECT s.doc_id, len(sh)::BIGINT AS n_shingles, min(c)::BIGINT AS component_id, s.doc_id = min(c) AS kept
FROM s JOIN r ON r.d = s.doc_id GROUP BY s.doc_id, sh
"""
