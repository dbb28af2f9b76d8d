"""Compressed column packs, and the global search for first occurrences built on them.

A pack holds integer columns as byte planes under zstd: sorted keys differ little in their
high planes, which vanish. Shuffling packs instead of rows keeps the JVM's work per pack.

first_occurrences() answers, for items (key, doc, pos): which occurrence of the key is the
least by (doc, pos), and which occurrences are later ones? Work per key is bounded:

- a block (a bounded run of rows of one task) keeps one document per key, the one with the
  least doc, for the global round; occurrences in other documents are settled in the block,
  with the block's least as their source. A key that a third of all rows share thus sends a
  few items per block.
- the least items go to buckets by a hash of their key, as packs.
- a bucket settles them: later ones get the global least as their source.
"""

from __future__ import annotations

import struct
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgflow.llm.words import U, mix, trim
from kgflow.session import width

#: Items in a block; 20 bytes each, and about three times that while it is sorted.
BLOCK = 1 << 20
#: Bits of a key that are sent; the bucket, of other bits, adds its share.
KEY_BITS = U(56)
KEY_MASK = (U(1) << KEY_BITS) - U(1)
#: Seed of the bucket function of keys.
BY_KEY = U(0x51ED270B0D1A3F27)


def pack(*cols: np.ndarray) -> bytes:
    """Columns of equal length, as unsigned 64-bit numbers."""
    n = len(cols[0])
    parts = [struct.pack("<II", n, len(cols))]
    for c in cols:
        c = np.ascontiguousarray(c).view(np.uint64) if c.dtype.itemsize == 8 else c.astype(np.uint64)
        wide = (int(c.max()).bit_length() + 7) // 8 if n else 0
        parts.append(bytes([wide]))
        parts.append(np.ascontiguousarray(c.view(np.uint8).reshape(n, 8)[:, :wide].T).tobytes())
    return zstandard.ZstdCompressor(level=1).compress(b"".join(parts))


def unpack(blob: bytes) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(blob)
    n, k = struct.unpack_from("<II", raw)
    at, out = 8, []
    for _ in range(k):
        wide = raw[at]
        c = np.zeros((n, 8), np.uint8)
        c[:, :wide] = np.frombuffer(raw, np.uint8, n * wide, at + 1).reshape(wide, n).T
        out.append(c.reshape(-1).view(np.uint64))
        at += 1 + n * wide
    return out


def pack_sorted(key: np.ndarray, *cols: np.ndarray) -> bytes:
    """As pack(), the first column ascending and sent as differences."""
    d = key.copy()
    d[1:] -= key[:-1]
    return pack(d, *cols)


def unpack_sorted(blob: bytes) -> list[np.ndarray]:
    first, *rest = unpack(blob)
    return [np.cumsum(first, dtype=np.uint64), *rest]


def dealt(x: np.ndarray, seed: np.uint64, n: int) -> np.ndarray:
    """A bucket of n for every number."""
    return (mix(x.view(np.uint64) ^ seed) % U(n)).astype(np.int64)


def xxhash64(x: np.ndarray) -> np.ndarray:
    """Spark's xxhash64() of a bigint column, so that both sides of a join agree on buckets."""
    p1, p2, p3, p4, p5 = (U(v) for v in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    turn = lambda v, r: (v << U(r)) | (v >> U(64 - r))
    h = (U(42) + p5 + U(8)) ^ (turn(x.astype(np.int64).view(np.uint64) * p2, 31) * p1)
    h = turn(h, 27) * p1 + p4
    h = (h ^ (h >> U(33))) * p2
    h = (h ^ (h >> U(29))) * p3
    return (h ^ (h >> U(32))).view(np.int64)


def repeats(key: np.ndarray, doc: np.ndarray, pos: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of items: (order by key, where the key changes, items of keys that occur again, by key, doc, pos)."""
    order = np.argsort(key)
    k = key[order]
    new = np.ones(len(k), bool)
    new[1:] = k[1:] != k[:-1]
    again = ~new
    again[:-1] |= ~new[1:]
    sub = order[again]
    sub = sub[np.lexsort((pos[sub], doc[sub], key[sub]))]
    return order, new, sub


def heads(key: np.ndarray) -> np.ndarray:
    """Of sorted keys: the index of the first item of each item's run."""
    new = np.ones(len(key), bool)
    new[1:] = key[1:] != key[:-1]
    return np.flatnonzero(new)[np.cumsum(new) - 1]


Items = Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]
SHIPPED = "bucket int, kind int, blob binary"


def send(items: Callable[[Iterator[pa.RecordBatch]], Items], buckets: int, doc_buckets: int) -> Callable:
    """mapInArrow function: packs of least items (kind 0, by key) and of hits settled in the block (kind 1, by doc)."""

    def flush(parts: list) -> Iterator[pa.RecordBatch]:
        key, doc, pos = (np.concatenate(x) for x in zip(*parts, strict=True))
        keep = np.ones(len(key), bool)
        _, _, sub = repeats(key, doc, pos)
        out: list[tuple[int, int, bytes]] = []
        if len(sub):
            least = sub[heads(key[sub])]
            later = sub != least
            # other positions of the least document stay in the global round
            local = later & (doc[sub] != doc[least])
            keep[sub[local]] = False
            out += pack_hits(doc[sub[local]], pos[sub[local]], doc[least[local]], pos[least[local]], key[sub[local]], doc_buckets)
        key, doc, pos = key[keep], doc[keep], pos[keep]
        to = dealt(key, BY_KEY, buckets)
        key = key & KEY_MASK
        order = np.lexsort((key, to)) if buckets > 1 << 16 else np.argsort((to.astype(np.uint64) << U(48)) | (key >> U(8)))
        cuts = np.searchsorted(to[order], np.arange(buckets + 1))
        for b in np.flatnonzero(np.diff(cuts)):
            i = order[cuts[b] : cuts[b + 1]]
            i = i[np.argsort(key[i], kind="stable")]
            out.append((int(b), 0, pack_sorted(key[i], doc[i], pos[i])))
        yield from shipped(out)
        del out, key, doc, pos
        trim()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, n = [], 0
        for part in items(batches):
            if len(part[0]):
                parts.append(part)
                n += len(part[0])
            if n >= BLOCK:
                yield from flush(parts)
                parts, n = [], 0
        if n:
            yield from flush(parts)

    return run


def shipped(rows: list[tuple[int, int, bytes]]) -> Iterator[pa.RecordBatch]:
    for lo in range(0, len(rows), 256):
        b, k, x = zip(*rows[lo : lo + 256], strict=True)
        yield pa.RecordBatch.from_arrays([pa.array(b, pa.int32()), pa.array(k, pa.int32()), pa.array(x, pa.binary())], ["bucket", "kind", "blob"])


def pack_hits(doc, pos, src_doc, src_pos, key, doc_buckets: int) -> list[tuple[int, int, bytes]]:
    to = xxhash64(doc) % doc_buckets
    order = np.lexsort((pos, doc, to))
    cuts = np.searchsorted(to[order], np.arange(doc_buckets + 1))
    tag = key & U(0xFFFF)
    return [(int(b), 1, pack(*(x[i] for x in (doc, pos, src_doc, src_pos, tag)))) for b in np.flatnonzero(np.diff(cuts)) for i in (order[cuts[b] : cuts[b + 1]],)]


def settle(doc_buckets: int, most: int = BLOCK) -> Callable:
    """mapInArrow function over packs sorted by (kind, bucket): hits (kind 1, by doc bucket) of all of them."""

    def judge(blobs: list[bytes]) -> tuple | None:
        key, doc, pos = (np.concatenate(x) for x in zip(*map(unpack_sorted, blobs), strict=True))
        doc = doc.view(np.int64)
        _, _, sub = repeats(key, doc, pos)
        if not len(sub):
            return None
        least = sub[heads(key[sub])]
        later = (doc[sub] != doc[least]) | (pos[sub] != pos[least])
        sub, least = sub[later], least[later]
        return (doc[sub], pos[sub], doc[least], pos[least], key[sub]) if len(sub) else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bucket, blobs, hits, n = None, [], [], 0

        def flush():
            nonlocal hits, n
            if hits:
                yield from shipped(pack_hits(*(np.concatenate(x) for x in zip(*hits, strict=True)), doc_buckets))
            hits, n = [], 0

        def close():
            nonlocal blobs, n
            if blobs and (found := judge(blobs)):
                hits.append(found)
                n += len(found[0])
            blobs = []

        for batch in batches:
            for b, kind, blob in zip(*(batch.column(i) for i in range(3)), strict=True):
                b, kind = b.as_py(), kind.as_py()
                if kind == 1:
                    yield from shipped([(b, 1, blob.as_py())])
                    continue
                if b != bucket:
                    close()
                    bucket = b
                    if n >= most:
                        yield from flush()
                blobs.append(blob.as_py())
        close()
        yield from flush()

    return run


def first_occurrences(src: DataFrame, items: Callable[[Iterator[pa.RecordBatch]], Items], parts: int, buckets: int, doc_buckets: int) -> DataFrame:
    """Packs (bucket by document, kind 1, blob) of all later occurrences: doc, pos, source doc, source pos, key tag."""
    sent = src.mapInArrow(send(items, buckets, doc_buckets), SHIPPED)
    return sent.repartition(parts, "kind", "bucket").sortWithinPartitions("kind", "bucket").mapInArrow(settle(doc_buckets), SHIPPED)


def hits_of(blobs: Iterable[bytes]) -> list[np.ndarray]:
    """(doc, pos, source doc, source pos, tag) of packs, by doc and pos."""
    got = [unpack(b) for b in blobs]
    if not got:
        return [np.zeros(0, np.int64) for _ in range(5)]
    doc, pos, sdoc, spos, tag = (np.concatenate(x).view(np.int64) for x in zip(*got, strict=True))
    order = np.lexsort((pos, doc))
    return [x[order] for x in (doc, pos, sdoc, spos, tag)]


def spread(spark: SparkSession) -> tuple[int, int, int]:
    """(tasks, key buckets, document buckets) of a search: in proportion to the partitions the cluster is set to."""
    n = width(spark)
    return n, 2 * n, 4 * n


def in_buckets(rows: DataFrame, parts: int, take: Callable[[dict[int, list[bytes]]], Iterable[pa.RecordBatch]], schema: str) -> DataFrame:
    """take() of the blobs, by kind, of every bucket of packed rows, one bucket at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bucket, blobs = None, {}
        for batch in batches:
            for b, kind, blob in zip(*(batch.column(i) for i in range(3)), strict=True):
                if b.as_py() != bucket:
                    if blobs:
                        yield from take(blobs)
                    bucket, blobs = b.as_py(), {}
                blobs.setdefault(kind.as_py(), []).append(blob.as_py())
        if blobs:
            yield from take(blobs)
        trim()

    return rows.repartition(parts, "bucket").sortWithinPartitions("bucket").mapInArrow(run, schema)


def shared_ids(src: DataFrame, doc_buckets: int) -> DataFrame:
    """Packs (bucket, kind 0, blob) of the ids that several rows have."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            doc = np.asarray(b.column(0)).astype(np.int64)
            to = xxhash64(doc) % doc_buckets
            yield from shipped([(int(k), 0, pack(doc[to == k])) for k in np.unique(to)])

    return src.where("id is not null").groupBy("id").agg(F.count("*").alias("n")).where("n > 1").select("id").mapInArrow(run, SHIPPED)


def shared_of(blobs: list[bytes]) -> np.ndarray:
    return np.sort(np.concatenate([unpack(b)[0] for b in blobs]).view(np.int64)) if blobs else np.zeros(0, np.int64)


def zipped(src: DataFrame) -> DataFrame:
    """(id, blob) of rows (id, text): texts compressed for the shuffle; null stays null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=1).compress
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([press(t.as_buffer()) if t.is_valid else None for t in b.column(1)], pa.binary())], ["id", "blob"])

    return src.mapInArrow(run, "id long, blob binary")


def unzipped(blob: pa.BinaryScalar) -> bytes:
    return zstandard.ZstdDecompressor().decompress(blob.as_buffer()) if blob.is_valid else b""
