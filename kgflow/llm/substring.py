"""Repeated word spans across documents, on a de Bruijn graph of word k-mers.

An edge is a k-mer (k consecutive words); an occurrence has coordinates (document, word).

1. The global search of :mod:`packs` finds the repeated edges and gives each later occurrence the
   coordinates of one in a smaller document.
2. Of one document's edges, those that run on along one source are a nonbranching path: ``pieces``.
3. ``compacted`` goes on by joins: a piece whose source lies on a path of the source's own document moves to
   that path's source, and pieces that then run on along one source become one path.
4. ``verified`` reads the words at the source coordinates of every path and joins their digest back; a
   document's words go only where the words of the path, read in that document, have the same digest
   (128 bits, of the words themselves). Hashes of k-mers only propose.

Texts are shuffled compressed, once to read the source coordinates and once for the removal.

Edge cases: null and empty texts have no words; texts with under k words no k-mers; rows with a
null id neither lose words nor serve as sources; rows sharing an id don't remove each other's words, and as
their coordinates are mixed, their paths are single k-mers; columns beside id and text are ignored,
whatever their names. If the hash of a k-mer meets that of another one in the smallest document (once in
some 1e18 pairs), the words stay.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgflow.llm import packs, words
from kgflow.llm.frames import id_and_text
from kgflow.session import stored

WINDOW = 13
#: Words of a source document whose paths are looked up together.
REQUESTS = 4096
#: Words of a document in which paths are looked up together.
CHUNK = 64
SPANS = pa.list_(pa.struct([("start", pa.int32()), ("length", pa.int32()), ("source_doc", pa.int64()), ("source_start", pa.int32())]))
PIECES = "doc long, start int, length int, source_doc long, source_start int, lone boolean"


def kmers(k: int):
    """Items (hash, document, word position) of every k-mer of batches (id, text)."""

    def items(batches: Iterator[pa.RecordBatch]) -> packs.Items:
        for b in batches:
            known = b.filter(b.column(0).is_valid())
            ids = np.asarray(known.column(0)).astype(np.int64)
            for c in words.chunks(known.column(1)):
                key, own, pos = words.windows(c, k)
                yield key, ids[c.lo + own], pos

    return items


def pieces(hits: DataFrame, shared: DataFrame, tasks: int, k: int) -> DataFrame:
    """Runs of repeated edges of one document along one source; of documents whose id is shared, single edges (lone)."""

    def take(blobs: dict[int, list[bytes]]) -> Iterator[pa.RecordBatch]:
        doc, pos, sdoc, spos, _ = packs.hits_of(blobs.get(1, []))
        ok = sdoc < doc
        doc, pos, sdoc, spos = doc[ok], pos[ok], sdoc[ok], spos[ok]
        if not len(doc):
            return
        shift = spos - pos
        order = np.lexsort((pos, shift, sdoc, doc))
        doc, pos, sdoc, shift = doc[order], pos[order], sdoc[order], shift[order]
        lone = np.isin(doc, packs.shared_of(blobs.get(0, [])))
        cut = np.ones(len(doc), bool)
        cut[1:] = lone[1:] | (np.diff(doc) != 0) | (np.diff(sdoc) != 0) | (np.diff(shift) != 0) | (np.diff(pos) > 1)
        at = np.flatnonzero(cut)
        last = np.append(at[1:], len(doc)) - 1
        cols = [pa.array(doc[at]), pa.array(pos[at].astype(np.int32)), pa.array((pos[last] - pos[at] + k).astype(np.int32)), pa.array(sdoc[at]), pa.array((pos + shift)[at].astype(np.int32)), pa.array(lone[at])]
        whole = pa.RecordBatch.from_arrays(cols, [f.split()[0] for f in PIECES.split(", ")])
        yield from (whole.slice(i, 8192) for i in range(0, len(at), 8192))

    return packs.in_buckets(hits.unionByName(shared), tasks, take, PIECES)


SOURCE = ["source_doc", "source_start", "length"]


def roots(found: DataFrame) -> DataFrame:
    """Of the pieces' distinct sources: where the path begins that a source lies on in its own document, if it does
    (source_doc, source_start, length, up struct<start, length, d, p>). Paths are looked up by chunks of words that they run
    through, so a source meets the few paths of its place, not all of its document."""
    asked = found.select(*SOURCE).distinct().withColumn("chunk", F.floor(F.col("source_start") / CHUNK))
    path = F.struct("start", "length", F.col("source_doc").alias("d"), F.col("source_start").alias("p"))
    through = F.sequence(F.floor(F.col("start") / CHUNK), F.floor((F.col("start") + F.col("length") - 1) / CHUNK))
    own = found.where("not lone").select(F.col("doc").alias("source_doc"), F.explode(through).alias("chunk"), path.alias("up"))
    inside = (F.col("up.start") <= F.col("source_start")) & (F.col("source_start") + F.col("length") <= F.col("up.start") + F.col("up.length"))
    return asked.join(own, ["source_doc", "chunk"]).where(inside).groupBy(*SOURCE).agg(F.min("up").alias("up"))


def compacted(found: DataFrame) -> DataFrame:
    """Paths of the pieces: sources moved to the source of the path they lie on, and pieces that run on, or
    overlap, along one source joined.

    One round is enough: only the source that a block of rows chose can lie on another path, and that path's
    source is settled over all rows. The roots are stored first, so that the join with them, on a source that a third of all
    rows may share, is one of two shuffles, which Spark splits where it is skewed."""
    rooted = found.join(stored(roots(found)), SOURCE, "left").select(
        "doc", "start", "length", F.coalesce("up.d", "source_doc").alias("source_doc"), F.coalesce(F.col("source_start") - F.col("up.start") + F.col("up.p"), "source_start").alias("source_start"), "lone"
    )
    line = Window.partitionBy("doc", "source_doc", F.col("source_start") - F.col("start"), F.when(F.col("lone"), F.col("start"))).orderBy("start")
    reached = F.max(F.col("start") + F.col("length")).over(line.rowsBetween(Window.unboundedPreceding, -1))
    runs = rooted.withColumn("new", F.coalesce(F.col("start") > reached, F.lit(True)).cast("int")).withColumn("run", F.sum("new").over(line))
    shift = (F.col("source_start") - F.col("start")).alias("shift")
    joined = runs.groupBy("doc", "source_doc", shift, F.when(F.col("lone"), F.col("start")).alias("at"), "run").agg(F.min("start").alias("start"), F.max(F.col("start") + F.col("length")).alias("stop"))
    return joined.select("doc", "start", (F.col("stop") - F.col("start")).alias("length"), "source_doc", (F.col("start") + F.col("shift")).alias("source_start"))


def digest(tokens: list[bytes], start: int, length: int) -> bytes:
    return hashlib.blake2b(b" ".join(tokens[start : start + length]), digest_size=16).digest()


def verified(zipped: DataFrame, paths: DataFrame) -> DataFrame:
    """paths with the digests of the words at their source coordinates (several where rows share the source's id)."""
    asked = paths.select("source_doc", "source_start", "length").distinct()
    lists = asked.groupBy("source_doc", F.floor(F.col("source_start") / REQUESTS).alias("part")).agg(F.collect_list(F.struct("source_start", "length")).alias("asked"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for doc, blob, wanted in zip(*(b.column(i) for i in range(3)), strict=True):
                tokens, n = packs.unzipped(blob).split(), len(wanted)
                start, length = (np.asarray(wanted.values.field(i)) for i in (0, 1))
                got = [digest(tokens, s, w) for s, w in zip(start.tolist(), length.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array([doc.as_py()] * n, pa.int64()), pa.array(start, pa.int32()), pa.array(length, pa.int32()), pa.array(got, pa.binary())], ["source_doc", "source_start", "length", "digest"])

    read = zipped.join(lists, F.col("id") == F.col("source_doc")).select("source_doc", "blob", "asked").mapInArrow(run, "source_doc long, source_start int, length int, digest binary")
    known = stored(read.groupBy(*SOURCE).agg(F.collect_set("digest").alias("digests")))
    return paths.join(known, SOURCE)


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = WINDOW, items=kmers) -> DataFrame:
    """(id, n_words, n_removed, spans, kept_text): each word covered by a k-mer that also starts in a document with a
    smaller id is removed; spans are the verified paths with the coordinates of their sources."""
    tasks, buckets, doc_buckets = packs.spread(docs.sparkSession)
    src = id_and_text(docs, id_col, text_col)
    hits = packs.first_occurrences(src, items(k), tasks, buckets, doc_buckets)
    paths = stored(compacted(stored(pieces(hits, packs.shared_ids(src, doc_buckets), tasks, k))))
    zipped = packs.zipped(src)
    per_doc = verified(zipped, paths).groupBy(F.col("doc").alias("id")).agg(F.collect_list(F.struct("start", "length", "source_doc", "source_start", "digests")).alias("paths"))

    def edit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n_words, n_removed, spans, kept = [], [], [], []
            for blob, found in zip(b.column(1), b.column(2), strict=True):
                own = packs.unzipped(blob).split()
                sure = [x for x in found.as_py() or () if x["start"] + x["length"] <= len(own) and digest(own, x["start"], x["length"]) in x.pop("digests")]
                keep = np.ones(len(own), bool)
                for x in sure:
                    keep[x["start"] : x["start"] + x["length"]] = False
                n_words.append(len(own))
                n_removed.append(int(len(own) - keep.sum()))
                spans.append(sorted(sure, key=lambda x: (x["start"], x["length"], x["source_doc"], x["source_start"])))
                kept.append(b" ".join(compress(own, keep.tolist()) if sure else own))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(spans, SPANS), pa.array(kept, pa.binary()).cast(pa.string())], ["id", "n_words", "n_removed", "spans", "kept_text"])

    out = zipped.join(per_doc, "id", "left").select("id", "blob", "paths").mapInArrow(edit, "id long, n_words long, n_removed long, spans array<struct<start:int,length:int,source_doc:long,source_start:int>>, kept_text string")
    return out.withColumnRenamed("id", id_col)


ORACLE = r"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
win AS (
  SELECT doc_id, unnest(range(1, len(ws) - 11)) AS p, ws FROM w WHERE len(ws) >= 13),
keyed AS (SELECT doc_id, p, array_to_string(ws[p:p + 12], ' ') AS k FROM win),
leasts AS (SELECT k, min(doc_id) AS d FROM keyed GROUP BY k HAVING count(DISTINCT doc_id) > 1),
gone AS (
  SELECT DISTINCT doc_id, unnest(range(p, p + 13)) AS i FROM keyed JOIN leasts USING (k) WHERE d < doc_id),
dropped AS (SELECT doc_id, list(i) AS g FROM gone GROUP BY doc_id)
SELECT doc_id, len(ws)::BIGINT AS n_words, coalesce(len(g), 0)::BIGINT AS n_removed,
  sha256(array_to_string(CASE WHEN g IS NULL THEN ws ELSE list_filter(list_transform(range(1, len(ws) + 1), lambda i: CASE WHEN list_contains(g, i) THEN NULL ELSE ws[i] END), lambda x: x IS NOT NULL) END, ' ')) AS kept_sha256
FROM w LEFT JOIN dropped USING (doc_id)
"""
