"""Line dedup by overlapping windows of three lines.

Lines end at line feeds; blank lines (white space only) are skipped, neither hashed nor removed.
Every window of three consecutive lines of a document is hashed. Of windows that repeat anywhere,
the first by (document id, line) stays, and all lines that later occurrences cover are removed;
overlapping occurrences merge. The first occurrence of any line's content is never removed.

Edge cases: null and empty texts and texts with under three lines stay as they are; rows with a
null id neither lose lines nor serve as sources; equal rows with one id stay as they are
towards each other; other columns pass through under any name, but for _lines and _removed, which are
replaced; names of id and text match in any case.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kgflow.llm import packs, words
from kgflow.llm.frames import by_position, column, id_and_text, place, restored

WINDOW = 3
#: Bytes inside lines: all but the line feed.
INLINE = np.ones(256, bool)
INLINE[0x0A] = False


def line_windows(col: pa.Array, k: int) -> Iterator[tuple[words.Chunk, np.ndarray, np.ndarray, np.ndarray]]:
    """(chunk, hash, text index, position among the text's non-blank lines) of every window."""
    for c in words.chunks(col, INLINE):
        h = c.hashes()
        ink = np.concatenate(([0], np.cumsum(words.NONSPACE[c.buf])))
        full = ink[c.end] > ink[c.start]
        own = c.owners()[full]
        key = words.window_hashes(h[full], k)
        first = np.searchsorted(own, np.arange(c.hi - c.lo))
        ok = own[: len(key)] == own[k - 1 :] if len(key) else np.zeros(0, bool)
        own = own[: len(key)][ok]
        yield c, key[ok], own, np.flatnonzero(ok) - first[own]


def found_lines(hits: DataFrame, shared: DataFrame, tasks: int) -> DataFrame:
    """(id, found): per document the positions of its later windows with 16 bits of their hash, and whether other rows have its id."""

    def take(blobs: dict[int, list[bytes]]) -> Iterator[pa.RecordBatch]:
        doc, pos, _, _, tag = packs.hits_of(blobs.get(1, []))
        ids, first = np.unique(doc, return_index=True)
        both = np.isin(ids, packs.shared_of(blobs.get(0, [])))
        cuts = np.append(first, len(doc))
        for lo in range(0, len(ids), 4096):
            part = range(lo, min(len(ids), lo + 4096))
            blob = [packs.pack(pos[cuts[i] : cuts[i + 1]], tag[cuts[i] : cuts[i + 1]]) for i in part]
            yield pa.RecordBatch.from_arrays([pa.array(ids[part.start : part.stop]), pa.array(blob, pa.binary()), pa.array(both[part.start : part.stop])], ["id", "found", "shared"])

    return packs.in_buckets(hits.unionByName(shared), tasks, take, "id long, found binary, shared boolean")


def kept_lines(text: str, pos: np.ndarray, tag: np.ndarray, shared: bool, k: int) -> tuple[int, int, str]:
    """(non-blank lines, removed lines, text left)."""
    lines = text.split("\n")
    full = [j for j, line in enumerate(lines) if line.strip(" \t\r\v\f")]
    gone = np.zeros(len(full) + k, bool)
    if shared and len(pos):
        ok = np.zeros(len(pos), bool)
        for _, key, _, _ in line_windows(pa.array([text], pa.string()), k):
            inside = pos < len(key)
            ok[inside] = (key[pos[inside]] & words.U(0xFFFF)).astype(np.int64) == tag[inside]
        pos = pos[ok]
    for d in range(k):
        gone[pos + d] = True
    drop = {full[j] for j in np.flatnonzero(gone[: len(full)])}
    return len(full), len(drop), "\n".join(x for j, x in enumerate(lines) if j not in drop) if drop else text


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = WINDOW) -> DataFrame:
    """The rows of docs with the text's later line windows removed, and two more columns:
    _lines (non-blank lines before) and _removed."""
    tasks, buckets, doc_buckets = packs.spread(docs.sparkSession)
    src = id_and_text(docs, id_col, text_col)

    def items(batches: Iterator[pa.RecordBatch]) -> packs.Items:
        for b in batches:
            known = b.filter(b.column(0).is_valid())
            ids = np.asarray(known.column(0)).astype(np.int64)
            for c, key, own, pos in line_windows(known.column(1), k):
                yield key, ids[c.lo + own], pos

    hits = packs.first_occurrences(src, items, tasks, buckets, doc_buckets)
    found = found_lines(hits, packs.shared_ids(src, doc_buckets), tasks)
    at, width = place(docs, text_col), len(docs.columns)

    def edit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n_lines, n_removed, kept = [], [], []
            for text, blob, shared in zip(b.column(at).cast(pa.string()), b.column(width), b.column(width + 1), strict=True):
                pos, tag = (x.view(np.int64) for x in packs.unpack(blob.as_py())) if blob.is_valid else (np.zeros(0, np.int64),) * 2
                n, gone, left = kept_lines(text.as_py() or "", pos, tag, bool(shared.as_py()), k)
                n_lines.append(n)
                n_removed.append(gone)
                kept.append(left if gone else text.as_py())
            cols = b.columns[:width]
            cols[at] = pa.array(kept, pa.string())
            yield pa.RecordBatch.from_arrays([*cols, pa.array(n_lines, pa.int64()), pa.array(n_removed, pa.int64())], [*(f"c{i}" for i in range(width)), "_lines", "_removed"])

    key = column(docs, id_col).cast("long")
    wide = by_position(docs)
    joined = wide.join(found, key == F.col("id"), "left").select(*wide.columns, "found", "shared")
    fields = [T.StructField(f"c{i}", T.StringType() if i == at else f.dataType) for i, f in enumerate(docs.schema.fields)]
    schema = T.StructType([*fields, T.StructField("_lines", T.LongType()), T.StructField("_removed", T.LongType())])
    return restored(joined.mapInArrow(edit, schema), docs.columns, ["_lines", "_removed"])


ORACLE = r"""
WITH l AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS n FROM documents),
f AS (
  SELECT doc_id, line, n, row_number() OVER (PARTITION BY doc_id ORDER BY n) AS p FROM l WHERE regexp_matches(line, '[^\x20\x09\x0B-\x0D]')),
w AS (
  SELECT doc_id, p, [line, lead(line) OVER v, lead(line, 2) OVER v] AS k FROM f WINDOW v AS (PARTITION BY doc_id ORDER BY p)),
later AS (
  SELECT doc_id, p FROM (SELECT doc_id, p, row_number() OVER (PARTITION BY k ORDER BY doc_id, p) AS r FROM w WHERE k[3] IS NOT NULL) WHERE r > 1),
gone AS (SELECT DISTINCT doc_id, unnest(range(p, p + 3)) AS p FROM later),
m AS (SELECT l.doc_id, l.line, l.n, f.p IS NOT NULL AS inked, gone.p IS NOT NULL AS removed
  FROM l LEFT JOIN f USING (doc_id, n) LEFT JOIN gone ON gone.doc_id = f.doc_id AND gone.p = f.p)
SELECT doc_id, sum(inked::INT)::BIGINT AS n_lines, sum(removed::INT)::BIGINT AS n_removed,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY n) FILTER (WHERE NOT removed), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""
