"""Benchmark decontamination: CGK embedding, bit-sampling LSH and exact edit distance, on words.

A document is contaminated by an item if some stretch of it is within ``RATIO`` of the item's
words in edit distance (insertions, deletions and replacements of words).

- Windows: an item of n words with at most e edits keeps one of e + 1 stretches of
  q = n // (e + 1) words intact, so a window of n words is looked at where a q-gram of the item
  occurs, on its diagonal. At most e of the item's words are replaced or deleted, so at least n - e of
  them have to occur in the window widened by e words on both sides. Both rules lose nothing.
- Embedding: a walk over a window emits the current word for 3n steps and moves on when a random
  function of step and word says so. Item and window walk with the same functions, so that they
  fall in step again after an edit: small edit distance becomes small Hamming distance.
- LSH: a table samples places of the embedding; a window is a candidate if all sampled places agree with
  the item's in any table. For every class of item lengths the places per table and the number of walks are
  those with which items at their largest number of random edits, cut from other text as the windows
  are, are found with a share of ``RECALL``.
- Candidates are verified by the exact distance of the item to the best stretch of the widened window.
- An exact way for the rest: where no candidate of an item and a document holds, the document's other windows of that item
  are verified too. So every item within its edits is found, also where no number of walks reaches the
  target, and what the tables find spares its other windows.

Items are a stated query set. They are sent to the tasks in blocks of at most ``ITEM_BYTES`` of text, a flat
array of words however long the longest is; more items mean more blocks, each over all documents.

Words are runs of ASCII digits, letters in lower case and other non-ASCII characters.

Edge cases: null and empty texts and items match nothing; items under ``SHORT`` words have to
occur unchanged; repeated items are looked for once each; texts are searched whole; other columns pass
through under any name, but for _found, which is replaced; names match in any case.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kgflow.llm import words
from kgflow.llm.frames import by_position, column, restored
from kgflow.llm.words import U, mix

RATIO, RECALL, SHORT = 0.2, 0.99, 5
#: Places that a table may sample, tables per walk, and most walks.
SAMPLES, TABLES, WALKS = (6, 4, 3, 2), 8, 12
#: Items of a class differ in length by this factor at most; random edits tried per class.
CLASS, TRIALS = 1.5, 200
#: Words of widened windows that are judged at once (one window at least).
CELLS = 1 << 18
#: Bytes of item texts in a block.
ITEM_BYTES = 16 << 20


@dataclass
class Items:
    ids: np.ndarray
    words: np.ndarray  # hashes of all items' words, one item after the other
    at: np.ndarray  # where an item's words begin
    size: np.ndarray
    edits: np.ndarray
    #: By class of lengths: places per table, and walks.
    plan: dict[int, tuple[int, int]] = field(default_factory=dict)

    def rows(self, i: np.ndarray) -> np.ndarray:
        """Words of these items, 0 beyond the end."""
        spot = np.arange(int(self.size[i].max(initial=1)))
        return np.where(spot < self.size[i][:, None], self.words[np.minimum(self.at[i][:, None] + spot, len(self.words) - 1)], U(0))

    def classes(self) -> np.ndarray:
        return np.floor(np.log(np.maximum(self.size, 1)) / math.log(CLASS)).astype(int)


def table_places(size: np.ndarray, walk: int, sample: int) -> np.ndarray:
    """(rows, TABLES, sample) sampled steps of the walk, by the item's size."""
    share = np.random.default_rng(700 + walk).random((TABLES, sample))
    return (share[None] * (3 * size)[:, None, None]).astype(np.int64)


def walked(x: np.ndarray, size: np.ndarray, walk: int) -> np.ndarray:
    """CGK embedding of rows of word hashes: (rows, 3 * longest)."""
    n, longest = x.shape
    padded = np.concatenate([x, np.zeros((n, 1), np.uint64)], 1)
    at, out, rows = np.zeros(n, np.int64), np.zeros((n, 3 * longest), np.uint64), np.arange(n)
    # one stream of seeds per walk: a row's walk doesn't depend on the rows beside it
    seeds = np.random.default_rng(300 + walk).integers(1, 2**63, 3 * longest, dtype=np.uint64)
    for j in range(3 * longest):
        here = padded[rows, at]
        out[:, j] = here
        at = np.minimum(at + (mix(here ^ seeds[j]) & U(1)).astype(np.int64), size)
    return out


def tables(x: np.ndarray, size: np.ndarray, sample: int, walks: int) -> np.ndarray:
    """(rows, walks * TABLES) keys."""
    keys = []
    for walk in range(walks):
        e = walked(x, size, walk)
        got = np.take_along_axis(e, table_places(size, walk, sample).reshape(len(x), TABLES * sample), 1).reshape(len(x), TABLES, sample)
        key = np.zeros((len(x), TABLES), np.uint64)
        for i in range(sample):
            key = mix(key * words.WORD_BASE + got[:, :, i] + U(1))
        keys.append(key)
    return np.concatenate(keys, 1)


def grams(items: Items) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """By gram length: (hash, item, offset) of the q-grams of every item, by hash."""
    by: dict[int, list] = {}
    for i, (n, e) in enumerate(zip(items.size.tolist(), items.edits.tolist(), strict=True)):
        q = n // (e + 1)
        h = words.window_hashes(items.words[items.at[i] : items.at[i] + n], q)
        by.setdefault(q, []).append((h, np.full(len(h), i), np.arange(len(h))))
    out = {}
    for q, parts in by.items():
        h, i, o = (np.concatenate(x) for x in zip(*parts, strict=True))
        order = np.argsort(h, kind="stable")
        out[q] = (h[order], i[order], o[order])
    return out


class Gate:
    """Windows (item, first word) of the items on the diagonals of their q-grams."""

    def __init__(self, items: Items):
        self.by_length = grams(items)
        self.lookups = {q: words.Lookup(h) for q, (h, _, _) in self.by_length.items()}

    def windows(self, h: np.ndarray, own: np.ndarray, first: np.ndarray) -> np.ndarray:
        out = []
        for q, (keys, item, offset) in self.by_length.items():
            hashed = words.window_hashes(h, q)
            where, _ = self.lookups[q].found(hashed)
            where = where[own[where] == own[where + q - 1]]
            key = hashed[where]
            lo, n = np.searchsorted(keys, key), np.searchsorted(keys, key, "right") - np.searchsorted(keys, key)
            spot = np.repeat(lo, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            start = np.repeat(where, n) - offset[spot]
            out.append(np.unique(np.stack([item[spot], np.maximum(start, np.repeat(first[own[where]], n))], 1), axis=0))
        return np.unique(np.concatenate(out), axis=0) if out else np.zeros((0, 2), np.int64)


def cut(h: np.ndarray, start: np.ndarray, length: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Rows of the words start .. start + length - 1, 0 outside of lo .. hi - 1."""
    spot = start[:, None] + np.arange(int(length.max(initial=1)))
    fits = (spot >= lo[:, None]) & (spot < np.minimum(hi, start + length)[:, None])
    return np.where(fits, h[np.clip(spot, 0, len(h) - 1)], U(0))


def edited(w: list[int], edits: int, rng: np.random.Generator) -> list[int]:
    """w after so many random insertions, deletions and replacements."""
    for _ in range(edits):
        kind, p = rng.integers(0, 3), int(rng.integers(0, max(1, len(w))))
        w = w[:p] + ([int(rng.integers(1, 2**62))] if kind < 2 else []) + w[p + (kind != 1) :]
    return w


def calibrated(items: Items, cls: int, recall: float) -> tuple[int, int]:
    """(places, walks): the most places per table, and then the fewest walks, with which random edits of the class's items,
    at the largest number allowed, are found with this share; the fewest places and most walks where none does."""
    rng = np.random.default_rng(11 + cls)
    among = np.flatnonzero(items.classes() == cls)
    pick = among[rng.integers(0, len(among), TRIALS)]
    texts = []
    for i in pick:
        w = items.words[items.at[i] : items.at[i] + items.size[i]].tolist()
        around = rng.integers(1, 2**62, 2 * int(items.edits[i]) + 2).tolist()
        half = len(around) // 2
        texts.append(np.array(around[:half] + edited(w, int(items.edits[i]), rng) + around[half:], np.uint64))
    h, size = np.concatenate(texts), np.array([len(t) for t in texts])
    first = np.concatenate(([0], np.cumsum(size)))
    own = np.repeat(np.arange(len(texts)), size)
    sub = Items(items.ids[among], items.words, items.at[among], items.size[among], items.edits[among])
    item, start = Gate(sub).windows(h, own, first).T
    item = among[item]
    mine = item == pick[own[start]]
    item, start = item[mine], start[mine]
    n = items.size[item]
    x, y = cut(h, start, n, first[own[start]], first[own[start] + 1]), items.rows(item)
    for sample in SAMPLES:
        hit = tables(x, n, sample, WALKS) == tables(y, n, sample, WALKS)
        for walks in range(1, WALKS + 1):
            found = np.zeros(len(texts), bool)
            found[own[start[hit[:, : walks * TABLES].any(1)]]] = True
            if found.mean() >= recall:
                return sample, walks
    return SAMPLES[-1], WALKS


def read_items(rows: list[tuple[int, str]], ratio: float, recall: float) -> Items:
    ids, seqs = [], []
    for c in words.chunks(pa.array([t for _, t in rows], pa.string()), words.ALNUM, lower=True):
        h = c.hashes()
        for i in range(c.hi - c.lo):
            if c.first[i + 1] > c.first[i]:
                ids.append(rows[c.lo + i][0])
                seqs.append(h[c.first[i] : c.first[i + 1]])
    size = np.array([len(s) for s in seqs], np.int64)
    edits = np.where(size < SHORT, 0, np.floor(ratio * size)).astype(np.int64)
    out = Items(np.array(ids, np.int64), np.concatenate([*seqs, np.zeros(0, np.uint64)]), np.cumsum(size) - size, size, edits)
    out.plan = {int(c): calibrated(out, c, recall) for c in np.unique(out.classes())}
    return out


def held(item: np.ndarray, size: np.ndarray, text: np.ndarray) -> np.ndarray:
    """How many places of each row's item (its first size words) have a word that occurs in its text row."""
    salt = mix(np.arange(1, len(item) + 1, dtype=np.uint64))[:, None]
    inside = np.isin(item ^ salt, text ^ salt)  # rows of 64-bit hashes set apart by their salt
    return (inside & (np.arange(item.shape[1]) < size[:, None])).sum(1)


def distances(item: np.ndarray, size: np.ndarray, text: np.ndarray) -> np.ndarray:
    """Least edit distance of each row's item (its first size words) to any stretch of its text row."""
    steps = np.arange(text.shape[1] + 1)
    row = np.zeros((len(item), text.shape[1] + 1), np.int64)
    best = row.min(1)
    for i in range(item.shape[1]):
        new = np.empty_like(row)
        new[:, 0] = i + 1
        new[:, 1:] = np.minimum(row[:, :-1] + (text != item[:, i : i + 1]), row[:, 1:] + 1)
        row = np.minimum.accumulate(new - steps, 1) + steps
        best = np.where(size == i + 1, row.min(1), best)
    return best


KIND = pa.list_(pa.struct([("item", pa.int64()), ("word", pa.int64()), ("edits", pa.int64())]))
FOUND = T.ArrayType(T.StructType([T.StructField("item", T.LongType()), T.StructField("word", T.LongType()), T.StructField("edits", T.LongType())]))


def batches_of(size: np.ndarray, kind: np.ndarray) -> Iterator[np.ndarray]:
    """Rows of one kind and of about one size together, at most CELLS words of widened windows (or one row)."""
    order = np.lexsort((size, kind))
    lo = 0
    while lo < len(order):
        last = min(len(order), lo + max(1, CELLS // int(2 * size[order[lo]])))
        part = order[lo:last]
        same = (kind[part] == kind[part[0]]) & (size[part] <= 2 * size[part[0]])
        n = len(part) if same.all() else int(same.argmin())
        yield part[:n]
        lo += n


class Judge:
    """Finds items in the words of texts; works inside a task."""

    def __init__(self, items: Items):
        self.items, self.gate, self.classes = items, Gate(items), items.classes()
        self.keys: dict[int, dict[int, np.ndarray]] = {}

    def item_keys(self, i: np.ndarray, cls: int) -> np.ndarray:
        known = self.keys.setdefault(cls, {})
        new = np.array([k for k in np.unique(i).tolist() if k not in known], np.int64)
        if len(new):
            known.update(zip(new.tolist(), tables(self.items.rows(new), self.items.size[new], *self.items.plan[cls]), strict=True))
        return np.stack([known[k] for k in i.tolist()])

    def found(self, c: words.Chunk) -> dict[tuple[int, int], tuple[int, int]]:
        """(text, item): (edits, first word) of the items in a chunk."""
        items, h, own, first = self.items, c.hashes(), c.owners(), c.first
        if not len(h) or not len(items.ids):
            return {}
        pairs = self.gate.windows(h, own, first)
        n, e, t = items.size[pairs[:, 0]], items.edits[pairs[:, 0]], own[pairs[:, 1]]
        kept, near = [], []
        for b in batches_of(n, self.classes[pairs[:, 0]]):
            i, s = pairs[b].T
            lo, hi = first[t[b]], first[t[b] + 1]
            rows = items.rows(i)
            ok = held(rows, n[b], cut(h, s - e[b], n[b] + 2 * e[b], lo, hi)) >= n[b] - e[b]
            b, i, s, lo, hi, rows = b[ok], i[ok], s[ok], lo[ok], hi[ok], rows[ok]
            if len(b):
                cls = int(self.classes[i[0]])
                sample, walks = items.plan[cls]
                x = cut(h, s, n[b], lo, hi)
                hit = (x[:, : rows.shape[1]] == rows[:, : x.shape[1]]).all(1)
                rest = np.flatnonzero(~hit)
                if len(rest):
                    hit[rest] = (tables(x[rest], n[b[rest]], sample, walks) == self.item_keys(i[rest], cls)).any(1)
                kept.append(b)
                near.append(hit)
        out: dict[tuple[int, int], tuple[int, int]] = {}
        if kept:
            keep, hit = np.concatenate(kept), np.concatenate(near)
            self.verify(c, h, pairs[keep[hit]], out)
            rest = keep[~hit]
            missed = np.array([(int(t[r]), int(pairs[r, 0])) not in out for r in rest], bool)
            self.verify(c, h, pairs[rest[missed]], out) if len(rest) else None
        return out

    def verify(self, c: words.Chunk, h: np.ndarray, pairs: np.ndarray, out: dict[tuple[int, int], tuple[int, int]]) -> None:
        items, own = self.items, c.owners()
        for b in batches_of(items.size[pairs[:, 0]], np.zeros(len(pairs), np.int64)):
            i, s = pairs[b].T
            n, e, t = items.size[i], items.edits[i], own[s]
            d = distances(items.rows(i), n, cut(h, s - e, n + 2 * e, c.first[t], c.first[t + 1]))
            for k in np.flatnonzero(d <= e).tolist():
                key, got = (int(t[k]), int(i[k])), (int(d[k]), int(s[k] - c.first[t[k]]))
                out[key] = min(out.get(key, got), got)


def search(docs: DataFrame, items: Items, text: str, name: str) -> DataFrame:
    """The rows of docs with one more column, array<struct<item, word, edits>>."""
    at = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = Judge(items)
        for b in batches:
            found: list[list] = []
            for c in words.chunks(b.column(at), words.ALNUM, lower=True):
                per: list[list] = [[] for _ in range(c.hi - c.lo)]
                for (t, i), (d, s) in sorted(judge.found(c).items()):
                    per[t].append({"item": int(items.ids[i]), "word": s, "edits": d})
                found += per
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(found, KIND)], [*b.schema.names, name])

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField(name, FOUND)]))


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", ratio: float = RATIO, recall: float = RECALL) -> DataFrame:
    """The rows of docs with _found, the items found in each."""
    src = by_position(benchmark).select(column(benchmark, item_col).cast("long").alias("item"), F.lower(column(benchmark, item_text).cast("string")).alias("text")).where("item is not null and text is not null")
    total = src.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, math.ceil(total / ITEM_BYTES))
    out = by_position(docs).withColumn("plain", F.lower(column(docs, text_col).cast("string")))
    for k in range(blocks):
        rows = [(r["item"], r["text"]) for r in src.where(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == k).orderBy("item", "text").collect()]
        out = search(out, read_items(rows, ratio, recall), "plain", f"found{k}")
    return restored(out.withColumn("_found", reduce(F.concat, [F.col(f"found{k}") for k in range(blocks)])), docs.columns, ["_found"])
