"""Toxicity severity by cumulative-link ordinal regression on sparse word features.

Grades are 0 (clean), 1 (toxic) and 2 (severely toxic). Labels say toxic or not; a toxic
labelled text counts as severe if the share of its words that are tied to toxicity is at or
above the median of toxic texts. One weight vector serves all thresholds:
P(grade > k) = sigmoid(w.x - theta_k), theta_0 <= theta_1; the severity reported is the
expected grade, the sum of these probabilities.

Features are words (ASCII alphanumerics lower-cased, and non-ASCII characters) and their first
``PREFIXES`` bytes, which stand for inflected forms, with a damped count. Those are kept whose log
odds for toxic against clean texts are at least ``Z_LEAST`` standard errors above zero, at most
``MAX_FEATURES`` by significance. The model is fitted on the driver on at most
``MAX_ROWS`` labelled texts, drawn by a hash of their id; both are documented bounds of a
model's size, and scoring runs over every text.

Edge cases: null and empty texts have no features and score what the thresholds give; without
labelled rows of both kinds nothing is toxic; labels that are null, or disagree for one id,
are ignored; repeated documents are scored alike; other columns pass through under any name, but for
_severity, _grade and _toxic, which are replaced; names match in any case.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kgflow.llm import words
from kgflow.llm.frames import by_position, column, id_and_text, place, restored
from kgflow.session import settled

MAX_ROWS, MAX_FEATURES = 8000, 16384
Z_LEAST, L2, STEPS = 3.0, 0.5, 800
PREFIXES = (4, 5, 6, 8)


@dataclass(frozen=True)
class Model:
    keys: np.ndarray  # hashes of the words
    weights: np.ndarray
    thresholds: np.ndarray

    def exceed(self, score: np.ndarray) -> np.ndarray:
        """P(grade > k) per row and k."""
        return sigmoid(score[:, None] - self.thresholds[None, :])


def damped(count: np.ndarray) -> np.ndarray:
    """Value of a feature that occurs so often: 1 for one occurrence, at most 2."""
    return np.minimum(np.log2(1.0 + count), 2.0)


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


def features_of_rows(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, most: int) -> DataFrame:
    """(id, toxic, size, keys, counts) of a bounded sample of labelled texts: distinct word hashes and their counts."""
    given = by_position(labels).select(column(labels, id_col).cast("long").alias("id"), column(labels, "toxic").cast("int").alias("toxic")).where("id is not null and toxic is not null")
    sure = given.groupBy("id").agg(F.min("toxic").alias("toxic"), F.max("toxic").alias("t2")).where("toxic = t2")
    # at most `most` rows of two numbers: a proven bound for the broadcast
    sample = sure.orderBy(F.xxhash64("id"), "id").limit(most).select("id", "toxic")
    src = id_and_text(docs, id_col, text_col).join(F.broadcast(sample), "id").select("id", "toxic", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for c in words.chunks(b.column(2), words.ALNUM, lower=True):
                h, keys, counts = c.hashes(*PREFIXES), [], []
                for i in range(c.hi - c.lo):
                    k, n = np.unique(h[c.first[i] : c.first[i + 1]].reshape(-1), return_counts=True)
                    keys.append(k.tobytes())
                    counts.append(n.astype(np.int32).tobytes())
                size = pa.array([h[c.first[i] : c.first[i + 1]].size for i in range(c.hi - c.lo)], pa.int64())
                yield pa.RecordBatch.from_arrays([b.column(0).slice(c.lo, c.hi - c.lo), b.column(1).cast(pa.int32()).slice(c.lo, c.hi - c.lo), size, pa.array(keys, pa.binary()), pa.array(counts, pa.binary())], ["id", "toxic", "size", "keys", "counts"])

    return src.mapInArrow(run, "id long, toxic int, size long, keys binary, counts binary")


def word_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, bad, good): toxic and clean texts of a block that have the word, of batches (toxic, keys)."""
    for batch in batches:
        for lo in range(0, batch.num_rows, 256):
            b = batch.slice(lo, 256)
            toxic = np.asarray(b.column(0)) > 0
            keys = [np.frombuffer(x.as_buffer(), np.uint64) for x in b.column(1)]
            key, code = np.unique(np.concatenate(keys), return_inverse=True)
            bad = np.bincount(code[np.repeat(toxic, [len(k) for k in keys])], minlength=len(key))
            good = np.bincount(code, minlength=len(key)) - bad
            yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(bad), pa.array(good)], ["key", "bad", "good"])


def tied_words(rows: DataFrame, n1: int, n0: int) -> np.ndarray:
    """Sorted hashes of the words whose log odds for toxic texts are significant (fit repeats the test exactly)."""
    bad, good = F.col("bad"), F.col("good")
    cells = [bad + 0.5, n1 - bad + 0.5, good + 0.5, n0 - good + 0.5]
    odds = F.log(cells[0]) - F.log(cells[1]) - F.log(cells[2]) + F.log(cells[3])
    error = F.sqrt(sum((1 / c for c in cells), F.lit(0.0)))
    counted = rows.select("toxic", "keys").mapInArrow(word_counts, "key long, bad long, good long").groupBy("key").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    got = counted.where(odds / error >= Z_LEAST - 1e-6).select("key").toArrow()
    return np.sort(np.asarray(got.column("key")).astype(np.int64).view(np.uint64))


def restricted(rows: DataFrame, vocab: np.ndarray) -> pa.Table:
    """(id, toxic, size, slots, counts) of the rows, with words of the vocabulary only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            slots, counts = [], []
            for k, n in zip(b.column(3), b.column(4), strict=True):
                k, n = np.frombuffer(k.as_buffer(), np.uint64), np.frombuffer(n.as_buffer(), np.int32)
                at = np.minimum(np.searchsorted(vocab, k), len(vocab) - 1)
                hit = vocab[at] == k
                slots.append(at[hit].astype(np.int32).tobytes())
                counts.append(n[hit].tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(slots, pa.binary()), pa.array(counts, pa.binary())], ["id", "toxic", "size", "slots", "counts"])

    return rows.mapInArrow(run, "id long, toxic int, size long, slots binary, counts binary").toArrow().sort_by([("id", "ascending"), ("slots", "ascending")])


def labelled(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, most: int) -> tuple[np.ndarray, list[np.ndarray], list[np.ndarray], np.ndarray] | None:
    """(toxic, word hashes, their counts, numbers of features) of a bounded sample of labelled texts, as fit
    takes them. The executors count the words and the driver receives those tied to toxicity only."""
    rows = settled(features_of_rows(docs, labels, id_col, text_col, most))
    n, n1 = rows.agg(F.count("*"), F.count_if(F.col("toxic") > 0)).first()
    if not 0 < n1 < n:
        return None
    vocab = tied_words(rows, n1, n - n1)
    if not len(vocab):
        return None
    got = restricted(rows, vocab)
    slots, counts = ([np.frombuffer(x.as_py(), np.int32) for x in got.column(c)] for c in ("slots", "counts"))
    return np.asarray(got.column("toxic")) > 0, [vocab[x] for x in slots], counts, np.asarray(got.column("size"))


def fit(toxic: np.ndarray, keys: list[np.ndarray], counts: list[np.ndarray], size: np.ndarray | None = None, max_features: int = MAX_FEATURES, steps: int = STEPS) -> Model:
    """The model of rows with distinct word hashes and their counts. Words that no model would choose may be
    left out of the rows; size then has the rows' whole numbers of features."""
    none = Model(np.zeros(0, np.uint64), np.zeros(0), np.array([20.0, 21.0]))
    if not toxic.any() or toxic.all():
        return none
    vocab, code = np.unique(np.concatenate(keys), return_inverse=True)
    code, row, many = code.astype(np.int32), np.repeat(np.arange(len(keys), dtype=np.int32), [len(k) for k in keys]), np.concatenate(counts)
    bad = np.bincount(code[toxic[row]], minlength=len(vocab))
    good = np.bincount(code, minlength=len(vocab)) - bad
    n1, n0 = toxic.sum(), (~toxic).sum()
    odds = np.log((bad + 0.5) / (n1 - bad + 0.5)) - np.log((good + 0.5) / (n0 - good + 0.5))
    z = odds / np.sqrt(1 / (bad + 0.5) + 1 / (n1 - bad + 0.5) + 1 / (good + 0.5) + 1 / (n0 - good + 0.5))
    chosen = np.flatnonzero(z >= Z_LEAST)
    chosen = np.sort(chosen[np.argsort(-z[chosen], kind="stable")[:max_features]])
    if not len(chosen):
        return none
    slot = np.full(len(vocab), -1, np.int32)
    slot[chosen] = np.arange(len(chosen))
    kept = slot[code] >= 0
    r, f = row[kept], slot[code[kept]]
    size = np.bincount(row, many, len(keys)) if size is None else size
    tied = np.bincount(r, many[kept], len(keys)) / np.maximum(size, 1)
    grade = toxic.astype(int) + (toxic & (tied >= np.median(tied[toxic])))
    scale = np.clip(odds[chosen], -6, 6)
    value = damped(many[kept])
    del code, row, many, kept, bad, good
    # Adam on the mean log loss of the cumulative links
    per_row = np.full(len(keys), 1 / len(keys))
    w, theta = np.full(len(chosen), 0.3), np.array([1.0, np.log(2.0)])  # theta_1 = theta_0 + exp(second)
    m1, m2 = np.zeros(len(w) + 2), np.zeros(len(w) + 2)
    for t in range(1, steps + 1):
        score = np.bincount(r, (w * scale)[f] * value, len(keys))
        cut = np.array([theta[0], theta[0] + np.exp(theta[1])])
        p = sigmoid(score[:, None] - cut)
        # likelihood of the grade as a difference of neighbouring probabilities
        edge = np.concatenate([np.ones((len(p), 1)), p, np.zeros((len(p), 1))], 1)
        i = np.arange(len(p))
        like = np.maximum(edge[i, grade] - edge[i, grade + 1], 1e-9)
        slope = edge * (1 - edge)
        d_score = -per_row * (slope[i, grade] - slope[i, grade + 1]) / like
        d_cut = np.stack([per_row * ((grade == k + 1) * -1.0 + (grade == k)) * -slope[:, k + 1] / like for k in (0, 1)], 1).sum(0)
        grad = np.concatenate([np.bincount(f, d_score[r] * value, len(w)) * scale + L2 * w / len(keys), [d_cut.sum(), d_cut[1] * np.exp(theta[1])]])
        m1, m2 = 0.9 * m1 + 0.1 * grad, 0.99 * m2 + 0.01 * grad**2
        step = 0.05 * (m1 / (1 - 0.9**t)) / (np.sqrt(m2 / (1 - 0.99**t)) + 1e-10)
        w, theta = w - step[:-2], theta - step[-2:]
    return Model(vocab[chosen], w * scale, np.array([theta[0], theta[0] + np.exp(theta[1])]))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", max_rows: int = MAX_ROWS) -> Model:
    rows = labelled(docs, labels, id_col, text_col, max_rows)
    return fit(*(rows or (np.zeros(0, bool), [], [])))


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs with _severity (expected grade), _grade (most probable) and _toxic (P(grade > 0) >= 1/2)."""
    at, wide = place(docs, text_col), by_position(docs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lookup = words.Lookup(model.keys)
        for b in batches:
            total = []
            for c in words.chunks(b.column(at).cast(pa.string()), words.ALNUM, lower=True):
                where, which = lookup.found(c.hashes(*PREFIXES).reshape(-1))
                where = where // (1 + len(PREFIXES))
                own = np.searchsorted(c.first, where, "right") - 1
                pair, n = np.unique(own * np.int64(len(model.keys) + 1) + which, return_counts=True)
                weight = np.append(model.weights, 0.0)[pair % (len(model.keys) + 1)]
                total.append(np.bincount(pair // (len(model.keys) + 1), weight * damped(n), c.hi - c.lo))
            p = model.exceed(np.concatenate(total) if total else np.zeros(0))
            grades = np.stack([1 - p[:, 0], p[:, 0] - p[:, 1], p[:, 1]], 1).argmax(1)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(p.sum(1)), pa.array(grades.astype(np.int32)), pa.array(p[:, 0] >= 0.5)], [*b.schema.names, "_severity", "_grade", "_toxic"])

    added = [T.StructField("_severity", T.DoubleType()), T.StructField("_grade", T.IntegerType()), T.StructField("_toxic", T.BooleanType())]
    return restored(wide.mapInArrow(run, T.StructType([*wide.schema.fields, *added])), docs.columns, [f.name for f in added])
