"""Byte-level BPE encoding and decoding with the tiktoken library.

Ranks come from a local rank file whose path is a parameter. Texts longer than
``CUT_BYTES`` are first cut at places where the split pattern always ends one match and
starts the next, so that neither the regex engine nor the merger sees a huge string; the
ids are those of the uncut text. Decoding works on raw bytes.

Edge cases: a null or empty text has no ids; a long text without a safe boundary is
encoded whole; repeated rows and null ids are encoded like any other; columns of the
input other than the named ones are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgflow.llm.frames import id_and_text

#: Characters of a text from which it is cut before it is encoded.
CUT_BYTES = 1 << 16
#: A space between two ASCII letters: the pattern's letter run stops before it and the next
#: run takes the space along, so a match boundary always lies in front of the space.
SAFE = re.compile(r"(?<=[A-Za-z]) (?=[A-Za-z])")


@lru_cache(maxsize=4)
def codec(rank_file: str, pattern: str) -> tiktoken.Encoding:
    with open(rank_file, "rb") as f:
        ranks = {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in f if line.strip())}
    return tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


def default_vocabulary() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def pieces(text: str, most: int = CUT_BYTES) -> Iterator[str]:
    """Parts of text, cut at safe boundaries only, each a little over ``most`` where possible."""
    at = 0
    while len(text) - at > most:
        cut = SAFE.search(text, at + most)
        if cut is None:
            break
        yield text[at : cut.start()]
        at = cut.start()
    yield text[at:]


def encode_text(enc: tiktoken.Encoding, text: str) -> np.ndarray:
    parts = [np.asarray(enc.encode_ordinary(p), dtype="<u4") for p in pieces(text)]
    return parts[0] if len(parts) == 1 else np.concatenate(parts)


def encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rank_file: str | None = None, pattern: str | None = None) -> DataFrame:
    """ids of every text: (id, ids array<bigint>, decoded binary)."""
    path, pat = default_vocabulary()
    path, pat = rank_file or path, pattern or pat

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = codec(path, pat)
        for b in batches:
            for lo in range(0, b.num_rows, 512):
                part = b.slice(lo, 512)
                ids = [encode_text(enc, t or "") for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([x.astype("i8") for x in ids], pa.list_(pa.int64())), pa.array([enc.decode_bytes(x.tolist()) for x in ids], pa.binary())], ["id", "ids", "decoded"])

    src = id_and_text(docs, id_col, text_col)
    return src.mapInArrow(run, "id long, ids array<bigint>, decoded binary").withColumnRenamed("id", id_col)


def decode(encoded: DataFrame, id_col: str = "doc_id", ids_col: str = "ids", rank_file: str | None = None, pattern: str | None = None) -> DataFrame:
    """Raw bytes of every list of ids: (id, decoded binary)."""
    path, pat = default_vocabulary()
    path, pat = rank_file or path, pattern or pat

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = codec(path, pat)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([enc.decode_bytes(x or []) for x in b.column(1).to_pylist()], pa.binary())], ["id", "decoded"])

    src = encoded.select(F.col(id_col).cast("long").alias("id"), F.col(ids_col).cast("array<bigint>").alias("ids"))
    return src.mapInArrow(run, "id long, decoded binary").withColumnRenamed("id", id_col)


def round_trip_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rank_file: str | None = None, pattern: str | None = None) -> DataFrame:
    """Encode, decode and digest in one pass, where the ids themselves need not leave the task:
    (id, n_tokens, ids_sha256 of little-endian 32-bit ids, decoded_sha256 of the decoded bytes)."""
    path, pat = default_vocabulary()
    path, pat = rank_file or path, pattern or pat

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = codec(path, pat)
        for b in batches:
            counts, heads, bodies = [], [], []
            for t in b.column(1):
                ids = encode_text(enc, t.as_py() or "")
                counts.append(len(ids))
                heads.append(hashlib.sha256(ids.tobytes()).hexdigest())
                bodies.append(hashlib.sha256(enc.decode_bytes(ids.tolist())).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(counts, pa.int64()), pa.array(heads, pa.string()), pa.array(bodies, pa.string())], ["id", "n_tokens", "ids_sha256", "decoded_sha256"])

    src = id_and_text(docs, id_col, text_col)
    return src.mapInArrow(run, "id long, n_tokens long, ids_sha256 string, decoded_sha256 string").withColumnRenamed("id", id_col)
