"""The corpus pipeline against its stages by brute force."""

import pytest

pytest.importorskip("kgflow.llm")
pytest.importorskip("corpus_pipeline")

import corpus_pipeline
from kgflow.llm import bpe

from tests.llm.test_text_operators import brute_lines, brute_near


def test_stages_on_small_corpus(spark, tmp_path):
    import random

    r = random.Random(6)
    vocab = [f"q{i}" for i in range(400)]
    say = lambda n: " ".join(r.choice(vocab) for _ in range(n))
    rows = [(i, "\n".join(say(9) for _ in range(6))) for i in range(120)]
    rows += [(200 + i, say(30) + " vile nasty foul " + say(8)) for i in range(40)]
    copy = rows[4][1].split()
    rows += [(300, rows[3][1]), (301, " ".join(copy[:50] + ["other"] + copy[51:])), (302, None), (303, "")]
    passage = say(30)
    rows += [(304, f"{say(20)} {passage} {say(20)}"), (305, say(25))]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    d = str(tmp_path)
    docs.write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame([(i, 1, int(200 <= i < 240)) for i, _ in rows if i % 2 == 0 and i < 300], "doc_id long, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
    spark.createDataFrame([(1, passage)], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    clean = [(i, t) for i, t in rows if not 200 <= i < 240]
    edited = brute_lines(clean)
    left = [(i, t if t is None else edited[i]) for i, t in clean if not (t and not edited[i].strip())]
    near = brute_near(left, 80)
    kept = {i: t for i, t in left if near[i][2] and i != 304}
    out = {x.doc_id: x.decoded_sha256 for x in corpus_pipeline.run(spark, d).collect()}
    assert set(out) == set(kept)
    import hashlib

    assert all(out[i] == hashlib.sha256((t or "").encode()).hexdigest() for i, t in kept.items())
    assert bpe.default_vocabulary()[0].endswith(".tiktoken")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, d).columns == docs.columns, name
