"""Judges on hand-made cases, the deleting store, and late rows over several batches."""

import datetime as dt

from pyspark.sql import functions as F

from kgflow.baselines import hard_delete
from kgflow.corpus import segment
from kgflow.measures import verdicts
from kgflow.streaming import replay


def test_support_verdicts(spark):
    gold = spark.createDataFrame([("a", "r", "x", 0), ("a", "r", "y", 1)], "head string, relation string, tail string, batch_id int")
    stmts = spark.createDataFrame([("s1", "a told x"), ("s2", "a alone"), ("s3", None), ("s4", "a told z")], "stmt_id string, text string")
    adds = spark.createDataFrame(
        [("a", "r", "x", 0, "s1"), ("a", "r", "x", 1, "s1"), ("a", "r", "x", 0, "s2"), ("a", "r", "x", 0, "s3"), ("a", "r", "z", 0, "s4"), ("a", "r", "x", 0, "gone")],
        "head string, relation string, tail string, batch_id int, stmt_id string",
    )
    got = {(r.tail, r.batch_id, r.stmt_id): (r.verdict, r.request) for r in verdicts.support(adds, gold, stmts).collect()}
    short = {k: v[0].split("_")[0] for k, v in got.items()}
    assert short == {("x", 0, "s1"): "fully", ("x", 1, "s1"): "partially", ("x", 0, "s2"): "partially", ("x", 0, "s3"): "not", ("z", 0, "s4"): "not", ("x", 0, "gone"): "not"}
    given = spark.createDataFrame([(got["z", 0, "s4"][1], "fully_supported")], "request string, verdict string")
    assert verdicts.support(adds, gold, stmts, replay=given).where("verdict = 'fully_supported'").count() == 2
    assert verdicts.support(adds.limit(0), gold, stmts).count() == 0


def test_deletion_verdicts(spark):
    downs = spark.createDataFrame([(1, "s1", "s2"), (1, "s1", "s3"), (1, "s1", "gone")], "batch_id int, stmt_id string, by_stmt string")
    about = spark.createDataFrame([("s1", 7), ("s2", 7), ("s3", 8)], "stmt_id string, subject long")
    got = {r.by_stmt: r.verdict for r in verdicts.deletion(downs, about).collect()}
    assert got == {"s2": "justified", "s3": "unjustified", "gone": "unjustified"}


def test_hard_delete(spark):
    shape = "head string, relation string, tail string, batch_id int"
    adds = spark.createDataFrame([("a", "r", "x", 0), ("a", "r", "y", 1), ("a", "r", "x", 2)], shape)
    downs = spark.createDataFrame([("a", "r", "x", 1), ("a", "r", "y", 2)], shape)
    for k, want in enumerate(("x", "y", "x")):
        assert [r.tail for r in hard_delete.after(adds, downs, list(range(k + 1))).collect()] == [want]


def test_late_rows_after_an_older_batch(spark, tmp_path):
    """The newest time of all batches before counts, not that of the last one; a batch may hold no time at all."""
    day = lambda d: dt.datetime(2024, 1, d)
    files = [[(1, day(20))], [(2, day(19)), (3, day(10))], [(4, None)], [(5, day(17)), (6, day(18))]]
    for rows in files:
        spark.createDataFrame(rows, "id long, ts timestamp").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    late, timely = replay.split_late(stream, "ts", "2 days")
    assert sorted(r.id for r in late.collect()) == [3, 5]
    assert sorted(r.id for r in timely.collect()) == [1, 2, 4, 6]


def test_containing(spark):
    docs = spark.createDataFrame([(1, 'he said "what is it, then?" twice'), (2, "what is it"), (3, None), (4, "a::b"), (5, "what is it, then? what is it, then?")], "doc_id long, text string")
    items = spark.createDataFrame([("what is it, then?",), ("::",), (None,)], "text string")
    assert sorted(r.doc_id for r in segment.containing(docs, items).collect()) == [1, 4, 5]
    assert segment.containing(docs, items.limit(0)).count() == 0
    assert segment.containing(docs.withColumn("w", F.lit(1)).withColumn("passage", F.lit("p")).select("doc_id", "text"), items).count() == 3
