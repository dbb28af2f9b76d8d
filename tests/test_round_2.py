"""Faults found by the second round: each test fails on the code before."""

import datetime

import pytest

from kgflow import catalogue
from kgflow.extract import guidance
from kgflow.functions import text
from kgflow.govern import evidence
from kgflow.workloads import lifecycle

FIRST = datetime.datetime(2024, 1, 1)


def written(spark, path, **tables):
    """A folder with these tables, (rows, schema) each, and DuckDB views of them."""
    import duckdb

    con = duckdb.connect()
    for name, (rows, schema) in tables.items():
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{path}/{name}.parquet")
        con.sql(f"CREATE VIEW {name} AS SELECT * FROM '{path}/{name}.parquet/*.parquet'")
    return str(path), con


def agree(name, spark, sf_dir, con):
    got = catalogue.queries()[name](spark, sf_dir)
    want = con.sql(f"SELECT {', '.join(got.columns)} FROM ({catalogue.oracle_sql()[name]})").fetchall()
    assert sorted(tuple(r) for r in got.collect()) == sorted(want)
    return want


EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def test_range_frame_counts_nearest_seconds(spark, tmp_path):
    """Two events 604,800.4 s apart are a week apart once both are taken to the nearest second, not to the second below."""
    at = [0.6, 604801.0, 604801.5, 604802.5, 1209601.49]
    rows = [(i, FIRST + datetime.timedelta(seconds=s), 1, "view", float(i), '{"k": 1}') for i, s in enumerate(at)]
    want = agree("w_range_frame", spark, *written(spark, tmp_path, events=(rows, EVENTS)))
    assert {r[1] for r in want if r[0] == 1} == {2}


#: Six statements in our own words: an item active first, then retired, with a denial and a guess beside it.
CASE = [
    (0, 0, 900 * 3, "signup"), (1, 1, 900 * 3, "click"), (2, 2, 901 * 3, "signup"),
    (3, 11, 900 * 3, "error"), (4, 12, 901 * 3, "click"), (5, 13, 901 * 3, "view"),
]


def test_case_study_reads_the_events(spark, tmp_path):
    """The case comes from the event table: one retirement, one successor, and neither the guess nor the denial counts."""
    rows = [(i, FIRST + datetime.timedelta(days=d), u, kind, 1.0, '{"k": 4}') for i, d, u, kind in CASE]
    sf_dir, con = written(spark, tmp_path, events=(rows, EVENTS))
    want = agree("w8_case_study", spark, sf_dir, con)
    assert sorted(want) == [("acct 900 seat 0", "status", "active", "DEPRECATED"), ("acct 900 seat 0", "status", "deprecated", "ACTIVE"), ("acct 901 seat 0", "status", "active", "ACTIVE")]
    texts = [r.text for r in lifecycle.with_decoys(lifecycle.statements(spark, sf_dir)).orderBy("seq").collect()]
    assert [t.split(", ")[-1] for t in texts if ", " in t] == ["access may be removed later."] * 2 + ["access was not deprecated."]


def star_tables(orders):
    return {
        "region": ([(0, "EUROPE")], "r_regionkey int, r_name string"),
        "nation": ([(0, "FRANCE", 0)], "n_nationkey int, n_name string, n_regionkey int"),
        "customer": ([(k, f"c{k}", 0, 1.0, "TOOLS") for k in range(40)], "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string"),
        "supplier": ([(0, "s", 0, 1.0)], "s_suppkey long, s_name string, s_nationkey int, s_acctbal double"),
        "part": ([(0, "p", "Brand#1", "t", 1, 1.0)], "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double"),
        "orders": ([(k, k % 40, "O", 1.0, FIRST, "LOW") for k in range(orders)], "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string"),
    }


@pytest.mark.parametrize("name", ["m_schema_size", "s_traits", "v_signature_rejects"])
def test_static_queries_read_their_tables(spark, tmp_path, name):
    """Each query reads the tables as they are now, not statements kept from an earlier query of the application."""
    sf_dir, con = written(spark, tmp_path, **star_tables(1))
    agree(name, spark, sf_dir, con)
    rows, schema = star_tables(300)["orders"]
    spark.createDataFrame(rows, schema).coalesce(1).write.mode("overwrite").parquet(f"{sf_dir}/orders.parquet")
    agree(name, spark, sf_dir, con)


def test_bucket_search_that_meets_most_pairs_is_exact(spark, monkeypatch):
    """Where buckets hold more pairs than are worth joining, no pair is written and the exact search answers; ties go to smaller ids."""
    import numpy as np

    x = np.random.default_rng(5).integers(-2, 3, (300, 64)).astype(np.float32)
    x[7] = x[11] = x[200]
    e = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "id long, vec array<float>")
    shapes = []
    monkeypatch.setattr(guidance, "dot", lambda *c: shapes.append(c) or text.dot(*c))
    got = {(r.a, r.rank): (r.b, r.score) for r in guidance.topk_lsh(e, e, 30).collect()}
    assert not shapes
    score = x.astype(float) @ x.T.astype(float)
    np.fill_diagonal(score, -np.inf)
    want = {(a, i + 1): (int(b), float(score[a, b])) for a in range(300) for i, b in enumerate(np.argsort(-score[a], kind="stable")[:30])}
    assert got == want


def test_evidence_looks_at_a_statement_once(spark):
    """The gate of the loop groups and joins by statement alone: one exchange of either side, for both ends."""
    s = "stmt_id string, head string, relation string, tail string"
    said = spark.createDataFrame([("1", "o", "by", "x"), ("2", "o", "by", "x"), ("3", "o", "by", "x")], s)
    c = spark.createDataFrame([("1", "o", "by", "y"), ("2", "p", "by", "x"), ("3", "o", "by", "x"), ("3", "p", "by", None), ("4", "o", "by", "y")], s)
    got = evidence.verify(c, said, None)
    assert [(r.stmt_id, r.verdict) for r in got.orderBy("stmt_id", "head").collect()] == [("1", "REJECTED"), ("2", "REJECTED"), ("3", "ACCEPTED"), ("3", "ACCEPTED"), ("4", "ACCEPTED")]
    assert got._jdf.queryExecution().sparkPlan().toString().count("Join") == 1
