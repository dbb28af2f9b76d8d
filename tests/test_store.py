"""User-level writes of the stored graph."""

from kgflow.store.kg import Graph


def test_add_modify_retire_compact(spark, tmp_path):
    g = Graph(spark, f"file://{tmp_path}/g")
    f = lambda *rows: spark.createDataFrame(list(rows), "head string, relation string, tail string, evidence string")
    g.add(f(("a", "status", "on", "e1"), ("b", "status", "on", "e2"), ("a", "status", "on", "e1")))
    g.modify(spark.createDataFrame([("a", "status", "on", "off", "e3")], "head string, relation string, tail string, new_tail string, evidence string"))
    g.retire(f(("b", "status", "on", "e4"), ("c", "status", "on", "e5")))
    assert [(r.head, r.tail) for r in g.active().collect()] == [("a", "off")]
    assert g.active(0).count() == 2 and g.status().count() == 3
    assert [r.evidence for r in g.explain("a").collect()] == ["e1", "e3", "e3"]
    before = sorted(g.status().collect())
    g.compact()
    assert sorted(g.status().collect()) == before and len(g.store.chain()) == 1
    g.add(f(("b", "status", "on", "e6")))
    assert g.active().count() == 2
    g.views()
    assert spark.sql("SELECT count(*) FROM kg_active").first()[0] == 2
    assert spark.sql("SELECT count(*) FROM kg_deprecations").first()[0] == 2
    g.rollback(0)
    assert g.active().count() == 2 and {r.tail for r in g.active().collect()} == {"on"}
