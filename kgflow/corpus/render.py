"""Statements rendered from the star tables and the event table.

Texts are synthetic: a fixed set of phrasings, names in several surface forms, hypothetical
remarks, negations, wrongly typed and unsupported candidates, all placed by md5 of the keys.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgflow.functions.ids import h32

#: Ends of the first two windows of the event stream.
WINDOW_ENDS = ("2024-01-11", "2024-01-21")
#: One click in so many carries a hypothetical remark.
HYPOTHETICAL = 23
#: One order in so many names an object of the wrong type, or has a candidate its text doesn't support.
WRONG_TYPE, UNSUPPORTED, NEGATED = 17, 19, 13


def window_of(ts: Column) -> Column:
    first, second = (F.lit(x).cast("timestamp_ntz") for x in WINDOW_ENDS)
    return F.when(ts < first, 0).when(ts < second, 1).otherwise(2)


def lifecycle(events: DataFrame) -> DataFrame:
    """One statement per event: (stmt_id, seq, text, obs_time, batch_id)."""
    who = F.concat(F.lit("acct "), F.floor(F.col("user_id") / 3).cast("string"), F.lit(" seat "), F.pmod("user_id", F.lit(3)).cast("string"))
    item = F.from_json("props", "k int")["k"].cast("string")
    remark = F.when((F.col("event_type") == "click") & (h32("event", "event_id") % HYPOTHETICAL == 0), F.lit(", access may be removed later")).otherwise(F.lit(""))
    said = (
        F.when(F.col("event_type") == "signup", F.concat(F.lit("access for "), who, F.lit(" was activated")))
        .when(F.col("event_type") == "error", F.concat(F.lit("access for "), who, F.lit(" is deprecated")))
        .when(F.col("event_type") == "purchase", F.concat(F.lit("plan of "), who, F.lit(" was replaced by tier "), F.floor(F.col("value") / 50).cast("string")))
        .when(F.col("event_type") == "click", F.concat(who, F.lit(" opened item "), item, remark))
        .otherwise(F.concat(who, F.lit(" viewed item "), item))
    )
    text = F.concat(F.lit("At "), F.col("ts").cast("string"), F.lit(": "), said, F.lit("."))
    return events.select(F.concat(F.lit("ev-"), F.col("event_id").cast("string")).alias("stmt_id"), F.col("event_id").alias("seq"), text.alias("text"), F.col("ts").alias("obs_time"), window_of(F.col("ts")).alias("batch_id"))


#: Phrasings per relation: (relation, phrasing number, name that the phrasing suggests, tail first).
PHRASINGS = (
    ("placed_by", 0, "placed_by", False),
    ("placed_by", 1, "placed", True),
    ("placed_by", 2, "was_placed_by", False),
    ("has_status", 0, "has_status", False),
    ("has_status", 1, "with_status", False),
    ("has_priority", 0, "has_priority", False),
    ("has_priority", 1, "is_of_priority", False),
    ("based_in", 0, "based_in", False),
    ("based_in", 1, "is_based_in", False),
    ("in_region", 0, "in_region", False),
    ("in_region", 1, "contains", True),
    ("has_brand", 0, "has_brand", False),
    ("in_segment", 0, "in_segment", False),
)


FORMS = {
    "placed_by": [(" placed by ", False), (" placed ", True), (" was placed by ", False)],
    "has_status": [(" has status ", False), (" with status ", False)],
    "has_priority": [(" has priority ", False), (" is of priority ", False)],
    "based_in": [(" based in ", False), (" is based in ", False)],
    "in_region": [(" in region ", False), (" contains ", True)],
    "has_brand": [(" has brand ", False)],
    "in_segment": [(" in segment ", False)],
}


def _sources(t: dict[str, DataFrame]) -> list[tuple]:
    """What the facts are made of: (rows, kind of head, its key, relation, head, tail, kind of tail and its key where it is numbered)."""
    nation = t["nation"].join(F.broadcast(t["region"]), F.col("n_regionkey") == F.col("r_regionkey"))
    nations = F.broadcast(t["nation"].select("n_nationkey", "n_name"))  # 25 rows by definition of the table
    customer = t["customer"].join(nations, F.col("c_nationkey") == F.col("n_nationkey"))
    supplier = t["supplier"].join(nations, F.col("s_nationkey") == F.col("n_nationkey"))
    return [
        (nation, "nation", "n_nationkey", "in_region", F.lower("n_name"), F.lower("r_name"), None),
        (customer, "customer", "c_custkey", "based_in", _name("customer", "c_custkey"), F.lower("n_name"), None),
        (supplier, "supplier", "s_suppkey", "based_in", _name("supplier", "s_suppkey"), F.lower("n_name"), None),
        (t["customer"], "customer", "c_custkey", "in_segment", _name("customer", "c_custkey"), F.lower("c_mktsegment"), None),
        (t["part"], "part", "p_partkey", "has_brand", _name("part", "p_partkey"), F.lower("p_brand"), None),
        (t["orders"], "order", "o_orderkey", "placed_by", _name("order", "o_orderkey"), _name("customer", "o_custkey"), "o_custkey"),
        (t["orders"], "order", "o_orderkey", "has_status", _name("order", "o_orderkey"), F.lower("o_orderstatus"), None),
        (t["orders"], "order", "o_orderkey", "has_priority", _name("order", "o_orderkey"), F.lower("o_orderpriority"), None),
    ]


def _name(kind: str, key: str) -> Column:
    return F.concat(F.lit(f"{kind} "), F.col(key).cast("string"))


def _all(parts: list[DataFrame]) -> DataFrame:
    total = parts[0]
    for x in parts[1:]:
        total = total.unionByName(x)
    return total


def fact_rows(t: dict[str, DataFrame]) -> DataFrame:
    """Gold facts of the star tables with keys: (kind, key, relation, head, tail), canonical names."""
    return _all([df.select(F.lit(kind).alias("kind"), F.col(key).cast("string").alias("key"), F.lit(relation).alias("relation"), head.alias("head"), tail.alias("tail")) for df, kind, key, relation, head, tail, _ in _sources(t)])


def _shown(kind: str, key: str) -> Column:
    """A numbered name in the surface form that its md5 picks."""
    n = F.col(key).cast("string")
    v = F.pmod(h32(kind, key), F.lit(4))
    # by place, so that the md5 is made once
    forms = F.array(F.concat(F.lit(f"{kind.capitalize()}#"), F.lpad(n, 9, "0")), _name(kind, key), F.concat(F.lit(f"{kind.upper()} #"), n), F.concat(F.lit(f"{kind}-"), n))
    return F.when(F.col(key) >= 0, F.get(forms, v.cast("int"))).otherwise(_name(kind, key))


def _said(source: tuple) -> DataFrame:
    df, kind, key, relation, head, tail, other = source
    forms = FORMS[relation]
    if other:
        wrong = h32(kind, key) % WRONG_TYPE == 0
        tail = F.when(wrong, _shown("part", other)).otherwise(_shown("customer", other))
    pick = F.pmod(h32(f"say {relation} text", F.col(key).cast("string")), F.lit(len(forms))).cast("int") if len(forms) > 1 else F.lit(0)
    rows = df.select(F.lit(kind).alias("kind"), F.col(key).cast("string").alias("key"), (head if kind == "nation" else _shown(kind, key)).alias("h"), tail.alias("t"), pick.alias("form"))
    text = F.coalesce(*(F.when(F.col("form") == i, F.concat("t", F.lit(between), "h", F.lit(".")) if swapped else F.concat("h", F.lit(between), "t", F.lit("."))) for i, (between, swapped) in enumerate(forms)))
    return rows.select(F.concat_ws("-", "kind", "key", F.lit(relation)).alias("stmt_id"), text.alias("text"), "kind", "key", _slice())


def _slice() -> Column:
    return F.pmod(h32("slice", F.concat_ws(" ", "kind", "key")), F.lit(3)).cast("int").alias("batch_id")


def star_statements(t: dict[str, DataFrame]) -> DataFrame:
    """One statement per gold fact, and one negated remark for some orders:
    (stmt_id, text, kind, key, batch_id); the batch is a slice by md5. Kind and relation are known per source, so that
    no name is taken apart again."""
    o = t["orders"].where(h32("order", "o_orderkey") % NEGATED == 0).select(F.lit("order").alias("kind"), F.col("o_orderkey").cast("string").alias("key"), "o_custkey")
    remark = F.concat(F.lit("order "), F.col("key"), F.lit(" was not placed by customer "), (F.col("o_custkey") + 7).cast("string"), F.lit("."))
    denied = o.select(F.concat_ws("-", F.lit("not"), "key").alias("stmt_id"), remark.alias("text"), "kind", "key", _slice())
    return _all([*map(_said, _sources(t)), denied])
