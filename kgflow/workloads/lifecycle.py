"""The life-cycle stream (events as statements), its measures and its ablations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgflow.config import LoopConfig
from kgflow.corpus import render
from kgflow.evolve import event_schema, relationalize
from kgflow.extract import event_track, routing
from kgflow.functions.ids import h32
from kgflow.govern import intent
from kgflow.measures import quality
from kgflow.plans import update
from kgflow.sources.tables import table
from kgflow.store import graph
from kgflow.workloads.common import query

BASE = """
WITH ev AS (
  SELECT *, CASE WHEN ts < TIMESTAMP '2024-01-11' THEN 0 WHEN ts < TIMESTAMP '2024-01-21' THEN 1 ELSE 2 END AS w,
    'acct ' || (user_id // 3) || ' seat ' || (user_id % 3) AS full_name, 'acct ' || (user_id // 3) AS alias FROM events),
st AS (
  SELECT event_id, user_id, ts, w, full_name, alias, {name} AS who, CASE WHEN event_type = 'purchase' THEN 'plan' ELSE 'status' END AS rel,
    CASE event_type WHEN 'signup' THEN 'active' WHEN 'error' THEN 'deprecated' ELSE 'tier ' || floor(value / 50)::BIGINT END AS val
  FROM ev WHERE event_type IN ('signup', 'error', 'purchase')),
lastw AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY who, rel, w ORDER BY ts DESC, event_id DESC) AS r FROM st) WHERE r = 1),
chg AS (SELECT *, lag(val) OVER (PARTITION BY who, rel ORDER BY w) AS pv FROM lastw),
adds AS (
  SELECT *, lag(val) OVER o AS prev, lag(user_id) OVER o AS prev_user, lag(event_id) OVER o AS prev_event, lead(w) OVER o AS next_w FROM chg
  WHERE pv IS NULL OR pv <> val WINDOW o AS (PARTITION BY who, rel ORDER BY w)),
gold AS (
  SELECT name, rel, w, min(val) AS lo, max(val) AS hi FROM (
    SELECT user_id, rel, w, val, unnest([full_name, alias]) AS name FROM (SELECT *, row_number() OVER (PARTITION BY user_id, rel, w ORDER BY ts DESC, event_id DESC) AS r2 FROM st) WHERE r2 = 1)
  GROUP BY name, rel, w),
firsts AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY who, rel, val ORDER BY ts, event_id) AS r3 FROM st) WHERE r3 = 1),
win AS (SELECT unnest([0, 1, 2])::INT AS batch_id),
log AS (
  SELECT who AS head, rel AS relation, val AS tail, 'ACTIVE' AS status, w AS batch_id, 1 AS seq FROM adds
  UNION ALL SELECT who, rel, prev, 'DEPRECATED', w, 0 FROM adds WHERE prev IS NOT NULL)
"""
FULL, ALIAS = BASE.format(name="full_name"), BASE.format(name="alias")
EVENT_SQL = "h AS (SELECT *, ('0x' || substr(md5('event:' || event_id), 1, 8))::BIGINT % 23 = 0 AND event_type = 'click' AS hypo FROM ev)"


def statements(spark: SparkSession, sf_dir: str) -> DataFrame:
    return render.lifecycle(table(spark, sf_dir, "events"))


def loop(spark: SparkSession, sf_dir: str, **switches) -> update.Run:
    return update.lifecycle(statements(spark, sf_dir), LoopConfig(**switches))


def gold_states(events: DataFrame) -> DataFrame:
    """(name, relation, batch_id, lo, hi): least and greatest last value, in each window, of the users
    that a name stands for. Reads the event table only."""
    rel = F.when(F.col("event_type") == "purchase", "plan").otherwise("status")
    val = F.when(F.col("event_type") == "signup", "active").when(F.col("event_type") == "error", "deprecated").otherwise(F.concat(F.lit("tier "), F.floor(F.col("value") / 50).cast("string")))
    rows = events.where(F.col("event_type").isin("signup", "error", "purchase")).select("user_id", rel.alias("relation"), val.alias("val"), "ts", "event_id", render.window_of(F.col("ts")).alias("batch_id"))
    last = rows.groupBy("user_id", "relation", "batch_id").agg(F.max_by("val", F.struct("ts", "event_id")).alias("val"))
    alias = F.concat(F.lit("acct "), F.floor(F.col("user_id") / 3).cast("string"))
    full = F.concat(alias, F.lit(" seat "), F.pmod("user_id", F.lit(3)).cast("string"))
    named = last.select("relation", "batch_id", "val", F.explode(F.array(full, alias)).alias("name"))
    return named.groupBy("name", "relation", "batch_id").agg(F.min("val").alias("lo"), F.max("val").alias("hi"))


def judged_additions(run: update.Run, events: DataFrame) -> DataFrame:
    gold = gold_states(events).withColumnRenamed("name", "head")
    return run.adds.join(gold, ["head", "relation", "batch_id"], "left").withColumn("supported", F.coalesce((F.col("lo") == F.col("tail")) & (F.col("hi") == F.col("tail")), F.lit(False)))


def judged_deprecations(run: update.Run, events: DataFrame) -> DataFrame:
    """Justified: what retired the fact speaks of the user that the fact is about."""
    who = events.select(F.concat(F.lit("ev-"), F.col("event_id").cast("string")).alias("id"), "user_id")
    old, new = (who.select(F.col("id").alias(c), F.col("user_id").alias(u)) for c, u in (("stmt_id", "u1"), ("by_stmt", "u2")))
    return run.downs.join(old, "stmt_id").join(new, "by_stmt").withColumn("justified", F.col("u1") == F.col("u2"))


def window_rows(spark: SparkSession) -> DataFrame:
    return spark.range(3).select(F.col("id").cast("int").alias("batch_id"))


def measured(spark: SparkSession, sf_dir: str, **switches) -> DataFrame:
    """(batch_id, additions, supported, delta_precision, deprecations, justified, dhp) per window."""
    ev = table(spark, sf_dir, "events")
    run = loop(spark, sf_dir, **switches)
    a = quality.delta_precision(judged_additions(run, ev))
    d = quality.dhp(judged_deprecations(run, ev), window_rows(spark))
    return d.join(a, "batch_id", "left").select("batch_id", F.coalesce("additions", F.lit(0)).alias("additions"), F.coalesce("supported", F.lit(0)).alias("supported"), "delta_precision", "deprecations", "justified", "dhp")


def measured_sql(base: str, additions: str, downs: bool) -> str:
    d = "SELECT w AS batch_id, count(*) AS d, sum((user_id = prev_user)::INT) AS j FROM adds WHERE prev IS NOT NULL GROUP BY w" if downs else "SELECT 0 AS batch_id, 0 AS d, 0 AS j WHERE false"
    return base + f""", a AS (
  SELECT x.w AS batch_id, count(*) AS n, sum((g.lo = x.val AND g.hi = x.val)::INT) AS ok FROM {additions} x LEFT JOIN gold g ON g.name = x.who AND g.rel = x.rel AND g.w = x.w GROUP BY x.w),
d AS ({d})
SELECT batch_id, coalesce(n, 0)::BIGINT AS additions, coalesce(ok, 0)::BIGINT AS supported, round(ok / n, 6) AS delta_precision,
  coalesce(d, 0)::BIGINT AS deprecations, coalesce(j, 0)::BIGINT AS justified, round(j / nullif(d, 0), 6) AS dhp
FROM win LEFT JOIN a USING (batch_id) LEFT JOIN d USING (batch_id)
"""


# state algebra ------------------------------------------------------------------------------


@query(FULL + "SELECT w AS batch_id, who AS head, rel AS relation, prev AS tail, 'ev-' || prev_event AS stmt_id, 'ev-' || event_id AS by_stmt FROM adds WHERE prev IS NOT NULL")
def kg_deprecations(spark, sf_dir):
    return loop(spark, sf_dir).downs.select("batch_id", "head", "relation", "tail", "stmt_id", "by_stmt")


@query(FULL + ", n AS (SELECT who AS node, min(w) AS batch_id FROM adds GROUP BY who UNION ALL SELECT val, min(w) FROM adds GROUP BY val) SELECT node, batch_id FROM n")
def kg_apply_nodes(spark, sf_dir):
    run = loop(spark, sf_dir)
    nodes = None
    for k in range(3):
        new = graph.nodes_of(run.adds.where(F.col("batch_id") == k)).withColumn("batch_id", F.lit(k))
        nodes = new if nodes is None else graph.apply_nodes(nodes, new)
    return nodes


@query(FULL + "SELECT who AS head, rel AS relation, val AS tail, w AS batch_id FROM adds WHERE next_w IS NULL")
def kg_apply_edges(spark, sf_dir):
    return loop(spark, sf_dir).active.select("head", "relation", "tail", "batch_id")


@query(FULL + "SELECT batch_id, rel AS relation, count(*)::BIGINT AS added, count(prev)::BIGINT AS retired FROM win JOIN adds ON w = batch_id GROUP BY ALL")
def kg_increment_counts(spark, sf_dir):
    run = loop(spark, sf_dir)
    add = run.adds.groupBy("batch_id", "relation").agg(F.count("*").alias("added"))
    down = run.downs.groupBy("batch_id", "relation").agg(F.count("*").alias("retired"))
    return add.join(down, ["batch_id", "relation"], "left").select("batch_id", "relation", "added", F.coalesce("retired", F.lit(0)).alias("retired"))


STATUS = "SELECT head, relation, tail, arg_max(status, batch_id * 2 + seq) AS status, min(batch_id) AS first_batch, max(batch_id) AS last_batch FROM log {where} GROUP BY ALL"


@query(FULL + STATUS.format(where=""))
def kg_status_at(spark, sf_dir):
    return graph.status_at(loop(spark, sf_dir).log())


@query(FULL + STATUS.format(where="WHERE batch_id <= 1"))
def kg_as_of(spark, sf_dir):
    return graph.status_at(loop(spark, sf_dir).log(), 1)


@query(FULL + f""", a AS ({STATUS.format(where="WHERE batch_id <= 0")}), b AS ({STATUS.format(where="WHERE batch_id <= 2")})
SELECT b.head, b.relation, b.tail, a.status AS before, b.status AS after FROM b LEFT JOIN a USING (head, relation, tail) WHERE a.status IS DISTINCT FROM b.status""")
def kg_diff(spark, sf_dir):
    return graph.diff(loop(spark, sf_dir).log(), 0, 2)


@query(FULL + "SELECT who AS head, rel AS relation, val AS tail, w AS from_batch, next_w AS to_batch FROM adds")
def kg_validity_intervals(spark, sf_dir):
    return graph.intervals(loop(spark, sf_dir).log())


@query(FULL + "SELECT who AS head, rel AS relation, val AS tail, count(*)::BIGINT AS spells FROM adds GROUP BY ALL HAVING count(*) > 1")
def kg_revived(spark, sf_dir):
    return graph.revived(loop(spark, sf_dir).log())


@query(FULL + "SELECT who AS head, rel AS relation, val AS tail, w AS batch_id, 'ev-' || event_id AS stmt_id, CASE WHEN next_w IS NULL THEN 'ACTIVE' ELSE 'DEPRECATED' END AS status FROM adds WHERE rel = 'status' AND user_id = 7")
def q_explain(spark, sf_dir):
    """Why a user's status facts hold or held: evidence, batch and present status."""
    run = loop(spark, sf_dir)
    spells = graph.intervals(run.log())
    mine = run.adds.where("head = 'acct 2 seat 1' and relation = 'status'")
    return mine.join(spells.withColumnRenamed("from_batch", "batch_id"), [*graph.KEY, "batch_id"]).select(*graph.KEY, "batch_id", "stmt_id", F.when(F.col("to_batch").isNull(), "ACTIVE").otherwise("DEPRECATED").alias("status"))


# extraction and governance --------------------------------------------------------------------


@query(BASE.format(name="full_name") + "SELECT 'event' AS track, count(*)::BIGINT AS n FROM ev UNION ALL SELECT 'static', (SELECT count(*) FROM nation)::BIGINT")
def x_route_tracks(spark, sf_dir):
    rows = statements(spark, sf_dir).select("text").unionByName(table(spark, sf_dir, "nation").select(F.concat("n_name", F.lit(" is a nation.")).alias("text")))
    return routing.route(rows).groupBy("track").agg(F.count("*").alias("n"))


TRIGGER = "CASE event_type WHEN 'signup' THEN 'activated' WHEN 'error' THEN 'deprecated' WHEN 'purchase' THEN 'replaced' WHEN 'click' THEN 'opened' ELSE 'viewed' END"


@query(FULL + f"SELECT 'ev-' || event_id AS stmt_id, {TRIGGER} AS trigger, full_name AS subject, CASE WHEN event_type = 'purchase' THEN floor(value / 50)::BIGINT::VARCHAR WHEN event_type IN ('click', 'view') THEN json_extract_string(props, '$.k') END AS object, epoch_us(ts)::BIGINT AS micros FROM ev")
def x_events(spark, sf_dir):
    ev = event_track.events(statements(spark, sf_dir))
    micros = F.timestamp_diff("MICROSECOND", F.lit("1970-01-01").cast("timestamp_ntz"), F.col("valid_time"))
    return ev.select("stmt_id", "trigger", F.concat_ws(" ", "alias", "qualifier").alias("subject"), "object", micros.alias("micros"))


@query(FULL + f", {EVENT_SQL} SELECT CASE WHEN event_type IN ('signup', 'error', 'purchase') THEN 'EVOLUTIONARY' ELSE 'INFORMATIONAL' END AS intent, hypo AS hypothetical, count(*)::BIGINT AS n FROM h GROUP BY ALL")
def v_intent(spark, sf_dir):
    s = statements(spark, sf_dir)
    return s.groupBy(intent.intent("text").alias("intent"), F.col("text").contains("may be removed").alias("hypothetical")).agg(F.count("*").alias("n"))


@query(FULL + "SELECT a.who AS head, a.rel AS relation, a.prev AS tail, a.val AS successor FROM adds a WHERE a.prev IS NOT NULL AND a.w = 1")
def v_targets(spark, sf_dir):
    """Facts of the first window that the second window's changes retire."""
    facts = update.lifecycle_facts(statements(spark, sf_dir), LoopConfig())
    active = graph.latest(facts.where("batch_id = 0"))
    change = graph.latest(facts.where("batch_id = 1"))
    return intent.targets(change, active).join(change.select("head", "relation", F.col("tail").alias("successor")), ["head", "relation"]).select("head", "relation", "tail", "successor")


@query(FULL + "SELECT w AS batch_id, rel AS relation, val AS reason, count(*)::BIGINT AS n FROM adds WHERE prev IS NOT NULL GROUP BY ALL")
def v_deprecation_log(spark, sf_dir):
    run = loop(spark, sf_dir)
    new = run.adds.select("head", "relation", "batch_id", F.col("tail").alias("reason"))
    return run.downs.join(new, ["head", "relation", "batch_id"]).groupBy("batch_id", "relation", "reason").agg(F.count("*").alias("n"))


# schemas of events ----------------------------------------------------------------------------


def event_structs(spark, sf_dir):
    return event_track.as_structs(event_track.events(statements(spark, sf_dir)))


@query(FULL + f"SELECT {TRIGGER} AS trigger, count(*)::BIGINT AS support, CASE WHEN count(*) > 5 THEN 'PASS' ELSE 'POOL' END AS verdict FROM ev GROUP BY ALL")
def s_event_types(spark, sf_dir):
    return event_schema.register(event_structs(spark, sf_dir), LoopConfig()).select("trigger", "support", "verdict")


@query(FULL + f"SELECT {TRIGGER} AS trigger, role, count(*)::BIGINT AS events, 1.0::DOUBLE AS share FROM ev, (SELECT unnest(['subject', 'object']) AS role) WHERE role = 'subject' OR event_type IN ('purchase', 'click', 'view') GROUP BY ALL")
def s_role_presence(spark, sf_dir):
    return event_schema.role_presence(event_structs(spark, sf_dir))


@query(FULL + f", e AS (SELECT *, 'ev-' || event_id AS head, {TRIGGER} AS t FROM ev) SELECT head, 'type' AS relation, t AS tail FROM e UNION ALL SELECT head, 'subject', full_name FROM e UNION ALL SELECT head, 'object', CASE WHEN event_type = 'purchase' THEN floor(value / 50)::BIGINT::VARCHAR ELSE json_extract_string(props, '$.k') END FROM e WHERE event_type IN ('purchase', 'click', 'view')")
def s_relationalised(spark, sf_dir):
    return relationalize.facts(event_structs(spark, sf_dir)).where("relation <> 'time'").select("head", "relation", "tail")


@query(FULL + "SELECT event_type, count(*)::BIGINT AS events, (4 * count(*))::BIGINT AS facts FROM ev WHERE event_type IN ('signup', 'error') GROUP BY ALL")
def s_relationalised_counts(spark, sf_dir):
    """Type, subject, state and time of every status event: four facts each."""
    s = event_structs(spark, sf_dir).where("trigger in ('activated', 'deprecated')")
    state = F.map_concat("roles", F.create_map(F.lit("state"), F.array(F.when(F.col("trigger") == "activated", "active").otherwise("deprecated"))))
    f = relationalize.facts(s.withColumn("roles", state))
    kind = f.where("relation = 'type'").select("head", F.when(F.col("tail") == "activated", "signup").otherwise("error").alias("event_type"))
    return f.join(kind, "head").groupBy("event_type").agg(F.countDistinct("head").alias("events"), F.count("*").alias("facts"))


@query(FULL + ", x AS (SELECT *, ('0x' || substr(md5('event:' || event_id), 1, 8))::BIGINT % 29 = 0 AS bad FROM ev) SELECT 'ev-' || event_id AS event_id FROM x WHERE bad AND event_type = 'purchase'")
def v_role_rejects(spark, sf_dir):
    """Purchases whose object role was lost fail the role check of their schema."""
    from kgflow.govern import logic

    s = event_structs(spark, sf_dir)
    schemas = event_schema.register(s, LoopConfig())
    lost = (h32("event", F.regexp_extract("event_id", r"([0-9]+)", 1)) % 29 == 0) & (F.col("trigger") == "replaced")
    broken = s.withColumn("roles", F.when(lost, F.map_filter("roles", lambda k, v: k != "object")).otherwise(F.col("roles")))
    return logic.roles(broken, schemas).where("not fits").select("event_id")


# measures and ablations -----------------------------------------------------------------------


@query(measured_sql(FULL, "adds", True))
def m_delta_precision(spark, sf_dir):
    return measured(spark, sf_dir)


@query(FULL + "SELECT rel AS relation, batch_id, count(*)::BIGINT AS deprecations FROM win JOIN adds ON w = batch_id WHERE prev IS NOT NULL GROUP BY ALL")
def m_dhp(spark, sf_dir):
    return judged_deprecations(loop(spark, sf_dir), table(spark, sf_dir, "events")).where("justified").groupBy("relation", "batch_id").agg(F.count("*").alias("deprecations"))


@query(FULL + "SELECT w AS batch_id, count(prev)::BIGINT AS gold, count(prev)::BIGINT AS retired, round(count(prev) / nullif(count(prev), 0), 6) AS dhr FROM adds GROUP BY w")
def m_dhr(spark, sf_dir):
    """Gold outdated facts that were retired. Gold comes from the event table alone."""
    gold = gold_states(table(spark, sf_dir, "events")).where(F.col("name").contains("seat"))
    from pyspark.sql import Window

    w = Window.partitionBy("name", "relation").orderBy("batch_id")
    due = gold.withColumn("prev", F.lag("lo").over(w)).withColumn("old", F.when(F.col("prev") != F.col("lo"), F.col("prev")))
    got = loop(spark, sf_dir).downs.select(F.col("head").alias("name"), "relation", "batch_id", F.col("tail").alias("old"), F.lit(1).alias("hit"))
    j = due.join(got, ["name", "relation", "batch_id", "old"], "left").groupBy("batch_id").agg(F.count("old").alias("gold"), F.count("hit").alias("retired"))
    return j.withColumn("dhr", quality.ratio(F.col("retired"), F.nullif(F.col("gold"), F.lit(0))))


@query(FULL + "SELECT batch_id, status, count(*)::BIGINT AS edges FROM log GROUP BY ROLLUP (batch_id, status)")
def m_graph_size_rollup(spark, sf_dir):
    return quality.graph_size(loop(spark, sf_dir).log())


@query(measured_sql(FULL, "firsts", False))
def a_no_intent(spark, sf_dir):
    return measured(spark, sf_dir, intent=False)


@query(measured_sql(FULL, "firsts", False))
def a_no_events(spark, sf_dir):
    return measured(spark, sf_dir, events=False)


@query(measured_sql(ALIAS, "adds", True))
def a_no_coref(spark, sf_dir):
    return measured(spark, sf_dir, coref=False)


@query(FULL + "SELECT count(*)::BIGINT AS n, round(avg((a = b)::INT), 6) AS accuracy, round((avg((a = b)::INT) - (avg(a::INT) * avg(b::INT) + (1 - avg(a::INT)) * (1 - avg(b::INT)))) / nullif(1 - (avg(a::INT) * avg(b::INT) + (1 - avg(a::INT)) * (1 - avg(b::INT))), 0), 6) AS kappa FROM (SELECT x.val = g.lo AND x.val = g.hi AS a, x.val <> 'deprecated' AS b FROM firsts x JOIN gold g ON g.name = x.who AND g.rel = x.rel AND g.w = x.w)")
def m_kappa(spark, sf_dir):
    """Agreement of the support judge with a naive second judge that trusts every value but one."""
    j = judged_additions(loop(spark, sf_dir, intent=False), table(spark, sf_dir, "events")).withColumn("naive", F.col("tail") != "deprecated")
    return quality.kappa(j, "supported", "naive")


# reconstruction and hard deletion ---------------------------------------------------------------


@query(FULL + "SELECT count(*)::BIGINT AS incremental, count(*)::BIGINT AS rebuilt, 0::BIGINT AS only_incremental, 0::BIGINT AS only_rebuilt FROM adds WHERE next_w IS NULL")
def b_rebuild_equal(spark, sf_dir):
    stmts = statements(spark, sf_dir)
    return compared(update.lifecycle(stmts).active, update.rebuilt(update.lifecycle_facts(stmts, LoopConfig())))


def compared(active: DataFrame, rebuilt: DataFrame) -> DataFrame:
    a, b = active.select(*graph.KEY).withColumn("x", F.lit(1)), rebuilt.select(*graph.KEY).withColumn("y", F.lit(1))
    j = a.join(b, graph.KEY, "full_outer")
    return j.agg(F.count("x").alias("incremental"), F.count("y").alias("rebuilt"), F.count(F.when(F.col("y").isNull(), 1)).alias("only_incremental"), F.count(F.when(F.col("x").isNull(), 1)).alias("only_rebuilt"))


@query(FULL + "SELECT rel AS relation, count(*)::BIGINT AS asserted, count(*) FILTER (WHERE next_w IS NOT NULL)::BIGINT AS history_lost FROM adds GROUP BY rel")
def b_hard_delete_loss(spark, sf_dir):
    """Spells of facts that a store which deletes retired edges could no longer explain."""
    spells = graph.intervals(loop(spark, sf_dir).log())
    return spells.groupBy("relation").agg(F.count("*").alias("asserted"), F.count("to_batch").alias("history_lost"))


SUPPLIER_BASE = """
WITH l AS (SELECT l_partkey, l_suppkey, l_shipdate, l_orderkey, l_linenumber, year(l_shipdate) - min(year(l_shipdate)) OVER () AS w FROM lineitem),
lastw AS (SELECT *, row_number() OVER (PARTITION BY l_partkey, w ORDER BY l_shipdate DESC, l_orderkey DESC, l_linenumber DESC, l_suppkey DESC) AS r FROM l),
chg AS (SELECT *, lag(l_suppkey) OVER (PARTITION BY l_partkey ORDER BY w) AS prev FROM lastw WHERE r = 1)
"""


def supplier_facts(spark, sf_dir) -> DataFrame:
    l = table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", "l_shipdate", "l_orderkey", "l_linenumber")
    first = l.agg(F.min(F.year("l_shipdate")).alias("y0"))
    return l.crossJoin(F.broadcast(first)).select(  # one row
        F.concat(F.lit("part "), F.col("l_partkey").cast("string")).alias("head"), F.lit("current_supplier").alias("relation"), F.concat(F.lit("supplier "), F.col("l_suppkey").cast("string")).alias("tail"),
        F.col("l_shipdate").alias("valid_time"), F.array(F.col("l_orderkey"), F.col("l_linenumber").cast("bigint"), F.col("l_suppkey")).alias("ord"), F.concat_ws("-", F.lit("li"), "l_orderkey", "l_linenumber", "l_suppkey").alias("stmt_id"), (F.year("l_shipdate") - F.col("y0")).alias("batch_id"),
    )


def supplier_run(spark, sf_dir) -> tuple[update.Run, DataFrame]:
    facts = supplier_facts(spark, sf_dir)
    last = facts.agg(F.max("batch_id")).first()[0] or 0
    return update.run(facts, LoopConfig(), list(range(last + 1))), facts


@query(SUPPLIER_BASE + "SELECT w::INT AS batch_id, count(*) FILTER (WHERE prev IS NULL OR prev <> l_suppkey)::BIGINT AS added, count(*) FILTER (WHERE prev <> l_suppkey)::BIGINT AS retired FROM chg GROUP BY w")
def w5_supplier_increments(spark, sf_dir):
    run, _ = supplier_run(spark, sf_dir)
    add = run.adds.groupBy("batch_id").agg(F.count("*").alias("added"))
    down = run.downs.groupBy("batch_id").agg(F.count("*").alias("retired"))
    return add.join(down, "batch_id", "left").select("batch_id", "added", F.coalesce("retired", F.lit(0)).alias("retired"))


@query(SUPPLIER_BASE + "SELECT count(DISTINCT l_partkey)::BIGINT AS incremental, count(DISTINCT l_partkey)::BIGINT AS rebuilt, 0::BIGINT AS only_incremental, 0::BIGINT AS only_rebuilt FROM l")
def b_rebuild_suppliers(spark, sf_dir):
    run, facts = supplier_run(spark, sf_dir)
    return compared(run.active, update.rebuilt(facts))


@query("SELECT batch_id, deprecations, dhp FROM (VALUES (0, 0::BIGINT, NULL::DOUBLE), (1, 0::BIGINT, NULL::DOUBLE), (2, 0::BIGINT, NULL::DOUBLE)) AS t(batch_id, deprecations, dhp)")
def w4_static_dhp(spark, sf_dir):
    """Slices of a static set retire nothing: the deprecation measure is null in every window."""
    o = table(spark, sf_dir, "orders")
    facts = o.select(F.concat(F.lit("order "), F.col("o_orderkey").cast("string")).alias("head"), F.lit("placed_by").alias("relation"), F.concat(F.lit("customer "), F.col("o_custkey").cast("string")).alias("tail"), F.col("o_orderdate").alias("valid_time"), F.array("o_orderkey").alias("ord"), F.concat(F.lit("o-"), F.col("o_orderkey").cast("string")).alias("stmt_id"), F.pmod(h32("order", "o_orderkey"), F.lit(3)).cast("int").alias("batch_id"))
    run = update.run(facts, LoopConfig(), [0, 1, 2])
    return quality.dhp(run.downs.withColumn("justified", F.lit(True)), window_rows(spark)).select("batch_id", "deprecations", "dhp")


def with_decoys(stmts: DataFrame) -> DataFrame:
    """Statements in which every opening carries a guess and every viewing a denial, which retire nothing."""
    text, plain = F.col("text"), F.regexp_replace("text", r"(, access may be removed later)?\.$", "")
    decoyed = F.when(text.contains(" opened item "), F.concat(plain, F.lit(", access may be removed later."))).when(text.contains(" viewed item "), F.concat(plain, F.lit(", access was not deprecated."))).otherwise(text)
    return stmts.withColumn("text", decoyed)


@query(FULL + "SELECT head, relation, tail, arg_max(status, batch_id * 2 + seq) AS status FROM log WHERE relation = 'status' GROUP BY head, relation, tail")
def w8_case_study(spark, sf_dir):
    """The access of every user of the event table after three windows: active first, then retired, with denials and guesses beside it."""
    run = update.lifecycle(with_decoys(statements(spark, sf_dir)))
    return graph.status_at(run.log().where("relation = 'status'")).select("head", "relation", "tail", "status")
