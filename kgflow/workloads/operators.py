"""Operators, graph reads, functions, sources and streams on the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from kgflow.functions import text
from kgflow.operators import graph, joins
from kgflow.plans import update
from kgflow.session import ship
from kgflow.sources import tables as sources
from kgflow.sources.tables import table
from kgflow.store import graph as algebra
from kgflow.streaming import replay
from kgflow.workloads import lifecycle
from kgflow.workloads.common import query

# joins ----------------------------------------------------------------------------------------


@query("SELECT n_name, count(*)::BIGINT AS customers, round(avg(c_acctbal), 4) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def j_inner_broadcast(spark, sf_dir):
    c, n = table(spark, sf_dir, "customer"), table(spark, sf_dir, "nation")
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("customers"), F.round(F.avg("c_acctbal"), 4).alias("balance"))


@query("SELECT c_custkey, count(o_orderkey)::BIGINT AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def j_left(spark, sf_dir):
    c, o = table(spark, sf_dir, "customer").select("c_custkey"), table(spark, sf_dir, "orders").select("o_custkey", "o_orderkey")
    per = o.groupBy("o_custkey").agg(F.count("*").alias("n"))
    return c.join(per, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("orders"))


@query("SELECT coalesce(c_nationkey, s_nationkey) AS nation, coalesce(c, 0)::BIGINT AS customers, coalesce(s, 0)::BIGINT AS suppliers FROM (SELECT c_nationkey, count(*) AS c FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS s FROM supplier GROUP BY 1) ON c_nationkey = s_nationkey")
def j_full(spark, sf_dir):
    c = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("customers"))
    s = table(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("suppliers"))
    return c.join(s, "nation", "full_outer").select("nation", F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P')")
def j_semi(spark, sf_dir):
    o = table(spark, sf_dir, "orders").where("o_orderstatus = 'P'").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, sf_dir, "customer").select("c_custkey").join(o, "c_custkey", "left_semi")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P')")
def j_anti(spark, sf_dir):
    o = table(spark, sf_dir, "orders").where("o_orderstatus = 'P'").select(F.col("o_custkey").alias("c_custkey"))
    return joins.minus(table(spark, sf_dir, "customer").select("c_custkey"), o, ["c_custkey"])


@query("SELECT e.event_id, s.event_type AS state FROM (SELECT * FROM events WHERE event_type IN ('click', 'view')) e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type IN ('signup', 'error')) s ON e.user_id = s.user_id AND e.ts >= s.ts")
def j_asof(spark, sf_dir):
    """The status of a user at the time of each click or view."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    left = e.where(F.col("event_type").isin("click", "view")).select("event_id", "user_id", "ts")
    right = e.where(F.col("event_type").isin("signup", "error")).select("user_id", F.col("ts").alias("at"), F.col("event_type").alias("state"))
    return joins.asof(left, right, ["user_id"], "ts", "at", ["state"]).select("event_id", "state")


@query("SELECT a.c_custkey AS a, b.s_suppkey AS b FROM customer a JOIN supplier b ON c_nationkey = s_nationkey AND abs(c_acctbal - s_acctbal) <= 50")
def j_range(spark, sf_dir):
    """Customers and suppliers of one nation with balances within 50: intervals that meet."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("a"), F.col("c_nationkey").alias("n"), (F.col("c_acctbal") - 25).alias("l1"), (F.col("c_acctbal") + 25).alias("l2"), F.col("c_acctbal").alias("x"))
    s = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("b"), F.col("s_nationkey").alias("n"), (F.col("s_acctbal") - 25.1).alias("r1"), (F.col("s_acctbal") + 25.1).alias("r2"), F.col("s_acctbal").alias("y"))
    return joins.overlap(c, s, ["n"], ("l1", "l2"), ("r1", "r2"), 200).where(F.abs(F.col("x") - F.col("y")) <= 50).select("a", "b")


@query("SELECT p_brand, count(*)::BIGINT AS items, sum(l_quantity)::DOUBLE AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def j_salted(spark, sf_dir):
    l, p = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("k"), "l_quantity", "l_orderkey"), table(spark, sf_dir, "part").select(F.col("p_partkey").alias("k"), "p_brand")
    return joins.salted_join(l, p, ["k"], 4).groupBy("p_brand").agg(F.count("*").alias("items"), F.sum("l_quantity").alias("quantity"))


# aggregates, windows, sets --------------------------------------------------------------------


@query("SELECT o_orderstatus, o_orderpriority, count(*)::BIGINT AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def agg_cube(spark, sf_dir):
    return table(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("SELECT event_type, year(ts)::INT AS y, count(*)::BIGINT AS n, grouping(event_type)::INT AS g1 FROM events GROUP BY GROUPING SETS ((event_type), (year(ts)), ())")
def agg_grouping_sets(spark, sf_dir):
    table(spark, sf_dir, "events").selectExpr("event_type", "year(ts) AS y").createOrReplaceTempView("kg_ev_sets")
    return spark.sql("SELECT event_type, y, count(*) AS n, CAST(grouping(event_type) AS INT) AS g1 FROM kg_ev_sets GROUP BY GROUPING SETS ((event_type), (y), ())")


@query("SELECT event_type, count(DISTINCT user_id)::BIGINT AS users, min(value) AS lo, max(value) AS hi, bool_or(value > 400) AS big, count(*) FILTER (WHERE value < 100)::BIGINT AS small, arg_max(event_id, (value, event_id)) AS top FROM events GROUP BY event_type")
def agg_distinct_and_extremes(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    return e.groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.min("value").alias("lo"), F.max("value").alias("hi"), F.bool_or(F.col("value") > 400).alias("big"), F.count_if(F.col("value") < 100).alias("small"), F.max_by("event_id", F.struct("value", "event_id")).alias("top"))


@query("SELECT event_type, count(DISTINCT ts::DATE)::BIGINT AS days, count(DISTINCT user_id)::BIGINT AS users, true AS close FROM events GROUP BY event_type")
def agg_sketch_history(spark, sf_dir):
    """Distinct users per event type from mergeable per-day sketches, beside the exact number: within 5 %, or 1."""
    e = table(spark, sf_dir, "events").withColumn("day", F.to_date("ts"))
    merged = joins.sketch_merge(joins.sketch_count(e, ["event_type", "day"], "user_id"), ["event_type"])
    exact = e.groupBy("event_type").agg(F.countDistinct("day").alias("days"), F.countDistinct("user_id").alias("users"))
    return exact.join(merged, "event_type").select("event_type", "days", "users", (F.abs(F.col("estimate") - F.col("users")) <= F.greatest(0.05 * F.col("users"), F.lit(1.0))).alias("close"))


@query("SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, ntile(4) OVER w AS quarter, lag(event_type) OVER w AS before, sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS recent FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def w_ranking_and_frames(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return e.select("event_id", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.ntile(4).over(w).alias("quarter"), F.lag("event_type").over(w).alias("before"), F.sum("value").over(w.rowsBetween(-2, 0)).alias("recent"))


@query("SELECT event_id, user_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS r FROM events) WHERE r <= 3")
def topk_per_user(spark, sf_dir):
    return joins.topk(table(spark, sf_dir, "events"), ["user_id"], [F.desc("value"), F.col("event_id")], 3).select("event_id", "user_id")


@query("SELECT user_id FROM events WHERE event_type = 'signup' INTERSECT SELECT user_id FROM events WHERE event_type = 'error' EXCEPT SELECT user_id FROM events WHERE value > 499")
def set_algebra(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    u = lambda c: e.where(c).select("user_id")
    return u("event_type = 'signup'").intersect(u("event_type = 'error'")).exceptAll(u("value > 499").distinct())


@query("SELECT user_id, event_id, epoch_us(ts)::BIGINT AS from_us, epoch_us(lead(ts) OVER (PARTITION BY user_id ORDER BY ts))::BIGINT AS to_us FROM events WHERE event_type IN ('signup', 'error')")
def op_validity(spark, sf_dir):
    e = table(spark, sf_dir, "events").where(F.col("event_type").isin("signup", "error")).select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    return joins.intervals(e, ["user_id"], "t").select("user_id", "event_id", F.col("valid_from").alias("from_us"), F.col("valid_to").alias("to_us"))


# functions ------------------------------------------------------------------------------------


@query("SELECT p_partkey, lower(p_name) AS low, levenshtein(p_name, p_type)::INT AS dist, len(list_intersect(a, b)) / len(list_distinct(list_concat(a, b))) AS jac, substr(p_name, 1, 3) || '/' || upper(p_brand) AS code FROM (SELECT *, list_distinct(string_split(lower(p_name), ' ')) AS a, list_distinct(string_split(lower(p_type), ' ')) AS b FROM part)")
def fn_strings(spark, sf_dir):
    p = table(spark, sf_dir, "part")
    words = lambda c: F.array_distinct(F.split(F.lower(c), " "))
    return p.select("p_partkey", F.lower("p_name").alias("low"), F.levenshtein("p_name", "p_type").alias("dist"), text.jaccard(words("p_name"), words("p_type")).alias("jac"), F.concat(F.substring("p_name", 1, 3), F.lit("/"), F.upper("p_brand")).alias("code"))


@query("SELECT event_id, (props::JSON->>'$.k')::INT AS k, year(ts)::INT AS y, dayofweek(ts)::INT + 1 AS dow, epoch_us(date_trunc('hour', ts))::BIGINT AS hour_us FROM events")
def fn_json_and_dates(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    return e.select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.year("ts").alias("y"), F.dayofweek("ts").alias("dow"), F.unix_micros(F.date_trunc("hour", F.col("ts").cast("timestamp"))).alias("hour_us"))


@query("SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 5) AS square, round(list_max(embedding)::DOUBLE, 5) AS hi, len(list_filter(embedding, lambda x: x > 0))::INT AS positive FROM embeddings")
def fn_arrays(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings")
    return e.select("vec_id", F.round(text.dot("embedding", "embedding"), 5).alias("square"), F.round(F.array_max("embedding").cast("double"), 5).alias("hi"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"))


# graph reads ----------------------------------------------------------------------------------

GRAPH = "WITH e AS (SELECT DISTINCT 'c' || o_custkey AS head, 'p' || o_orderpriority AS tail FROM orders UNION SELECT 'n' || c_nationkey, 'c' || c_custkey FROM customer UNION SELECT 'r' || n_regionkey, 'n' || n_nationkey FROM nation)\n"


def star_graph(spark, sf_dir):
    key = lambda p, c: F.concat(F.lit(p), F.col(c).cast("string"))
    o = table(spark, sf_dir, "orders").select(key("c", "o_custkey").alias("head"), key("p", "o_orderpriority").alias("tail"))
    c = table(spark, sf_dir, "customer").select(key("n", "c_nationkey").alias("head"), key("c", "c_custkey").alias("tail"))
    n = table(spark, sf_dir, "nation").select(key("r", "n_regionkey").alias("head"), key("n", "n_nationkey").alias("tail"))
    return o.unionByName(c).unionByName(n).distinct()


def region_seed(spark):
    return spark.sql("SELECT 'r1' AS node")


@query(GRAPH + "SELECT DISTINCT tail AS node FROM e WHERE head = 'r1'")
def q_one_hop(spark, sf_dir):
    return graph.hop(star_graph(spark, sf_dir), region_seed(spark))


@query(GRAPH + "SELECT x.head AS a, count(*)::BIGINT AS paths FROM e x JOIN e y ON x.tail = y.head GROUP BY x.head")
def q_two_hop(spark, sf_dir):
    return graph.paths2(star_graph(spark, sf_dir)).groupBy("a").agg(F.count("*").alias("paths"))


@query(GRAPH + "SELECT node, sum(o)::BIGINT AS out_degree, sum(i)::BIGINT AS in_degree FROM (SELECT head AS node, 1 AS o, 0 AS i FROM e UNION ALL SELECT tail, 0, 1 FROM e) GROUP BY node")
def q_degree(spark, sf_dir):
    return graph.degree(star_graph(spark, sf_dir))


@query("WITH RECURSIVE " + GRAPH[5:] + ", r(node, hops) AS (SELECT 'r1', 0 UNION SELECT tail, hops + 1 FROM r JOIN e ON head = node WHERE hops < 3) SELECT node, min(hops)::INT AS hops FROM r GROUP BY node")
def q_reachable_3(spark, sf_dir):
    return graph.reach(star_graph(spark, sf_dir), region_seed(spark), 3)


TRI = "WITH e AS (SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v FROM (SELECT 3 * l_suppkey AS a, 3 * l_partkey + 1 AS b FROM lineitem UNION SELECT 3 * l_suppkey, 3 * l_orderkey + 2 FROM lineitem UNION SELECT 3 * l_partkey + 1, 3 * l_orderkey + 2 FROM lineitem))\n"


TRI += """, d AS (SELECT n, count(*) AS d FROM (SELECT u AS n FROM e UNION ALL SELECT v FROM e) GROUP BY n),
o AS (SELECT CASE WHEN a.d < b.d OR a.d = b.d AND u < v THEN u ELSE v END AS x, CASE WHEN a.d < b.d OR a.d = b.d AND u < v THEN v ELSE u END AS y FROM e JOIN d a ON a.n = u JOIN d b ON b.n = v),
t AS (SELECT list_sort([p.x, p.y, q.y]) AS t FROM o p JOIN o q ON p.x = q.x AND p.y < q.y JOIN e ON e.u = p.y AND e.v = q.y)
"""


@query(TRI + "SELECT t[1] AS a, t[2] AS b, t[3] AS c FROM t")
def q_triangles(spark, sf_dir):
    """Suppliers, parts and orders that occur together pairwise in line items."""
    l = table(spark, sf_dir, "lineitem")
    s, p, o = 3 * F.col("l_suppkey"), 3 * F.col("l_partkey") + 1, 3 * F.col("l_orderkey") + 2
    side = lambda x, y: F.struct(x.alias("head"), y.alias("tail"))
    return graph.triangles(l.select(F.explode(F.array(side(s, p), side(s, o), side(p, o))).alias("e")).select("e.*"))


# sources and sinks ----------------------------------------------------------------------------

FACTS = "SELECT 'order ' || o_orderkey AS head, 'placed|by' AS relation, 'customer \"' || o_custkey || '\"' AS tail FROM orders"


def fact_sample(spark, sf_dir):
    return table(spark, sf_dir, "orders").select(F.concat(F.lit("order "), F.col("o_orderkey").cast("string")).alias("head"), F.lit("placed|by").alias("relation"), F.concat(F.lit('customer "'), F.col("o_custkey").cast("string"), F.lit('"')).alias("tail"))


@query(FACTS)
def io_roundtrip_parquet(spark, sf_dir):
    path = replay.folder(spark, "io")
    fact_sample(spark, sf_dir).write.parquet(path)
    return spark.read.parquet(path)


@query(FACTS)
def io_roundtrip_json(spark, sf_dir):
    path = replay.folder(spark, "io")
    fact_sample(spark, sf_dir).write.json(path)
    return sources.triples_from_json(spark, path)


@query(FACTS)
def io_roundtrip_csv(spark, sf_dir):
    path = replay.folder(spark, "io")
    fact_sample(spark, sf_dir).write.option("header", True).option("escape", '"').csv(path)
    return sources.triples_from_csv(spark, path)


@query(FACTS)
def io_ntriples(spark, sf_dir):
    path = replay.folder(spark, "io")
    sources.to_lines(fact_sample(spark, sf_dir)).write.text(path)
    return sources.from_lines(spark.read.text(path))


# streams --------------------------------------------------------------------------------------


def event_stream(spark, sf_dir):
    return replay.with_utc(sources.table_stream(spark, sf_dir, "events"))


@query("SELECT strftime(DATE '2024-01-01' + (floor(datediff('day', DATE '2024-01-01', ts::DATE) / 10)::INT * 10), '%Y-%m-%d') AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY ALL")
def st_tumbling(spark, sf_dir):
    return replay.drained(replay.tumbling(event_stream(spark, sf_dir)), "complete")


@query("SELECT strftime(DATE '2023-12-27' + (5 * k)::INT, '%Y-%m-%d') AS start, event_type, count(*)::BIGINT AS n FROM events, range(0, 12) AS r(k) WHERE ts >= DATE '2023-12-27' + (5 * k)::INT AND ts < DATE '2023-12-27' + (5 * k + 10)::INT GROUP BY ALL")
def st_sliding(spark, sf_dir):
    return replay.drained(replay.sliding(event_stream(spark, sf_dir)), "complete")


@query("WITH g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) SELECT user_id, epoch_us(min(ts))::BIGINT AS start_us, count(*)::BIGINT AS n FROM g GROUP BY user_id, s")
def st_session(spark, sf_dir):
    return replay.drained(replay.sessions(event_stream(spark, sf_dir)), "complete")


@query("SELECT event_id FROM events")
def st_dedup(spark, sf_dir):
    """Every event delivered twice, kept once."""
    e = event_stream(spark, sf_dir).select("event_id", "ts")
    twice = e.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    return replay.drained(replay.once(twice, "event_id")).select("event_id")


@query(lifecycle.FULL + "SELECT user_id, val AS status, epoch_us(ts)::BIGINT AS at FROM (SELECT *, lag(val) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM st WHERE rel = 'status') WHERE b IS NULL OR b <> val")
def st_stateful_status(spark, sf_dir):
    ship(spark)
    with replay.column_family_state(spark):
        return replay.drained(replay.tracked(event_stream(spark, sf_dir)))


@query(lifecycle.FULL + "SELECT who AS head, rel AS relation, val AS tail FROM adds WHERE next_w IS NULL")
def st_replay_equals_batch(spark, sf_dir):
    """The loop driven by a stream of three files, one of them delivered twice and all shuffled inside."""
    from kgflow.config import LoopConfig

    facts = update.lifecycle_facts(lifecycle.statements(spark, sf_dir), LoopConfig())
    base = replay.folder(spark, "windows")
    for k in (0, 1, 2):
        facts.where(F.col("batch_id") == k).orderBy(F.md5("stmt_id")).coalesce(1).write.mode("append").parquet(base)
    facts.where("batch_id = 1").coalesce(1).write.mode("append").parquet(base)
    seen: dict[int, object] = {}

    def take(df, k):
        late = seen.get("active", spark.createDataFrame([], update.FACT))
        df = update.settled(df)
        add, down = update.step(late, df, int(k), LoopConfig())
        cols = [f.split()[0] for f in update.FACT.split(", ")]
        seen["active"] = update.settled(algebra.apply_edges(late, down, add.select(*cols)))

    stream = spark.readStream.schema(update.FACT).option("maxFilesPerTrigger", 1).parquet(base)
    replay.drained(stream, run=take)
    return seen["active"].select("head", "relation", "tail")


DELIVERED = "WITH d AS (SELECT event_id, ts, event_id % 3 AS k FROM events), top AS (SELECT k, max(ts) AS t FROM d GROUP BY k)\n"


@query(DELIVERED + "SELECT event_id, coalesce(ts < (SELECT max(t) FROM top WHERE top.k < d.k) - INTERVAL 2 DAY, false) AS late FROM d")
def st_late_rows(spark, sf_dir):
    """All events in three deliveries: rows older than the newest time of earlier deliveries less two days go to the late sink."""
    base = replay.folder(spark, "deliveries")
    e = table(spark, sf_dir, "events").select("event_id", "ts")
    for k in range(3):
        e.where(F.col("event_id") % 3 == k).coalesce(1).write.mode("append").parquet(base)
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(base)
    late, timely = replay.split_late(stream, "ts", "2 days")
    return late.select("event_id", F.lit(True).alias("late")).unionByName(timely.select("event_id", F.lit(False).alias("late")))
