"""The functions and operators that users find around the methods, each against SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from kgflow.operators import functions
from kgflow.session import ship
from kgflow.sources.tables import table
from kgflow.workloads.common import query


@query("SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND (a.n_regionkey + b.n_regionkey) % 3 = 0 AND length(a.n_name) <> length(b.n_name)")
def j_theta(spark, sf_dir):
    n = table(spark, sf_dir, "nation")
    cond = (F.col("a.n_nationkey") < F.col("b.n_nationkey")) & ((F.col("a.n_regionkey") + F.col("b.n_regionkey")) % 3 == 0) & (F.length("a.n_name") != F.length("b.n_name"))
    return functions.nested_loop(n.alias("a"), n.alias("b"), cond).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"))


@query("SELECT c_mktsegment, count(*)::BIGINT AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def j_merge_hint(spark, sf_dir):
    o, c = table(spark, sf_dir, "orders").select("o_custkey", "o_totalprice"), table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    return o.hint("merge").join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("SELECT event_id FROM events WHERE ('0x' || substr(md5('sample:' || event_id), 1, 8))::BIGINT % 16 = 0")
def op_sample(spark, sf_dir):
    return functions.sample(table(spark, sf_dir, "events"), "sample", "event_id", 16).select("event_id")


@query("SELECT event_type, event_id FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY ('0x' || substr(md5('spot:' || event_id), 1, 8))::BIGINT, event_id) AS r FROM events) WHERE r <= 5")
def op_spot_check(spark, sf_dir):
    return functions.spot_check(table(spark, sf_dir, "events"), ["event_type"], "spot", "event_id", 5).select("event_type", "event_id")


@query("SELECT doc_id, md5(strip_accents(lower(text))) AS folded FROM documents")
def fn_udf_folded(spark, sf_dir):
    return table(ship(spark), sf_dir, "documents").select("doc_id", F.md5(functions.folded("text")).alias("folded"))


@query("SELECT label, list(m ORDER BY i) AS centroid FROM (SELECT label, i, round(avg(embedding[i]::DOUBLE), 6) AS m FROM (SELECT label, embedding, unnest(range(1, len(embedding) + 1)) AS i FROM embeddings) GROUP BY label, i) GROUP BY label")
def fn_udaf_centroid(spark, sf_dir):
    return functions.centroid(table(spark, sf_dir, "embeddings"), ["label"], "embedding")


@query("SELECT doc_id, no::INT AS no, md5(line) AS h FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(0, len(string_split(text, chr(10))))) AS no FROM documents) WHERE regexp_matches(line, '\\S')")
def fn_udtf_statements(spark, sf_dir):
    functions.register(ship(spark))
    table(spark, sf_dir, "documents").select("doc_id", "text").createOrReplaceTempView("surface_documents")
    return spark.sql("SELECT doc_id, s.no, md5(s.statement) AS h FROM surface_documents, LATERAL extract_statements(text) AS s")


@query("SELECT p_partkey, word, count(*)::BIGINT AS n FROM (SELECT p_partkey, unnest(string_split(p_name, ' ')) AS word FROM part) GROUP BY ALL")
def j_lateral(spark, sf_dir):
    p = table(spark, sf_dir, "part").select("p_partkey", "p_name")
    words = spark.tvf.explode(F.split(F.col("p_name").outer(), " ")).toDF("word")
    return p.lateralJoin(words).groupBy("p_partkey", "word").agg(F.count("*").alias("n"))


@query("""SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(stddev_samp(value), 6) AS deviation, mode(year(ts))::INT AS usual_year, string_agg(DISTINCT (user_id % 3)::VARCHAR, ',' ORDER BY (user_id % 3)::VARCHAR) AS seats,
  bool_and(value >= 0) AS non_negative, count(*) FILTER (WHERE value > 100)::BIGINT AS large FROM events GROUP BY event_type""")
def agg_statistics(spark, sf_dir):
    e = table(spark, sf_dir, "events").withColumn("seat", F.pmod("user_id", F.lit(3)).cast("string")).withColumn("y", F.year("ts"))
    return e.groupBy("event_type").agg(
        F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.stddev_samp("value"), 6).alias("deviation"), F.mode("y", True).alias("usual_year"),
        F.array_join(F.array_sort(F.collect_set("seat")), ",").alias("seats"), F.bool_and(F.col("value") >= 0).alias("non_negative"), F.count_if(F.col("value") > 100).alias("large"),
    )


@query("SELECT user_id, count(*) FILTER (WHERE event_type = 'signup')::BIGINT AS signup, count(*) FILTER (WHERE event_type = 'error')::BIGINT AS error, count(*) FILTER (WHERE event_type = 'purchase')::BIGINT AS purchase FROM events WHERE event_type IN ('signup', 'error', 'purchase') GROUP BY user_id")
def agg_pivot(spark, sf_dir):
    e = table(spark, sf_dir, "events").where(F.col("event_type").isin("signup", "error", "purchase"))
    return e.groupBy("user_id").pivot("event_type", ["signup", "error", "purchase"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT event_type, true AS hll, true AS theta, true AS quantiles, true AS bloom, true AS heavy FROM events GROUP BY event_type")
def agg_sketch_bounds(spark, sf_dir):
    """Sketches against exact values, as bounds that hold: distinct users by HLL and theta within 5 %, the KLL median's
    rank within 3 %, no user missed by a hash filter, and a count-min estimate of the busiest user that is not below the count."""
    e = table(spark, sf_dir, "events").select("event_type", "user_id", "value", F.pmod(F.xxhash64("event_id"), F.lit(8)).alias("part"))
    part = e.groupBy("event_type", "part").agg(F.hll_sketch_agg("user_id").alias("h"), F.theta_sketch_agg("user_id").alias("t"), F.kll_sketch_agg_double("value").alias("k"))
    merged = part.groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_union_agg("h")).alias("h"), F.theta_sketch_estimate(F.theta_union_agg("t")).alias("t"), F.kll_sketch_get_quantile_double(F.kll_merge_agg_double("k"), F.lit(0.5)).alias("q"))
    exact = e.groupBy("event_type").agg(F.countDistinct("user_id").alias("n"), F.count("*").alias("rows"))
    rank = e.join(F.broadcast(merged.select("event_type", "q")), "event_type").groupBy("event_type").agg((F.count_if(F.col("value") <= F.col("q")) / F.count("*")).alias("rank"))
    bits = 1 << 16
    places = lambda c: F.array(*(F.pmod(F.xxhash64(F.lit(i), c), F.lit(bits)) for i in range(3)))
    seen = e.select("event_type", F.explode(places(F.col("user_id"))).alias("bit")).distinct()
    missed = e.select("event_type", "user_id").distinct().select("event_type", F.explode(places(F.col("user_id"))).alias("bit")).join(seen, ["event_type", "bit"], "left_anti").groupBy("event_type").agg(F.count("*").alias("missed"))
    cells = e.groupBy("event_type", "user_id").agg(F.count("*").alias("c")).select("event_type", "user_id", "c", F.posexplode(F.array(*(F.pmod(F.xxhash64(F.lit(i), "user_id"), F.lit(2048)) for i in range(4)))).alias("row", "cell"))
    sketch = cells.groupBy("event_type", "row", "cell").agg(F.sum("c").alias("s"))
    heavy = cells.join(sketch, ["event_type", "row", "cell"]).groupBy("event_type", "user_id").agg(F.min("s").alias("estimate"), F.max("c").alias("c")).groupBy("event_type").agg(F.bool_and(F.col("estimate") >= F.col("c")).alias("heavy"))
    j = exact.join(merged, "event_type").join(rank, "event_type").join(heavy, "event_type").join(missed, "event_type", "left")
    near = lambda x: F.abs(F.col(x) - F.col("n")) <= F.greatest(0.05 * F.col("n"), F.lit(1.0))
    return j.select("event_type", near("h").alias("hll"), near("t").alias("theta"), (F.abs(F.col("rank") - 0.5) <= F.greatest(F.lit(0.03), 2.0 / F.col("rows"))).alias("quantiles"), F.coalesce(F.col("missed") == 0, F.lit(True)).alias("bloom"), "heavy")


@query("""SELECT event_id, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, first_value(event_type) OVER f AS first_type, nth_value(event_id, 2) OVER f AS second,
  last_value(CASE WHEN event_type = 'error' THEN event_id END IGNORE NULLS) OVER r AS last_error FROM events
  WINDOW w AS (PARTITION BY user_id ORDER BY value, event_id), f AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), r AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)""")
def w_analytic(spark, sf_dir):
    w, line = Window.partitionBy("user_id").orderBy("value", "event_id"), Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole, so_far = line.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing), line.rowsBetween(Window.unboundedPreceding, 0)
    e = table(spark, sf_dir, "events")
    return e.select(
        "event_id", F.dense_rank().over(w).cast("long").alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.first("event_type").over(whole).alias("first_type"), F.nth_value("event_id", 2).over(whole).alias("second"),
        F.last(F.when(F.col("event_type") == "error", F.col("event_id")), ignorenulls=True).over(so_far).alias("last_error"),
    )


@query("""SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 604800 PRECEDING AND CURRENT ROW)::BIGINT AS week, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 6) AS around
FROM (SELECT *, epoch(ts)::BIGINT AS s FROM events)""")
def w_range_frame(spark, sf_dir):
    e = table(spark, sf_dir, "events").withColumn("s", F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000).cast("long"))  # seconds to the nearest, as the SQL cast has them
    week = Window.partitionBy("user_id").orderBy("s").rangeBetween(-604800, 0)
    return e.select("event_id", F.count("*").over(week).alias("week"), F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-1, 1)), 6).alias("around"))


@query("SELECT p_partkey, replace(p_name, ' ', '_') AS under, split_part(p_brand, '#', 1) AS brand, lpad(p_size::VARCHAR, 4, '0') AS size, reverse(p_type) AS turned, translate(p_name, 'aeiou', '12345') AS swapped, position('a' IN p_name)::INT AS at, len(regexp_extract_all(p_type, '[A-Z]+'))::INT AS words, p_type LIKE '%BRASS' AS brass FROM part")
def fn_strings_more(spark, sf_dir):
    p = table(spark, sf_dir, "part")
    return p.select(
        "p_partkey", F.replace("p_name", F.lit(" "), F.lit("_")).alias("under"), F.substring_index("p_brand", "#", 1).alias("brand"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("size"), F.reverse("p_type").alias("turned"),
        F.translate("p_name", "aeiou", "12345").alias("swapped"), F.instr("p_name", "a").alias("at"), F.size(F.regexp_extract_all("p_type", F.lit("[A-Z]+"), F.lit(0))).alias("words"), F.col("p_type").like("%BRASS").alias("brass"),
    )


@query("SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, datediff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days, strftime(o_orderdate + INTERVAL 36 HOUR, '%Y-%m-%d %H') AS later, quarter(o_orderdate)::INT AS q, strftime(last_day(o_orderdate), '%Y-%m-%d') AS month_end, o_orderdate < TIMESTAMP '1996-01-01' AND o_orderdate + INTERVAL 30 DAY > TIMESTAMP '1995-01-01' AS overlaps FROM orders")
def fn_dates(spark, sf_dir):
    o, d = table(spark, sf_dir, "orders"), F.col("o_orderdate")
    at = lambda x: F.lit(x).cast("timestamp_ntz")
    return o.select(
        "o_orderkey", F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("month"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).alias("days"), F.date_format(d + F.make_dt_interval(F.lit(1), F.lit(12)), "yyyy-MM-dd HH").alias("later"),
        F.quarter(d).alias("q"), F.date_format(F.last_day(d.cast("date")), "yyyy-MM-dd").alias("month_end"), ((d < at("1996-01-01")) & (d + F.make_dt_interval(F.lit(30)) > at("1995-01-01"))).alias("overlaps"),
    )


@query("SELECT user_id, string_agg(event_type || '=' || n, ',' ORDER BY event_type) AS counts, string_agg(event_type || '=' || n * 2, ',' ORDER BY event_type) FILTER (WHERE n > 1) AS doubled FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id")
def fn_maps(spark, sf_dir):
    per = table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = per.groupBy("user_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("event_type", "n")))).alias("m"))
    twice = F.transform_values(F.map_filter("m", lambda k, v: v > 1), lambda k, v: v * 2)
    text = lambda m: F.array_join(F.array_sort(F.transform(F.map_entries(m), lambda e: F.concat_ws("=", e["key"], e["value"].cast("string")))), ",")
    zipped = F.map_zip_with("m", twice, lambda k, a, b: F.coalesce(a, b))
    return maps.select("user_id", text(zipped).alias("counts"), F.nullif(text(twice), F.lit("")).alias("doubled"))


@query("SELECT event_id, (props::JSON->>'$.k')::INT AS k, json_extract_string(props, '$.none') AS missing, '{\"id\":' || event_id || ',\"k\":' || (props::JSON->>'$.k') || '}' AS again FROM events")
def fn_variant(spark, sf_dir):
    e = table(spark, sf_dir, "events").withColumn("v", F.try_parse_json("props"))
    k = F.variant_get("v", "$.k", "int")
    return e.select("event_id", k.alias("k"), F.get_json_object("props", "$.none").alias("missing"), F.to_json(F.struct(F.col("event_id").alias("id"), F.from_json("props", "k int")["k"].alias("k"))).alias("again"))


@query("SELECT c_custkey, round(c_acctbal, 0) IS NOT DISTINCT FROM nullif(round(c_acctbal, 0), 0) AS same, c_acctbal BETWEEN 0 AND 1000 AS low, regexp_matches(c_name, '[05]$') AS five, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal > 5000 THEN 'rich' ELSE 'plain' END AS kind FROM customer")
def fn_predicates(spark, sf_dir):
    c, whole = table(spark, sf_dir, "customer"), F.round("c_acctbal", 0)
    return c.select("c_custkey", whole.eqNullSafe(F.nullif(whole, F.lit(0.0))).alias("same"), F.col("c_acctbal").between(0, 1000).alias("low"), F.col("c_name").rlike("[05]$").alias("five"), F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") > 5000, "rich").otherwise("plain").alias("kind"))


@query("SELECT a.vec_id AS a, b.vec_id AS b, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) / sqrt(list_dot_product(a.embedding::DOUBLE[], a.embedding::DOUBLE[])) / sqrt(list_dot_product(b.embedding::DOUBLE[], b.embedding::DOUBLE[])), 5) AS c FROM embeddings a JOIN embeddings b ON a.vec_id + 1 = b.vec_id")
def sql_cosine(spark, sf_dir):
    """The SQL function cosine() on neighbouring rows."""
    functions.register(ship(spark))
    table(spark, sf_dir, "embeddings").selectExpr("vec_id", "cast(embedding AS array<double>) AS v").createOrReplaceTempView("surface_embeddings")
    return spark.sql("SELECT a.vec_id AS a, b.vec_id AS b, round(cosine(a.v, b.v), 5) AS c FROM surface_embeddings a JOIN surface_embeddings b ON a.vec_id + 1 = b.vec_id")
