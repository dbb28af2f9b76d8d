"""The assembled loop over the star tables' statements and over the life-cycle stream.

The loop is never given the gold names: it scores under the names and directions that it induced itself, matched to the
gold relations by what most of a type's facts say.
"""

from __future__ import annotations

import uuid
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kgflow.config import LoopConfig
from kgflow.coref import events as event_coref
from kgflow.corpus import render
from kgflow.functions.ids import h32
from kgflow.measures import quality
from kgflow.plans import loop
from kgflow.session import settled, shared_dir
from kgflow.sources.tables import table
from kgflow.store import graph
from kgflow.workloads import lifecycle, star
from kgflow.workloads.common import query

_RUNS: dict[tuple[str, str, str], loop.State] = {}


def beside_the_evidence(rows: DataFrame) -> DataFrame:
    """An extractor that names another customer than the text for some orders, whatever the name and direction of the relation."""
    order = F.col("stmt_id").endswith("-placed_by")
    key = F.regexp_extract("stmt_id", r"^order-([0-9]+)-", 1)
    hit = order & (h32("order", key) % render.UNSUPPORTED == 0)
    other = lambda c: F.concat(F.lit("customer "), (F.regexp_extract(c, r"([0-9]+)", 1).cast("bigint") + 1).cast("string"))
    told = F.col("head").startswith("order ")
    hit_ = F.col("_hit")
    return rows.withColumn("_hit", hit).withColumn("tail", F.when(hit_ & told, other("tail")).otherwise(F.col("tail"))).withColumn("head", F.when(hit_ & ~told, other("head")).otherwise(F.col("head"))).drop("_hit")


def static_state(spark: SparkSession, sf_dir: str, mode: str = "stream-end", corpus: dict[str, DataFrame] | None = None) -> loop.State:
    """The state after the statements of the star tables: all as one batch, or the slices in order, without (kept) or with the
    batch's own schemas applied to its facts. Each is run once per application. corpus: the tables where runs of one query share their statements."""
    place = (spark.sparkContext.applicationId, sf_dir, mode)
    if place not in _RUNS:
        t = corpus if corpus is not None else star.star(spark, sf_dir)
        stmts = t["statements"].withColumn("seq", F.lit(None).cast("bigint"))
        if mode == "batch":
            stmts = stmts.withColumn("batch_id", F.lit(0))
        root = f"{shared_dir(spark)}/loop-{uuid.uuid4().hex}"
        _RUNS[place] = loop.run(stmts, root, LoopConfig(), [0] if mode == "batch" else [0, 1, 2], lexicon=star.lexicon(t), extractor=beside_the_evidence, recheck=mode != "cold start kept")
    return _RUNS[place]


def stream_state(spark: SparkSession, sf_dir: str) -> loop.State:
    place = (spark.sparkContext.applicationId, sf_dir, "events")
    if place not in _RUNS:
        _RUNS[place] = loop.run(lifecycle.statements(spark, sf_dir), f"{shared_dir(spark)}/loop-{uuid.uuid4().hex}")
    return _RUNS[place]


def alike(runs: dict[str, DataFrame], gold: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(facts of the runs with mode, gold), one row for all pairs of ends that runs and gold tell alike, and their number n: made-up ends stand for such a
    class of pairs, so that what is counted over pairs of ends can be counted over classes.

    One aggregation of all rows by their ends: who tells which relation of them in which direction is a bit each, as relation names are a vocabulary."""
    spark, sources = gold.sparkSession, [(None, gold), *runs.items()]
    lists = [(source, d, sorted(r[0] for r in d.select("relation").distinct().collect())) for source, d in sources]
    codes = [(source, name) for source, _, names in lists for name in names]
    place = {c: 2 * i for i, c in enumerate(codes)}
    words = [f"w{i}" for i in range(max(1, -(-2 * len(codes) // BITS)))]
    lone = F.col("head").isNull() | F.col("tail").isNull()
    up = F.when(lone, F.col("head").isNotNull()).otherwise(F.col("head") <= F.col("tail"))

    def marked(source: str | None, d: DataFrame, names: list[str]) -> DataFrame:
        own = [(n, bool(u), *(1 << (place[source, n] + u) % BITS if (place[source, n] + u) // BITS == i else 0 for i in range(len(words)))) for n in names for u in (0, 1)]
        bits = spark.createDataFrame(own, f"relation string, up boolean, {', '.join(f'{w} long' for w in words)}")
        return d.withColumn("up", up).join(F.broadcast(bits), ["relation", "up"]).select(lone.alias("lone"), F.least("head", "tail").alias("lo"), F.greatest("head", "tail").alias("hi"), *words)

    parts = [marked(*x) for x in lists]
    rows = parts[0]
    for x in parts[1:]:
        rows = rows.unionByName(x)
    pairs = rows.groupBy("lone", "lo", "hi").agg(*(F.bit_or(w).alias(w) for w in words))
    key = ["lone", "loop", *words]
    classes = settled(pairs.withColumn("loop", F.coalesce(~F.col("lone") & (F.col("lo") == F.col("hi")), F.lit(False))).groupBy(*key).agg(F.count("*").alias("n")).withColumn("id", F.concat_ws("-", *(F.col(c).cast("string") for c in key))))
    bit = [(source, name, bool(u), (p + u) // BITS, (p + u) % BITS) for (source, name), p in place.items() for u in (0, 1)]
    vocabulary = spark.createDataFrame(bit, "mode string, relation string, up boolean, word int, bit int")
    held = F.expr(f"getbit(array({', '.join(words)})[word], bit)") == 1
    lo, hi = F.concat("id", F.lit(" a")), F.when(F.col("lone"), F.lit(None)).when(F.col("loop"), F.concat("id", F.lit(" a"))).otherwise(F.concat("id", F.lit(" b")))
    told = settled(classes.join(F.broadcast(vocabulary)).where(held).select("mode", "relation", F.when(F.col("up"), lo).otherwise(hi).alias("head"), F.when(F.col("up"), hi).otherwise(lo).alias("tail"), "n"))
    return told.where("mode is not null"), told.where("mode is null").drop("mode")


#: Bits of a word that alike() uses.
BITS = 62


def aligned(facts: DataFrame, gold: DataFrame, beside: tuple[str, ...] = (), weight: str | None = None) -> DataFrame:
    """(relation, head, tail, and the columns beside) of facts (head, relation, tail) under the gold relation of their type, turned where the type runs the
    other way. A gold relation is matched by the one type and direction that most of its facts are found under; facts of other types
    keep their own name and match nothing. weight: a column of facts, how many facts a row stands for."""
    f = facts.select("head", F.col("relation").alias("type"), "tail", *beside)
    pair = lambda d, *more: d.select(F.least("head", "tail").alias("lo"), F.greatest("head", "tail").alias("hi"), (F.col("head") <= F.col("tail")).alias("up"), *more)
    met = pair(f, "type", (F.col(weight) if weight else F.lit(1)).cast("long").alias("_w")).join(pair(gold.select("head", "tail", "relation").distinct(), "relation").withColumnRenamed("up", "gold_up"), ["lo", "hi"])  # an end that meets itself counts both ways
    total = lambda c: F.sum(F.when(c, F.col("_w")).otherwise(F.lit(0)))
    per = met.groupBy("relation", "type").agg(total(F.col("up") == F.col("gold_up")).alias("n"), total((F.col("up") != F.col("gold_up")) | (F.col("lo") == F.col("hi"))).alias("m"))
    ways = F.explode(F.array(F.struct(F.lit(False).alias("turned"), F.col("n").alias("n")), F.struct(F.lit(True).alias("turned"), F.col("m").alias("n")))).alias("x")
    votes = per.select("relation", "type", ways).select("relation", "type", "x.*").where("n > 0")
    best = settled(votes.withColumn("r", F.row_number().over(Window.partitionBy("relation").orderBy(F.desc("n"), "type"))).where("r = 1").select("relation", "type", "turned"))  # a vocabulary
    j = f.join(F.broadcast(best), "type", "left")
    turn = F.coalesce("turned", F.lit(False))
    return j.select(F.coalesce("relation", "type").alias("relation"), F.when(turn, F.col("tail")).otherwise(F.col("head")).alias("head"), F.when(turn, F.col("head")).otherwise(F.col("tail")).alias("tail"), *beside)


#: Facts of a slice whose relation has no more than 5 accepted facts so far keep the name that their text has; under another name than the leading one they match no gold relation.
POOLED = star.BASE + """, acc AS (SELECT *, NOT (made_up AND cand <> told) AS ok FROM g),
cum AS (SELECT relation, k, count(*) FILTER (WHERE ok AND batch_id <= k) AS cum FROM acc, (VALUES (0), (1), (2)) AS b(k) GROUP BY ALL),
lead AS (SELECT relation, arg_max(phrase, (n, -rank)) AS lead FROM (SELECT *, row_number() OVER (ORDER BY phrase) AS rank FROM (SELECT relation, phrase, count(*) FILTER (WHERE ok AND batch_id = 0) AS n FROM acc GROUP BY ALL)) GROUP BY relation),
z AS (SELECT acc.*, cum > 5 OR phrase = lead AS named FROM acc JOIN cum ON cum.relation = acc.relation AND cum.k = acc.batch_id JOIN lead ON lead.relation = acc.relation)
"""


@query(POOLED + ", r AS (SELECT relation, (named AND NOT wrong AND NOT made_up)::INT AS tp, (named AND ok AND NOT wrong)::INT AS np, 1 AS ng FROM z) " + star.PRF)
def m_prf_by_relation(spark, sf_dir):
    """The static score of the loop over the slices in order."""
    gold = render.fact_rows(star.star(spark, sf_dir))
    return quality.prf(aligned(static_state(spark, sf_dir).active(), gold), gold, ["relation"], ["head", "tail"]).where("n_gold > 0")


@query(POOLED + """, m AS (SELECT mode, sum((NOT wrong AND NOT made_up AND (named OR mode = 'batch'))::INT)::BIGINT AS tp, sum((ok AND NOT wrong OR mode = 'cold start kept' AND wrong AND ok AND batch_id = 0)::INT)::BIGINT AS n_pred, count(*)::BIGINT AS n_gold
  FROM z, (VALUES ('batch'), ('stream-end'), ('cold start kept')) AS x(mode) GROUP BY mode)
SELECT mode, tp, n_pred, n_gold, round(tp / n_pred, 6) AS precision, round(tp / n_gold, 6) AS recall, round(2 * (tp / n_pred) * (tp / n_gold) / (tp / n_pred + tp / n_gold), 6) AS f1 FROM m""")
def m_prf_batch_vs_stream(spark, sf_dir):
    """The whole corpus as one batch; its slices in order, scored at the end; and these with the first slice's facts left as the
    cold start took them, before any schema could vet them."""
    t, modes = star.star(spark, sf_dir), ("batch", "stream-end", "cold start kept")
    t["statements"]  # written before the runs, which scan them side by side
    with ThreadPoolExecutor(len(modes)) as pool:
        states = dict(zip(modes, pool.map(lambda mode: static_state(spark, sf_dir, mode, t), modes), strict=True))
    facts, gold = alike({mode: s.active().select(*graph.KEY) for mode, s in states.items()}, render.fact_rows(t).select(*graph.KEY))
    rows = None
    for mode in modes:
        one = aligned(facts.where(F.col("mode") == mode), gold, ("n",), "n").withColumn("mode", F.lit(mode))
        rows = one if rows is None else rows.unionByName(one)
    golds = gold.withColumn("mode", F.explode(F.array(*map(F.lit, modes))))
    return quality.prf(rows, golds, ["mode"], ["relation", "head", "tail"], "n")


@query(star.BASE + """, n AS (SELECT relation AS gold, phrase AS alias, swapped, count(*) FILTER (WHERE batch_id = 0 AND (NOT made_up OR cand = told)) AS early, min(batch_id) AS first FROM g GROUP BY ALL),
l AS (SELECT gold, arg_max(alias, (early, -rank)) AS lead, arg_max(swapped, (early, -rank)) AS way FROM (SELECT *, row_number() OVER (ORDER BY alias) AS rank FROM n) GROUP BY gold)
SELECT alias, lead AS relation, swapped <> way AS swapped FROM n JOIN l USING (gold)""")
def l_relation_names(spark, sf_dir):
    """The registry's names after three slices: the most used one of the first slice leads, later ones join it in its direction."""
    return static_state(spark, sf_dir).newest("aliases", "alias").select("alias", "relation", "swapped")


@query(star.BASE + """SELECT batch_id, 'evidence_gate' AS kind, 'REJECTED' AS verdict, count(*)::BIGINT AS n FROM g WHERE made_up AND cand <> told GROUP BY batch_id
UNION ALL SELECT batch_id, 'logic', 'signature', count(*)::BIGINT FROM g WHERE wrong AND NOT (made_up AND cand <> told) GROUP BY batch_id""")
def l_decisions(spark, sf_dir):
    """What the gates turned down, from the decision record."""
    return static_state(spark, sf_dir).table("decisions").where("kind in ('evidence_gate', 'logic')").groupBy("batch_id", "kind", "verdict").agg(F.count("*").alias("n"))


@query(star.BASE + "SELECT type, count(*)::BIGINT AS entities FROM (SELECT DISTINCT name, type FROM (SELECT head AS name, ht AS type FROM g UNION ALL SELECT told, CASE WHEN wrong THEN 'part' ELSE tt END FROM g)) GROUP BY type")
def l_profiles(spark, sf_dir):
    """Entities per type, through the SQL views of the state."""
    static_state(spark, sf_dir).views()
    return spark.sql("SELECT type, count(*) AS entities FROM kg_profiles GROUP BY type")


@query(star.BASE + ", p AS (SELECT DISTINCT batch_id, name FROM (SELECT batch_id, head AS name FROM g UNION ALL SELECT batch_id, told FROM g)) SELECT batch_id, count(*)::BIGINT AS reused FROM p x WHERE EXISTS (SELECT 1 FROM p y WHERE y.name = x.name AND y.batch_id < x.batch_id) GROUP BY batch_id")
def l_reused_entities(spark, sf_dir):
    """Names of later slices that take a profile's id."""
    return static_state(spark, sf_dir).table("decisions").where("kind = 'entity_reuse'").groupBy("batch_id").agg(F.count("*").alias("reused"))


@query(lifecycle.FULL + "SELECT batch_id, rel AS relation, count(*)::BIGINT AS added, count(prev)::BIGINT AS retired FROM win JOIN adds ON w = batch_id GROUP BY ALL")
def l_increments(spark, sf_dir):
    """State facts that each window adds and retires, through the whole loop."""
    log = stream_state(spark, sf_dir).table("log").where("relation in ('status', 'plan')")
    return log.groupBy("batch_id", "relation").agg(F.count_if(F.col("status") == "ACTIVE").alias("added"), F.count_if(F.col("status") == "DEPRECATED").alias("retired"))


@query(lifecycle.FULL + "SELECT w AS batch_id, CASE WHEN event_type IN ('signup', 'error', 'purchase') THEN 'EVOLUTIONARY' ELSE 'INFORMATIONAL' END AS verdict, count(*)::BIGINT AS n FROM ev GROUP BY ALL")
def l_intents(spark, sf_dir):
    return stream_state(spark, sf_dir).table("decisions").where("kind = 'intent'").groupBy("batch_id", "verdict").agg(F.count("*").alias("n"))


@query(lifecycle.FULL + f"SELECT {lifecycle.TRIGGER} AS trigger, count(*)::BIGINT AS support, 1.0::DOUBLE AS coherence, 'PASS' AS verdict FROM ev GROUP BY 1")
def l_event_schemas(spark, sf_dir):
    return stream_state(spark, sf_dir).newest("event_types", "trigger").select("trigger", "support", "coherence", "verdict")


@query(lifecycle.FULL + ", log2 AS (SELECT * FROM log) SELECT status, count(*)::BIGINT AS n FROM (SELECT head, relation, tail, arg_max(status, batch_id * 2 + seq) AS status FROM log2 GROUP BY ALL) GROUP BY status")
def l_sql_status(spark, sf_dir):
    """The state's SQL views: status of the state facts."""
    stream_state(spark, sf_dir).views()
    return spark.sql("SELECT status, count(*) AS n FROM kg_edges WHERE relation IN ('status', 'plan') GROUP BY status")


@query(star.BASE + """, n AS (SELECT batch_id, count(*) AS n FROM g GROUP BY batch_id), d AS (SELECT batch_id, count(*) FILTER (WHERE denied) AS k FROM g GROUP BY batch_id)
SELECT batch_id, n::BIGINT AS incremental, sum(n) OVER (ORDER BY batch_id)::BIGINT AS rebuilt, round(sum(n) OVER (ORDER BY batch_id) / n, 6) AS ratio FROM n""")
def m_cost_amortised(spark, sf_dir):
    """Candidates that a batch decides on, incrementally and where the graph is rebuilt from all batches so far. The rebuild's number for the last batch
    is what the one-batch run really decided on."""
    per = static_state(spark, sf_dir).table("support").groupBy("batch_id").agg(F.sum("n").alias("kept"))
    gone = static_state(spark, sf_dir).table("decisions").where("kind in ('evidence_gate') or (kind = 'logic' and batch_id > 0)").groupBy("batch_id").agg(F.count("*").alias("gone"))
    own = per.join(gone, "batch_id", "left").select("batch_id", (F.col("kept") + F.coalesce("gone", F.lit(0))).alias("incremental"))
    whole = static_state(spark, sf_dir, "batch")
    last = whole.table("support").agg(F.sum("n")).first()[0] + whole.table("decisions").where("kind = 'evidence_gate'").count()
    run = own.withColumn("rebuilt", F.sum("incremental").over(Window.orderBy("batch_id")))  # one row per batch
    return run.withColumn("rebuilt", F.when(F.col("batch_id") == 2, F.lit(last)).otherwise(F.col("rebuilt"))).withColumn("ratio", F.round(F.col("rebuilt") / F.col("incremental"), 6))


# event coreference ----------------------------------------------------------------------------

ARGS = "list_filter(['u' || user_id, CASE WHEN event_type = 'purchase' THEN floor(value / 50)::BIGINT::VARCHAR WHEN event_type IN ('click', 'view') THEN json_extract_string(props, '$.k') END], lambda x: x IS NOT NULL)"
SCORES = f"""WITH RECURSIVE e AS (SELECT event_id, user_id, event_type, epoch_us(ts) AS t, CASE WHEN ts < TIMESTAMP '2024-01-11' THEN 0 WHEN ts < TIMESTAMP '2024-01-21' THEN 1 ELSE 2 END AS w, {ARGS} AS args FROM events),
p AS (SELECT a.event_id AS a, b.event_id AS b, a.w AS wa, b.w AS wb, abs(a.t - b.t) AS us, round(0.4 * (a.event_type = b.event_type)::INT + 0.4 * len(list_intersect(a.args, b.args)) / len(list_distinct(list_concat(a.args, b.args))) + 0.2 * greatest(0, 1 - abs(b.t - a.t) / 1e6 / 3600), 6) AS score
  FROM e a JOIN e b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND abs(a.t - b.t) <= 3600000000)
"""


def event_forms(spark, sf_dir) -> DataFrame:
    e = table(spark, sf_dir, "events")
    obj = F.when(F.col("event_type") == "purchase", F.floor(F.col("value") / 50).cast("string")).when(F.col("event_type").isin("click", "view"), F.from_json("props", "k int")["k"].cast("string"))
    return e.select(F.col("event_id").alias("id"), F.col("event_type").alias("trigger"), F.concat(F.lit("u"), F.col("user_id").cast("string")).alias("subject"), obj.alias("object"), F.col("ts").alias("at"), render.window_of(F.col("ts")).alias("batch_id"))


@query(SCORES + "SELECT a, b, score FROM p WHERE a < b")
def c_event_scores(spark, sf_dir):
    f = event_forms(spark, sf_dir)
    return event_coref.scored(f, f, LoopConfig()).where("a < b").select("a", "b", "score")


@query(SCORES + ", r(x, y) AS (SELECT event_id, event_id FROM e UNION SELECT r.x, p.b FROM r JOIN p ON r.y = p.a WHERE p.score >= 0.75) SELECT x AS id, min(y) AS cluster FROM r GROUP BY x")
def c_event_clusters(spark, sf_dir):
    return event_coref.clustered(event_forms(spark, sf_dir), LoopConfig())


@query(SCORES + "SELECT a AS id, arg_min(b, (-score, us, b)) AS match, max(score) AS score FROM p WHERE wa = 1 AND wb = 0 AND score >= 0.5 GROUP BY a")
def c_event_matches(spark, sf_dir):
    """Events of the second window with their best match in the index of the first."""
    f = event_forms(spark, sf_dir)
    return event_coref.matches(f.where("batch_id = 1"), f.where("batch_id = 0"), LoopConfig(event_sim_min=0.5)).select("id", "match", "score")
