"""Verdicts on additions and deprecations, the store that deletes, forced tracks, event signatures, context budget and the stream of evidence."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgflow.baselines import hard_delete
from kgflow.corpus import render
from kgflow.evolve import event_schema
from kgflow.extract import guidance, routing
from kgflow.functions.ids import h32
from kgflow.measures import quality, verdicts
from kgflow.sources.tables import table
from kgflow.store import graph
from kgflow.streaming import replay
from kgflow.workloads import assembled, lifecycle, star
from kgflow.workloads.common import query
from kgflow.workloads.operators import event_stream

JUDGED = """SELECT '{run}' AS run, w AS batch_id, CASE WHEN EXISTS (SELECT 1 FROM gold g WHERE g.name = x.who AND g.rel = x.rel AND g.w = x.w AND g.lo = x.val AND g.hi = x.val) THEN 'fully_supported'
  WHEN EXISTS (SELECT 1 FROM gold g WHERE g.name = x.who AND g.rel = x.rel AND g.lo = x.val AND g.hi = x.val) THEN 'partially_supported' ELSE 'not_supported' END AS verdict FROM {adds} x"""


@query(lifecycle.FULL + ", v AS (" + JUDGED.format(run="full", adds="adds") + " UNION ALL " + JUDGED.format(run="no intent", adds="firsts") + ") SELECT run, batch_id, verdict, count(*)::BIGINT AS additions FROM v GROUP BY ALL")
def m_support_verdicts(spark, sf_dir):
    """Additions by three-valued verdict, of the full step and of the one that adds whatever is asserted."""
    gold = lifecycle.gold_states(table(spark, sf_dir, "events")).where("lo = hi").select(F.col("name").alias("head"), "relation", F.col("lo").alias("tail"), "batch_id")
    stmts = lifecycle.statements(spark, sf_dir)
    wording = F.when(F.col("tail") == "active", "activated").otherwise(F.col("tail"))
    out = None
    for run, switches in (("full", {}), ("no intent", {"intent": False})):
        adds = lifecycle.loop(spark, sf_dir, **switches).adds.select("head", "relation", "tail", "batch_id", "stmt_id")
        rows = verdicts.support(adds, gold, stmts, wording).groupBy("batch_id", "verdict").agg(F.count("*").alias("additions")).withColumn("run", F.lit(run))
        out = rows if out is None else out.unionByName(rows)
    return out


@query(lifecycle.ALIAS + "SELECT w AS batch_id, CASE WHEN user_id = prev_user THEN 'justified' ELSE 'unjustified' END AS verdict, count(*)::BIGINT AS deprecations FROM adds WHERE prev IS NOT NULL GROUP BY ALL")
def m_deletion_verdicts(spark, sf_dir):
    """Deprecations by verdict where users that share an alias are taken for one."""
    about = table(spark, sf_dir, "events").select(F.concat(F.lit("ev-"), F.col("event_id").cast("string")).alias("stmt_id"), F.col("user_id").alias("subject"))
    return verdicts.deletion(lifecycle.loop(spark, sf_dir, coref=False).downs, about).groupBy("batch_id", "verdict").agg(F.count("*").alias("deprecations"))


@query(lifecycle.FULL + ", k AS (SELECT who, rel, val, bool_or(next_w IS NULL) AS live FROM adds GROUP BY ALL) SELECT rel AS relation, count(*) FILTER (WHERE live)::BIGINT AS kept, count(*) FILTER (WHERE NOT live)::BIGINT AS forgotten FROM k GROUP BY rel")
def b_hard_delete_store(spark, sf_dir):
    """Edges that the deleting store keeps, and those of the soft log that it can't tell anything of."""
    run = lifecycle.loop(spark, sf_dir)
    kept = hard_delete.after(run.adds, run.downs, [0, 1, 2]).select(*graph.KEY).withColumn("kept", F.lit(1))
    return run.log().select(*graph.KEY).distinct().join(kept, graph.KEY, "left").groupBy("relation").agg(F.count("kept").alias("kept"), F.count(F.when(F.col("kept").isNull(), 1)).alias("forgotten"))


@query("WITH n AS (SELECT (SELECT count(*) FROM events) + (SELECT count(*) FROM nation) AS n) SELECT tracks, track, n::BIGINT AS n FROM n, (VALUES ('static', 'static'), ('both', 'static'), ('both', 'event')) AS t(tracks, track)")
def x_forced_tracks(spark, sf_dir):
    """Statements per track where all are taken as triples, or all on both tracks."""
    rows = lifecycle.statements(spark, sf_dir).select("text").unionByName(table(spark, sf_dir, "nation").select(F.concat("n_name", F.lit(" is a nation.")).alias("text")))
    out = [routing.route(rows, t).groupBy("track").agg(F.count("*").alias("n")).withColumn("tracks", F.lit(t)) for t in ("static", "both")]
    return out[0].unionByName(out[1])


@query(lifecycle.FULL + f""", x AS (SELECT {lifecycle.TRIGGER} AS trigger, ('0x' || substr(md5('event:' || event_id), 1, 8))::BIGINT % 29 = 0 AS hit, event_type FROM ev),
r AS (SELECT trigger, CASE WHEN hit AND event_type = 'click' THEN 'place' WHEN hit AND event_type = 'purchase' OR event_type IN ('signup', 'error') THEN 'subject' ELSE 'object,subject' END AS roles FROM x)
SELECT trigger, roles, count(*)::BIGINT AS events, CASE WHEN roles = 'place' THEN 'opened:place' ELSE trigger END AS cluster FROM r GROUP BY ALL""")
def s_event_clusters(spark, sf_dir):
    """Signatures of events: purchases that lost their object stay with their trigger's cluster, clicks that name a place alone don't."""
    s = lifecycle.event_structs(spark, sf_dir)
    hit = h32("event", F.regexp_extract("event_id", r"([0-9]+)", 1)) % 29 == 0
    lost = F.map_filter("roles", lambda k, v: k != "object")
    moved = F.transform_keys(F.map_filter("roles", lambda k, v: k == "subject"), lambda k, v: F.lit("place"))
    roles = F.when(hit & (F.col("trigger") == "replaced"), lost).when(hit & (F.col("trigger") == "opened"), moved).otherwise(F.col("roles"))
    return event_schema.clusters(s.withColumn("roles", roles)).withColumn("roles", F.array_join("roles", ","))


@query("SELECT conv_id, turn FROM (SELECT *, sum(length(text)) OVER (PARTITION BY conv_id ORDER BY turn ROWS UNBOUNDED PRECEDING) AS used FROM conversations) WHERE used <= 400")
def g_context_budget(spark, sf_dir):
    """Turns of a conversation, in order, that fit into 400 characters."""
    return guidance.budget(table(spark, sf_dir, "conversations"), "conv_id", "text", "turn", 400).select("conv_id", "turn")


@query("SELECT event_id AS stmt_id, (event_id % 90)::BIGINT AS minutes FROM events WHERE event_type = 'purchase' AND event_id % 4 <> 0 AND event_id % 90 <= 60")
def st_evidence_join(spark, sf_dir):
    """Statements joined with a stream of evidence that comes within the hour; some has none, some comes later."""
    said = event_stream(spark, sf_dir).where("event_type = 'purchase'").select(F.col("event_id").alias("stmt_id"), "ts")
    later = F.make_dt_interval(mins=F.pmod("stmt_id", F.lit(90)).cast("int"))
    seen = said.where("stmt_id % 4 <> 0").select("stmt_id", (F.col("ts") + later).alias("ev_ts"))
    got = replay.drained(replay.evidence_join(said, seen)).where("ev_id is not null")
    return got.select("stmt_id", F.floor((F.unix_micros("ev_ts") - F.unix_micros("ts")) / 60_000_000).alias("minutes"))


@query(assembled.POOLED + "SELECT batch_id, sum((ok AND NOT wrong)::INT)::BIGINT AS additions, sum((named AND NOT wrong AND NOT made_up)::INT)::BIGINT AS supported, round(sum((named AND NOT wrong AND NOT made_up)::INT) / sum((ok AND NOT wrong)::INT), 6) AS delta_precision FROM z GROUP BY batch_id")
def w4_slice_delta_precision(spark, sf_dir):
    """Additions of each slice of the static set that gold has, through the whole loop, among those that still hold."""
    gold = render.fact_rows(star.star(spark, sf_dir)).select("relation", "head", "tail")
    facts = assembled.aligned(assembled.static_state(spark, sf_dir).active(), gold, ("batch_id",))
    hit = facts.join(gold.distinct().withColumn("g", F.lit(True)), ["relation", "head", "tail"], "left").withColumn("supported", F.coalesce("g", F.lit(False)))
    return quality.delta_precision(hit).select("batch_id", "additions", "supported", "delta_precision")
