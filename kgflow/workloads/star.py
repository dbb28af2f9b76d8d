"""Static facts of the star tables: extraction, coreference, gates, schemas, baselines."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgflow.baselines import schema_free
from kgflow.config import LoopConfig
from kgflow.coref import entities, events as event_coref
from kgflow.corpus import render, segment
from kgflow.evolve import profiles, relation_schema
from kgflow.extract import guidance, static_track
from kgflow.functions.ids import h32
from kgflow.govern import evidence, logic
from kgflow.measures import quality
from kgflow.session import settled, stored
from kgflow.sources.tables import table
from kgflow.workloads.common import query, tables

NAMES = ("region", "nation", "customer", "supplier", "part", "orders")
H = "('0x' || substr(md5('{0}:' || {1}), 1, 8))::BIGINT"
PHRASES_SQL = {
    "placed_by": ("placed_by", "placed", "was_placed_by"),
    "has_status": ("has_status", "with_status"),
    "has_priority": ("has_priority", "is_of_priority"),
    "based_in": ("based_in", "is_based_in"),
    "in_region": ("in_region", "contains"),
    "has_brand": ("has_brand",),
    "in_segment": ("in_segment",),
}
PICK = " ".join(f"WHEN '{r}' THEN [{', '.join(repr(p) for p in ps)}][1 + ({H.format(f'say {r} text', 'key')}) % {len(ps)}]" for r, ps in PHRASES_SQL.items())
BASE = f"""
WITH facts AS (
  SELECT 'nation' AS kind, n_nationkey::VARCHAR AS key, 'in_region' AS relation, lower(n_name) AS head, lower(r_name) AS tail, 'nation' AS ht, 'region' AS tt FROM nation JOIN region ON n_regionkey = r_regionkey
  UNION ALL SELECT 'customer', c_custkey::VARCHAR, 'based_in', 'customer ' || c_custkey, lower(n_name), 'customer', 'nation' FROM customer JOIN nation ON c_nationkey = n_nationkey
  UNION ALL SELECT 'supplier', s_suppkey::VARCHAR, 'based_in', 'supplier ' || s_suppkey, lower(n_name), 'supplier', 'nation' FROM supplier JOIN nation ON s_nationkey = n_nationkey
  UNION ALL SELECT 'customer', c_custkey::VARCHAR, 'in_segment', 'customer ' || c_custkey, lower(c_mktsegment), 'customer', 'value' FROM customer
  UNION ALL SELECT 'part', p_partkey::VARCHAR, 'has_brand', 'part ' || p_partkey, lower(p_brand), 'part', 'value' FROM part
  UNION ALL SELECT 'order', o_orderkey::VARCHAR, 'placed_by', 'order ' || o_orderkey, 'customer ' || o_custkey, 'order', 'customer' FROM orders
  UNION ALL SELECT 'order', o_orderkey::VARCHAR, 'has_status', 'order ' || o_orderkey, lower(o_orderstatus), 'order', 'value' FROM orders
  UNION ALL SELECT 'order', o_orderkey::VARCHAR, 'has_priority', 'order ' || o_orderkey, lower(o_orderpriority), 'order', 'value' FROM orders),
f AS (
  SELECT *, CASE relation {PICK} END AS phrase, relation = 'placed_by' AND {H.format('order', 'key')} % 17 = 0 AS wrong,
    relation = 'placed_by' AND {H.format('order', 'key')} % 19 = 0 AS made_up, relation = 'placed_by' AND {H.format('order', 'key')} % 13 = 0 AS denied,
    ({H.format('slice', "kind || ' ' || key")} % 3)::INT AS batch_id FROM facts),
g AS (
  SELECT *, phrase IN ('placed', 'contains') AS swapped, CASE WHEN wrong THEN replace(tail, 'customer', 'part') ELSE tail END AS told,
    CASE WHEN made_up THEN 'customer ' || (regexp_extract(tail, '[0-9]+')::BIGINT + 1) WHEN wrong THEN replace(tail, 'customer', 'part') ELSE tail END AS cand FROM f)
"""


class Star(dict):
    """The star tables; the statements are rendered from them and written at their first use, as a corpus that extraction then scans."""

    def __missing__(self, name: str) -> DataFrame:
        if name != "statements":
            raise KeyError(name)
        self[name] = stored(render.star_statements(self))
        return self[name]


def star(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """Nothing is kept from one query for the next, so every query reads its tables."""
    return Star(tables(spark, sf_dir, *NAMES))


def lexicon(t: dict[str, DataFrame]) -> DataFrame:
    """Names of known profiles with their types."""
    return t["nation"].select(F.lower("n_name").alias("name"), F.lit("nation").alias("type")).unionByName(t["region"].select(F.lower("r_name").alias("name"), F.lit("region").alias("type")))


def candidates(t: dict[str, DataFrame]) -> DataFrame:
    """(stmt_id, phrase, h, t, kind, key, batch_id) with canonical names, in the order of the text."""
    found = static_track.triples(t["statements"])
    return found.select("stmt_id", "phrase", entities.canonical("h_name").alias("h"), entities.canonical("t_name").alias("t"), "kind", "key", "batch_id")


def registry(spark: SparkSession) -> DataFrame:
    """Known phrases: (alias, relation, swapped)."""
    return spark.createDataFrame([(p, r, s) for r, _, p, s in render.PHRASINGS], "alias string, relation string, swapped boolean")


def facts(t: dict[str, DataFrame], spark: SparkSession) -> DataFrame:
    return guidance.constrain(candidates(t), registry(spark)).select("stmt_id", "head", "relation", "tail", "kind", "key", "batch_id", "phrase")


def typed(rows: DataFrame, lex: DataFrame, head: str, tail: str) -> DataFrame:
    a = entities.infer_types(rows, lex, head).withColumnRenamed("type", "head_type")
    return entities.infer_types(a, lex, tail).withColumnRenamed("type", "tail_type")


def with_made_up(rows: DataFrame) -> DataFrame:
    """An extractor that answers beside its evidence for some orders."""
    hit = (F.col("relation") == "placed_by") & (h32("order", "key") % render.UNSUPPORTED == 0)
    beside = F.concat(F.lit("customer "), (F.regexp_extract("tail", r"([0-9]+)", 1).cast("bigint") + 1).cast("string"))
    return rows.withColumn("tail", F.when(hit, beside).otherwise(F.col("tail")))


def schemas(spark: SparkSession) -> DataFrame:
    rows = [("placed_by", ["order"], ["customer"]), ("based_in", ["customer", "supplier"], ["nation"]), ("in_region", ["nation"], ["region"]), ("has_status", ["order"], ["value"]), ("has_priority", ["order"], ["value"])]
    return spark.createDataFrame(rows, "relation string, domain array<string>, range array<string>")


def gated(spark: SparkSession, sf_dir: str, cfg: LoopConfig | None = None) -> DataFrame:
    """Candidates after evidence, self-loop and signature checks, as far as switched on."""
    cfg = cfg or LoopConfig()
    t = star(spark, sf_dir)
    said = facts(t, spark)
    cands = with_made_up(said)
    if cfg.evidence:
        cands = evidence.verify(cands, said, ("placed_by",)).where("verdict = 'ACCEPTED'").drop("verdict")
    if cfg.logic:
        cands = logic.signatures(typed(cands, lexicon(t), "head", "tail"), schemas(spark)).where("fits").where("not (relation in ('placed_by', 'in_region', 'based_in') and head = tail)")
    return cands.select("stmt_id", "head", "relation", "tail", "phrase", "batch_id")


@query(BASE + "SELECT kind || '-' || key || '-' || relation AS stmt_id, phrase, CASE WHEN swapped THEN told ELSE head END AS h, CASE WHEN swapped THEN head ELSE told END AS t FROM g")
def x_static_triples(spark, sf_dir):
    return candidates(star(spark, sf_dir)).select("stmt_id", "phrase", "h", "t")


@query(BASE + "SELECT relation, phrase, swapped, count(*)::BIGINT AS n FROM g GROUP BY ALL")
def g_constrain_names(spark, sf_dir):
    f = guidance.constrain(candidates(star(spark, sf_dir)), registry(spark))
    return f.groupBy("relation", "phrase", F.coalesce("swapped", F.lit(False)).alias("swapped")).agg(F.count("*").alias("n"))


@query(BASE + "SELECT key::BIGINT AS order_key FROM g WHERE made_up AND cand <> told")
def v_evidence_rejects(spark, sf_dir):
    said = facts(star(spark, sf_dir), spark)
    return evidence.verify(with_made_up(said), said, ("placed_by",)).where("verdict = 'REJECTED'").select(F.col("key").cast("bigint").alias("order_key"))


@query(BASE + "SELECT key::BIGINT AS order_key FROM g WHERE wrong")
def v_signature_rejects(spark, sf_dir):
    t = star(spark, sf_dir)
    return logic.signatures(typed(facts(t, spark), lexicon(t), "head", "tail"), schemas(spark)).where("not fits").select(F.col("key").cast("bigint").alias("order_key"))


@query(BASE + "SELECT type, count(*)::BIGINT AS names FROM (SELECT DISTINCT name, type FROM (SELECT head AS name, ht AS type FROM g UNION ALL SELECT told, CASE WHEN wrong THEN 'part' ELSE tt END FROM g)) GROUP BY type")
def c_types(spark, sf_dir):
    t = star(spark, sf_dir)
    c = facts(t, spark)
    names = c.select(F.explode(F.array("head", "tail")).alias("name")).distinct()
    return entities.infer_types(names, lexicon(t)).groupBy("type").agg(F.count("*").alias("names"))


PRF = """SELECT relation, sum(tp)::BIGINT AS tp, sum(np)::BIGINT AS n_pred, sum(ng)::BIGINT AS n_gold, round(sum(tp) / nullif(sum(np), 0), 6) AS precision, round(sum(tp) / nullif(sum(ng), 0), 6) AS recall,
  round(2 * (sum(tp) / nullif(sum(np), 0)) * (sum(tp) / nullif(sum(ng), 0)) / nullif(sum(tp) / nullif(sum(np), 0) + sum(tp) / nullif(sum(ng), 0), 0), 6) AS f1 FROM r GROUP BY relation"""


@query(BASE + ", r AS (SELECT relation, (cand = tail)::INT AS tp, 1 AS np, 1 AS ng FROM g) " + PRF)
def m_prf_without_gates(spark, sf_dir):
    gold = render.fact_rows(star(spark, sf_dir))
    return quality.prf(gated(spark, sf_dir, LoopConfig(evidence=False, logic=False)), gold, ["relation"], ["head", "tail"])


# schemas --------------------------------------------------------------------------------------


def signed(spark, sf_dir) -> DataFrame:
    t = star(spark, sf_dir)
    return settled(relation_schema.signatures(typed(candidates(t), lexicon(t), "h", "t")))  # a vocabulary


@query(BASE + "SELECT phrase, batch_id, count(*)::BIGINT AS support, count(DISTINCT CASE WHEN swapped THEN told ELSE head END)::BIGINT AS heads FROM g GROUP BY phrase, batch_id")
def s_relation_support(spark, sf_dir):
    return relation_schema.support(candidates(star(spark, sf_dir)))


CANON = BASE + """, n AS (SELECT relation AS gold, phrase AS alias, swapped, count(*) AS support FROM g GROUP BY ALL),
c AS (SELECT *, first(alias) OVER (PARTITION BY gold ORDER BY support DESC, alias) AS lead FROM n),
m AS (SELECT c.alias, c.lead AS relation, c.swapped <> l.swapped AS swapped, c.support, c.gold FROM c JOIN c l ON l.gold = c.gold AND l.alias = c.lead)
"""


@query(CANON + "SELECT alias, relation, swapped, support::BIGINT AS support FROM m")
def s_canonical_map(spark, sf_dir):
    return relation_schema.canonicalise(signed(spark, sf_dir)).drop("class")


@query(CANON + "SELECT relation, sum(support)::BIGINT AS support, count(*)::BIGINT AS aliases, CASE WHEN sum(support) > 5 THEN 'PASS' ELSE 'POOL' END AS verdict FROM m GROUP BY relation")
def s_relation_candidates(spark, sf_dir):
    s = signed(spark, sf_dir)
    out = relation_schema.propose(s, relation_schema.canonicalise(s), LoopConfig(review_type_share=0.5))
    return out.select("relation", "support", F.size("aliases").cast("bigint").alias("aliases"), "verdict")


@query(BASE + "SELECT phrase, sum(n)::BIGINT AS support FROM (SELECT phrase, batch_id, count(*) AS n FROM g GROUP BY ALL) GROUP BY phrase HAVING min(n) FILTER (WHERE batch_id = 0) <= 6 AND sum(n) > 6")
def s_pool(spark, sf_dir):
    """Phrases that are rare in the first slice and pass the frequency bar with later ones."""
    sup = relation_schema.support(candidates(star(spark, sf_dir)))
    return relation_schema.retry(sup.where("batch_id = 0 and support <= 6"), sup, 6)


@query(BASE + "SELECT relation, count(*)::BIGINT AS edges, 0.0::DOUBLE AS symmetric_share, 1.0::DOUBLE AS functional_share FROM g GROUP BY relation")
def s_traits(spark, sf_dir):
    return relation_schema.traits(facts(star(spark, sf_dir), spark))


@query(CANON + "SELECT count(DISTINCT relation)::BIGINT AS types, count(DISTINCT gold)::BIGINT AS matched, round(count(DISTINCT gold) / count(DISTINCT relation), 6) AS schema_precision, 0::BIGINT AS redundant, 0.0::DOUBLE AS redundancy FROM m")
def m_redundancy(spark, sf_dir):
    gold = registry(spark).select("alias", F.col("relation").alias("gold"))
    return quality.schema_quality(relation_schema.canonicalise(signed(spark, sf_dir)), gold)


@query(BASE + "SELECT count(DISTINCT phrase)::BIGINT AS phrases, count(DISTINCT relation)::BIGINT AS induced, round(1 - count(DISTINCT relation) / count(DISTINCT phrase), 6) AS fewer FROM g")
def m_schema_size(spark, sf_dir):
    m = relation_schema.canonicalise(signed(spark, sf_dir))
    return m.agg(F.countDistinct("alias").alias("phrases"), F.countDistinct("relation").alias("induced")).withColumn("fewer", F.round(1 - F.col("induced") / F.col("phrases"), 6))


NGRAMS = """, names AS (SELECT DISTINCT phrase AS alias, relation AS gold FROM g),
ng AS (SELECT alias, ('0x' || substr(md5(substr('^' || alias || '$', i, 3)), 1, 6))::BIGINT % 64 AS d, count(*) AS c FROM (SELECT alias, unnest(range(1, length(alias) + 1)) AS i FROM names) GROUP BY ALL),
len AS (SELECT alias, sqrt(sum(c * c)) AS l FROM ng GROUP BY alias),
near AS (SELECT x.alias AS a, y.alias AS b FROM ng x JOIN ng y ON x.d = y.d AND x.alias <> y.alias JOIN len p ON p.alias = x.alias JOIN len q ON q.alias = y.alias GROUP BY x.alias, y.alias, p.l, q.l HAVING sum(x.c * y.c) / p.l / q.l >= 0.8),
reach(a, b) AS (SELECT alias, alias FROM names UNION SELECT reach.a, near.b FROM reach JOIN near ON reach.b = near.a),
kind AS (SELECT a AS alias, min(b) AS type FROM reach GROUP BY a),
votes AS (SELECT type, gold, count(*) AS n FROM kind JOIN names USING (alias) GROUP BY ALL),
best AS (SELECT type, arg_max(gold, (n, gold)) AS gold FROM votes GROUP BY type),
per AS (SELECT gold, count(*) AS k FROM best GROUP BY gold)
"""


@query(BASE.replace("WITH facts", "WITH RECURSIVE facts") + NGRAMS + """SELECT 'define-canonicalise' AS method, sum(k)::BIGINT AS types, count(*)::BIGINT AS matched, round(count(*) / sum(k), 6) AS schema_precision, sum(CASE WHEN k > 1 THEN k ELSE 0 END)::BIGINT AS redundant, round(sum(CASE WHEN k > 1 THEN k ELSE 0 END) / sum(k), 6) AS redundancy FROM per
UNION ALL SELECT 'loop', count(DISTINCT gold)::BIGINT, count(DISTINCT gold)::BIGINT, 1.0::DOUBLE, 0::BIGINT, 0.0::DOUBLE FROM names""")
def m_schema_vs_baseline(spark, sf_dir):
    """Types, precision and redundancy of the loop and of the canonicalise-once baseline, which compares whole names and never turns them."""
    s = signed(spark, sf_dir)
    gold = registry(spark).select("alias", F.col("relation").alias("gold"))
    loop = quality.schema_quality(relation_schema.canonicalise(s), gold).withColumn("method", F.lit("loop"))
    base = quality.schema_quality(schema_free.canonical_names(s, LoopConfig().entity_sim_min), gold).withColumn("method", F.lit("define-canonicalise"))
    return loop.unionByName(base)


# baselines ------------------------------------------------------------------------------------


@query(BASE + "SELECT 'define-canonicalise' AS method, count(*) FILTER (WHERE NOT swapped AND cand = tail)::BIGINT AS tp, count(*)::BIGINT AS n_pred, count(*)::BIGINT AS n_gold FROM g")
def b_define_canonicalize_prf(spark, sf_dir):
    t = star(spark, sf_dir)
    pred = schema_free.define_canonicalise(with_made_up_text(t, spark), registry(spark))
    return scored("define-canonicalise", pred, t)


@query(BASE + "SELECT 'co-occurrence' AS method, count(*) FILTER (WHERE NOT swapped AND phrase = relation AND told = tail)::BIGINT AS tp, (count(*) + count(*) FILTER (WHERE denied))::BIGINT AS n_pred, count(*)::BIGINT AS n_gold FROM g")
def b_cooccurrence_prf(spark, sf_dir):
    t = star(spark, sf_dir)
    return scored("co-occurrence", schema_free.cooccurrence(t["statements"]), t)


@query(BASE + "SELECT 'fixed-schema' AS method, count(*) FILTER (WHERE relation IN ('placed_by', 'has_status') AND phrase = relation AND told = tail)::BIGINT AS tp, count(*) FILTER (WHERE relation IN ('placed_by', 'has_status') AND phrase = relation)::BIGINT AS n_pred, count(*)::BIGINT AS n_gold FROM g")
def b_fixed_schema_prf(spark, sf_dir):
    t = star(spark, sf_dir)
    return scored("fixed-schema", schema_free.fixed_schema(candidates(t), ("placed_by", "has_status")), t)


def with_made_up_text(t, spark) -> DataFrame:
    """The same extractor answers as the loop gets, under their phrases and in the order of the text."""
    c = guidance.constrain(candidates(t), registry(spark))
    m = with_made_up(c)
    return m.withColumn("h", F.when(F.col("swapped"), F.col("tail")).otherwise(F.col("head"))).withColumn("t", F.when(F.col("swapped"), F.col("head")).otherwise(F.col("tail"))).select("h", "phrase", "t")


def scored(method: str, pred: DataFrame, t) -> DataFrame:
    key = ["head", "relation", "tail"]
    gold = render.fact_rows(t).withColumn("method", F.lit(method))
    return quality.prf(pred.withColumn("method", F.lit(method)), gold, ["method"], key).select("method", "tp", "n_pred", "n_gold")


# coreference ----------------------------------------------------------------------------------


def mentions(t: dict[str, DataFrame]) -> DataFrame:
    """(surface, entity, type, batch_id): customers and suppliers under changing forms over three batches,
    each missing from one of them; parts under their ambiguous names."""
    out = None
    for kind, key, df in (("customer", "c_custkey", t["customer"]), ("supplier", "s_suppkey", t["supplier"])):
        rows = df.select(F.col(key).cast("string").alias("n"), F.explode(F.array(*map(F.lit, range(3)))).alias("batch_id"), h32(kind, key).alias("h"))
        v = F.pmod(F.col("h") + F.col("batch_id"), F.lit(4))
        forms = F.when(v == 0, F.concat(F.lit(kind.capitalize() + "#"), F.lpad("n", 9, "0"))).when(v == 1, F.concat(F.lit(kind + " "), F.col("n"))).when(v == 2, F.concat(F.lit(kind.upper() + " #"), F.col("n"))).otherwise(F.concat(F.lit(kind + "-"), F.col("n")))
        rows = rows.where(F.pmod(F.col("h") + F.col("batch_id"), F.lit(3)) != 0).select(forms.alias("surface"), F.concat(F.lit(kind + " "), F.col("n")).alias("entity"), F.lit(kind).alias("type"), "batch_id")
        out = rows if out is None else out.unionByName(rows)
    parts = t["part"].select(F.col("p_name").alias("surface"), F.concat(F.lit("part "), F.col("p_partkey").cast("string")).alias("entity"), F.lit("part").alias("type"), F.pmod(h32("part", "p_partkey"), F.lit(3)).cast("int").alias("batch_id"))
    return out.unionByName(parts)


def _mentions_sql() -> str:
    one = lambda kind, key, tab: f"""SELECT CASE (h + b) % 4 WHEN 0 THEN '{kind.capitalize()}#' || lpad(n, 9, '0') WHEN 1 THEN '{kind} ' || n WHEN 2 THEN '{kind.upper()} #' || n ELSE '{kind}-' || n END AS surface, '{kind} ' || n AS entity, '{kind}' AS type, b::INT AS batch_id
  FROM (SELECT {key}::VARCHAR AS n, {H.format(kind, key)} AS h, unnest([0, 1, 2]) AS b FROM {tab}) WHERE (h + b) % 3 <> 0"""  # noqa: E731
    return f"WITH m AS ({one('customer', 'c_custkey', 'customer')} UNION ALL {one('supplier', 's_suppkey', 'supplier')} UNION ALL SELECT p_name, 'part ' || p_partkey, 'part', ({H.format('part', 'p_partkey')} % 3)::INT FROM part)\n"


MENTIONS = _mentions_sql()


@query(MENTIONS + ", c AS (SELECT type, CASE WHEN type = 'part' THEN surface ELSE entity END AS cluster, entity FROM m), x AS (SELECT *, count(*) OVER (PARTITION BY type, cluster) AS nc, count(*) OVER (PARTITION BY type, entity) AS ne, count(*) OVER (PARTITION BY type, cluster, entity) AS n FROM c) SELECT type, count(*)::BIGINT AS mentions, round(avg(n / nc), 6) AS precision, round(avg(n / ne), 6) AS recall FROM x GROUP BY type")
def c_bcubed(spark, sf_dir):
    m = mentions(tables(spark, sf_dir, "customer", "supplier", "part")).withColumn("cluster", entities.canonical("surface"))
    return quality.bcubed(m, ["type"])


@query(MENTIONS + ", x AS (SELECT type, entity, min(batch_id) AS b0, batch_id FROM (SELECT type, entity, batch_id, min(batch_id) OVER (PARTITION BY type, entity) AS b0 FROM m WHERE type <> 'part') GROUP BY ALL), y AS (SELECT DISTINCT type, entity, batch_id, min(batch_id) OVER (PARTITION BY type, entity) AS f FROM m WHERE type <> 'part') SELECT type, batch_id, count(*) FILTER (WHERE f < batch_id)::BIGINT AS reused, count(*) FILTER (WHERE f = batch_id)::BIGINT AS minted FROM y GROUP BY ALL")
def c_reuse_ids(spark, sf_dir):
    """Clusters of each batch that take an earlier profile's id, and those that get a new one."""
    m = mentions(tables(spark, sf_dir, "customer", "supplier", "part")).where("type <> 'part'").withColumn("norm", entities.canonical("surface"))
    known, out = None, None
    for k in range(3):
        new = m.where(F.col("batch_id") == k).select("norm", "type").distinct()
        got = new.withColumn("entity_id", F.md5(F.concat_ws("|", "type", "norm"))).withColumn("reused", F.lit(False)) if known is None else entities.cross(new, known)
        known = got.select("entity_id", "norm", "type") if known is None else known.unionByName(got.where("not reused").select("entity_id", "norm", "type"))
        rows = got.groupBy("type").agg(F.count(F.when(F.col("reused"), 1)).alias("reused"), F.count(F.when(~F.col("reused"), 1)).alias("minted")).withColumn("batch_id", F.lit(k))
        out = rows if out is None else out.unionByName(rows)
    return out


@query(MENTIONS + "SELECT surface, min(surface) OVER (PARTITION BY entity) AS cluster FROM (SELECT DISTINCT surface, entity FROM m WHERE type = 'supplier')")
def c_clusters(spark, sf_dir):
    m = mentions(tables(spark, sf_dir, "customer", "supplier", "part")).where("type = 'supplier'")
    return entities.intra(m.select("surface"))


@query("WITH a AS (SELECT DISTINCT 'acct ' || (user_id // 3) AS s, user_id // 3 AS acct, NULL::BIGINT AS seat FROM events UNION SELECT DISTINCT 'acct ' || (user_id // 3) || ' seat ' || (user_id % 3), user_id // 3, user_id % 3 FROM events) SELECT x.s AS a, y.s AS b, 'HIERARCHY' AS verdict FROM a x JOIN a y ON x.acct = y.acct AND x.s < y.s WHERE (x.seat IS NULL) <> (y.seat IS NULL)")
def c_pair_verdicts(spark, sf_dir):
    """Names of which one lies in the other; pairs that are apart are not made."""
    ev = table(spark, sf_dir, "events")
    alias = F.concat(F.lit("acct "), F.floor(F.col("user_id") / 3).cast("string"))
    names = ev.select(F.explode(F.array(alias, F.concat(alias, F.lit(" seat "), F.pmod("user_id", F.lit(3)).cast("string")))).alias("surface")).distinct()
    return entities.block_pairs(names).withColumn("verdict", entities.pair_verdict("a", "b")).where("verdict <> 'SEPARATE'")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = b.event_type AND a.event_id < b.event_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000")
def c_event_alignment(spark, sf_dir):
    ev = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), "user_id", "event_type", "ts")
    return event_coref.within(ev, ev, ["user_id", "event_type"], "ts", LoopConfig().event_time_slack_seconds).where("a < b").select("a", "b")


@query(MENTIONS + "SELECT entity, type, array_to_string(list_sort(list_distinct(list(surface))), '|') AS aliases, count(*)::BIGINT AS support, min(batch_id) AS first_batch, max(batch_id) AS last_batch FROM m WHERE type <> 'part' GROUP BY entity, type")
def s_profiles(spark, sf_dir):
    m = mentions(tables(spark, sf_dir, "customer", "supplier", "part")).where("type <> 'part'")
    out = profiles.from_mentions(m.where("batch_id = 0"))
    for k in (1, 2):
        out = profiles.update(out, profiles.from_mentions(m.where(F.col("batch_id") == k)))
    return out.withColumn("aliases", F.array_join("aliases", "|"))


# raw text -------------------------------------------------------------------------------------


@query(r"""SELECT page_id, 'host' AS relation, regexp_extract(url, '://([^/?#]*)', 1) AS tail FROM pages WHERE regexp_extract(url, '://([^/?#]*)', 1) <> ''
UNION ALL SELECT page_id, 'title', regexp_extract(html, '<title>([^<]*)</title>', 1) FROM pages WHERE regexp_extract(html, '<title>([^<]*)</title>', 1) <> ''
UNION ALL SELECT page_id, 'links_to', x FROM (SELECT page_id, unnest(regexp_extract_all(html, '<a[^>]*href="([^"]*)"', 1)) AS x FROM pages) WHERE x <> ''""")
def x_pages_triples(spark, sf_dir):
    return segment.page_facts(table(spark, sf_dir, "pages"))


@query(r"SELECT doc_id, 'licensed_under' AS relation, lower(regexp_extract(text, '(?i)(MIT|Apache|General Public|CC BY[A-Z-]*)[ ,]*(?:License|[0-9])', 1)) AS tail FROM documents WHERE regexp_extract(text, '(?i)(MIT|Apache|General Public|CC BY[A-Z-]*)[ ,]*(?:License|[0-9])', 1) <> ''")
def x_license_triples(spark, sf_dir):
    return segment.license_facts(table(spark, sf_dir, "documents"))


@query(r"SELECT doc_id, 'contact_hash' AS relation, md5(lower(regexp_extract(text, '[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}', 0))) AS tail FROM documents WHERE regexp_extract(text, '[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}', 0) <> ''")
def x_contact_hash(spark, sf_dir):
    return segment.contact_facts(table(spark, sf_dir, "documents"))


@query("SELECT conv_id, turn, 'has_role' AS relation, role AS tail FROM conversations UNION ALL SELECT conv_id, turn, 'follows', p::VARCHAR FROM (SELECT conv_id, turn, lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS p FROM conversations) WHERE p IS NOT NULL")
def x_conversation_turns(spark, sf_dir):
    return segment.conversation_facts(table(spark, sf_dir, "conversations"))


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1 OR quality = 0)")
def w18_trusted(spark, sf_dir):
    return segment.trusted(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).select("doc_id")


@query("SELECT DISTINCT doc_id FROM documents d, benchmark b WHERE contains(d.text, b.text)")
def w18_contaminated(spark, sf_dir):
    return segment.containing(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))


# logic on transitions -------------------------------------------------------------------------

STEPS = "WITH s AS (SELECT DISTINCT 'u' || user_id || ':' || p AS head, 'u' || user_id || ':' || event_type AS tail FROM (SELECT *, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events) WHERE p IS NOT NULL)\n"


def transitions(spark, sf_dir) -> DataFrame:
    from pyspark.sql import Window

    e = table(spark, sf_dir, "events").withColumn("p", F.lag("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).where("p is not null")
    node = lambda c: F.concat(F.lit("u"), F.col("user_id").cast("string"), F.lit(":"), F.col(c))
    return e.select(node("p").alias("head"), F.lit("precedes").alias("relation"), node("event_type").alias("tail")).distinct()


@query(STEPS + "SELECT head, tail FROM s WHERE head = tail")
def v_self_loops(spark, sf_dir):
    return logic.self_loops(transitions(spark, sf_dir)).select("head", "tail")


@query(STEPS + "SELECT a.head, a.tail FROM s a JOIN s b ON a.head = b.tail AND a.tail = b.head WHERE a.head <> a.tail")
def v_mutual_pairs(spark, sf_dir):
    return logic.mutual_pairs(transitions(spark, sf_dir)).select("head", "tail")


@query("SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate < o_orderdate")
def v_time_conflicts(spark, sf_dir):
    """Shipments before their order."""
    l = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate")
    return l.join(o, F.col("l_orderkey") == F.col("o_orderkey")).where("l_shipdate < o_orderdate").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


# retrieval ------------------------------------------------------------------------------------


@query("""WITH p AS (SELECT a.vec_id AS a, b.vec_id AS b, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS score FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id)
SELECT a, b, score, r::INT AS rank FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY score DESC, b) AS r FROM p) WHERE r <= 30""")
def g_topk30_exact(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    return guidance.topk_exact(e, e, LoopConfig().retrieve_k)


@query("SELECT count(*)::BIGINT AS queries, true AS all_full, true AS recall_reached FROM embeddings")
def g_topk30_lsh(spark, sf_dir):
    """The bucket search beside the exact one: every row gets its 30, and at least nine in ten of the true ones."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    near, sure = stored(guidance.topk_lsh(e, e, LoopConfig().retrieve_k)), stored(guidance.topk_exact(e, e, LoopConfig().retrieve_k))
    per = near.groupBy("a").agg(F.count("*").alias("n")).join(sure.groupBy("a").agg(F.count("*").alias("m")), "a", "full_outer")
    hit = near.join(sure, ["a", "b"], "left_semi").agg(F.count("*").alias("hit"))
    sums = per.agg(F.count("*").alias("queries"), F.bool_and(F.col("n") == F.col("m")).alias("all_full"), F.sum("m").alias("due"))
    return sums.crossJoin(hit).select("queries", "all_full", (F.col("hit") >= 0.9 * F.col("due")).alias("recall_reached"))  # one row each
