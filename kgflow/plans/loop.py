"""One step of the assembled loop, and runs of steps: batch k reads the graph and the registry as of batch k-1 and
commits both, with every decision, as one transaction.

The first batch is a cold start: names are taken as the text has them, entities are resolved within the batch only, and candidates
meet general checks only. Later batches are guided: names are looked up among the K nearest schemas of the registry,
entities among its profiles, events in its event index, and known schemas vet types and roles.

After the gates, the batch's names are induced together with all counts of earlier batches; what the batch itself has taught is
applied to its own facts before they are integrated: they take the registered names, and facts that miss the
signature of a schema which only this batch has established are turned down (``recheck``).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kgflow.config import LoopConfig
from kgflow.coref import entities, events as event_coref
from kgflow.evolve import event_schema, relation_schema, relationalize
from kgflow.extract import event_track, guidance, routing, static_track
from kgflow.govern import evidence, intent, logic
from kgflow.session import settled, stored
from kgflow.store import graph
from kgflow.store.commit import Store

#: Tables of the graph and the registry; every batch adds rows, and the newest row of a key counts.
TABLES = {
    "log": "head string, relation string, tail string, status string, batch_id int, seq int, stmt_id string, valid_time timestamp_ntz, ord array<bigint>",
    "profiles": "entity string, type string, norm string, alias string, n long, batch_id int",
    "support": "phrase string, head_type string, tail_type string, n long, heads long, tails long, batch_id int",
    "aliases": "alias string, relation string, swapped boolean, batch_id int",
    "relations": "relation string, support long, aliases array<string>, domain array<string>, `range` array<string>, coherence double, verdict string, batch_id int",
    "event_types": "trigger string, support long, required array<string>, allowed array<string>, coherence double, verdict string, batch_id int",
    "event_index": "id string, trigger string, subject string, object string, at timestamp_ntz, batch_id int",
    "decisions": "kind string, item string, verdict string, batch_id int",
}


def columns(name: str) -> list[str]:
    return [f.strip().split()[0].strip("`") for f in TABLES[name].split(", ")]


@dataclass
class State:
    """Graph and registry as of a committed batch."""

    store: Store
    k: int

    @property
    def spark(self) -> SparkSession:
        return self.store.spark

    def table(self, name: str) -> DataFrame:
        rows = self.store.read(name, self.k) if self.k >= 0 else None
        return self.spark.createDataFrame([], TABLES[name]) if rows is None else rows

    def newest(self, name: str, key: str) -> DataFrame:
        """Of a registry table that is a vocabulary, the last row of every key."""
        rows = self.table(name)
        rest = [c for c in rows.columns if c != key]
        return rows.groupBy(key).agg(F.max_by(F.struct(*rest), "batch_id").alias("x")).select(key, "x.*")

    def active(self) -> DataFrame:
        """Edges in force: (head, relation, tail, stmt_id, valid_time, ord, batch_id). step() logs an edge that isn't a state fact once at most, unless
        it is retired between; a log of such edges alone needs no grouping."""
        log, rest = self.table("log"), ["stmt_id", "valid_time", "ord", "batch_id"]
        if self.k < 0:
            return log.select(*graph.KEY, *rest).limit(0)
        null = " or ".join(f"{c} is null" for c in graph.KEY)
        if log.where((F.col("status") != "ACTIVE") | F.col("relation").isin(*event_track.STATE_RELATIONS) | F.expr(null)).isEmpty():
            return log.select(*graph.KEY, *rest)
        last = log.groupBy(*graph.KEY).agg(F.max_by(F.struct("status", "stmt_id", "valid_time", "ord", "batch_id"), F.struct("batch_id", "seq")).alias("x"))
        return last.where("x.status = 'ACTIVE'").select(*graph.KEY, "x.stmt_id", "x.valid_time", "x.ord", "x.batch_id")

    def views(self) -> None:
        """Temp views over the state for SQL users."""
        log = self.table("log")
        log.createOrReplaceTempView("kg_log")
        graph.status_at(log).createOrReplaceTempView("kg_edges")
        self.active().createOrReplaceTempView("kg_active")
        graph.nodes_of(self.active()).createOrReplaceTempView("kg_nodes")
        log.where("status = 'DEPRECATED'").createOrReplaceTempView("kg_deprecations")
        self.table("profiles").groupBy("entity", "type").agg(F.array_sort(F.collect_set("alias")).alias("aliases"), F.sum("n").alias("support"), F.min("batch_id").alias("first_batch"), F.max("batch_id").alias("last_batch")).createOrReplaceTempView("kg_profiles")
        self.newest("relations", "relation").createOrReplaceTempView("kg_rel_schemas")
        self.newest("event_types", "trigger").createOrReplaceTempView("kg_event_schemas")
        self.table("event_index").createOrReplaceTempView("kg_events")
        self.table("decisions").createOrReplaceTempView("kg_decisions")
        self.spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION kg_status(h STRING, r STRING, t STRING, k INT) RETURNS STRING RETURN SELECT max_by(status, struct(batch_id, seq)) FROM kg_log WHERE head = h AND relation = r AND tail = t AND batch_id <= k")


def decisions(kind: str, rows: DataFrame, item: str, verdict) -> DataFrame:
    verdict = F.col(verdict) if isinstance(verdict, str) else verdict
    return rows.select(F.lit(kind).alias("kind"), F.col(item).cast("string").alias("item"), verdict.alias("verdict"))


def resolve(names: DataFrame, state: State, lexicon: DataFrame | None, cfg: LoopConfig, guided: bool) -> DataFrame:
    """names, distinct surfaces, with (entity, type, norm, reused). Within the batch, equal normal forms are one entity; against the
    registry, the profile with that form and type, else the most similar of a few near ones, if it is near enough."""
    own = names.withColumn("norm", normal("surface", cfg))
    lex = lexicon if lexicon is not None else names.sparkSession.createDataFrame([], "name string, type string")
    typed = entities.infer_types(own.withColumnRenamed("norm", "name"), lex).withColumnRenamed("name", "norm")
    if not (guided and cfg.coref):
        return typed.withColumn("entity", F.col("norm")).withColumn("reused", F.lit(False))
    return entities.align(typed, state.table("profiles").select("entity", "type", "norm"), cfg)


def normal(name: str, cfg: LoopConfig) -> Column:
    return entities.canonical(name) if cfg.coref else F.col(name)


def static_candidates(stmts: DataFrame, state: State, lexicon: DataFrame | None, cfg: LoopConfig, guided: bool) -> tuple[DataFrame, DataFrame, Callable[[DataFrame], DataFrame]]:
    """(found, resolved names, how found becomes candidates): found (stmt_id, phrase, h_name, t_name), in the order of the text; candidates have
    h, t, head_type and tail_type for the names. Where a name's entity is its normal form, and its type the one that the form shows, both are computed
    in place; only other names are joined, as far as there are any."""
    found = stored(static_track.triples(stmts).select("stmt_id", "phrase", "h_name", "t_name"))
    counts = found.select(F.explode(F.array("h_name", "t_name")).alias("surface")).groupBy("surface").agg(F.count("*").alias("n"))
    names = stored(resolve(counts, state, lexicon, cfg, guided))
    shown = F.coalesce(entities.kind_of("norm"), F.lit("value"))
    odd = stored(names.where((F.col("entity") != F.col("norm")) | (F.col("type") != shown)).select("surface", "entity", "type"))

    def named(rows: DataFrame) -> DataFrame:
        for name, entity, kind in (("h_name", "h", "head_type"), ("t_name", "t", "tail_type")):
            met = rows.withColumn("_n", normal(name, cfg)).join(odd.select(F.col("surface").alias(name), F.col("entity").alias("_e"), F.col("type").alias("_t")), name, "left")
            rows = met.withColumn(entity, F.coalesce("_e", "_n")).withColumn(kind, F.coalesce("_t", entities.kind_of("_n"), F.lit("value"))).drop(name, "_n", "_e", "_t")
        return rows

    return found, names, named


def known_names(cands: DataFrame, state: State, cfg: LoopConfig) -> DataFrame:
    """(alias, relation, swapped) for the names of the batch: registered ones as they are, and others under the nearest of the K
    schemas that are retrieved for them, if that is near enough. Requests are distinct names, not statements."""
    own = settled(cands.select("phrase").distinct())
    passed = state.newest("relations", "relation").where("verdict = 'PASS'").select("relation")
    registered = settled(state.newest("aliases", "alias").join(passed, "relation", "left_semi").select("alias", "relation", "swapped"))
    near = guidance.retrieve(own, registered, cfg.retrieve_k)
    best = near.where((F.col("rank") == 1) & (F.col("score") >= cfg.reuse_min)).join(registered, "alias").select(F.col("phrase").alias("alias"), "relation", "swapped")
    return best


def step(state: State, stmts: DataFrame, k: int, cfg: LoopConfig, lexicon: DataFrame | None = None, extractor: Callable[[DataFrame], DataFrame] | None = None, recheck: bool = True) -> State:
    """The state after batch k. stmts: (stmt_id, text, seq); lexicon (name, type): types that are known beforehand; extractor: what an
    imperfect extractor makes of the named candidates (stmt_id, head, relation, tail, ...) before the gates."""
    guided = cfg.guided(k) and state.k >= 0
    active = state.active()
    routed = routing.route(stmts.select("stmt_id", "text", "seq"), "routed" if cfg.events else "static")
    parsed = settled(event_track.events(routed.where("track = 'event'")).withColumn("batch_id", F.lit(k)))
    # a statement without an event's structure is a plain one, whatever the route
    plain = routed.where((F.col("track") != "event") | ~event_track.shaped())
    found, names, named = static_candidates(plain, state, lexicon, cfg, guided)
    made = [decisions("entity_reuse", names.where("reused"), "surface", F.lit("REUSE"))] if guided else []

    # names as the registry has them, and the gates
    known = settled(known_names(found, state, cfg)) if guided and cfg.guidance else None
    none = state.spark.createDataFrame([], "alias string, relation string, swapped boolean")
    says = lambda rows: typed_under(guidance.constrain(named(rows), none if known is None else known))
    said = says(found).withColumn("told", F.struct(*evidence.TOLD))
    offered = extractor(said) if extractor else said
    same = evidence.as_said() if "told" in offered.columns else F.lit(False)
    offered = as_told(stored(offered.withColumn("as_said", same).drop("told", "h", "t")))  # h and t are the ends, in the order of the text
    if cfg.evidence:
        # statements that the extractor left as they are need no second look
        changed = offered.where("not as_said")
        asked = found.join(stored(changed.select("stmt_id").distinct()), "stmt_id", "left_semi")
        judged = stored(evidence.verify(changed, says(asked).select(*evidence.TOLD), None))
        made.append(decisions("evidence_gate", judged.where("verdict = 'REJECTED'"), "stmt_id", "verdict"))
        offered = offered.where("as_said").unionByName(judged.where("verdict = 'ACCEPTED'").drop("verdict"))
    offered = offered.drop("as_said")
    if cfg.logic:
        bad = logic.self_loops(offered).select("stmt_id", "head", "relation", "tail", "reason").unionByName(logic.mutual_pairs(offered, active.select(*graph.KEY)).select("stmt_id", "head", "relation", "tail", "reason"))
        if guided:
            vetted = logic.signatures(offered, state.newest("relations", "relation").where("verdict = 'PASS'"))
            bad = bad.unionByName(vetted.where("not fits").select("stmt_id", "head", "relation", "tail", F.lit("signature").alias("reason")))
        bad = stored(bad.distinct())
        made.append(decisions("logic", bad, "stmt_id", "reason"))
        offered = offered.join(bad.select("stmt_id", *graph.KEY), ["stmt_id", *graph.KEY], "left_anti")

    # events: one of each, new to the index, with the roles of their schema
    fresh, event_notes = new_events(parsed, state, cfg, guided) if not parsed.isEmpty() else (parsed.withColumn("subject", F.lit("")), [])
    made += event_notes
    changes = fresh.where(intent.intent("text") == "EVOLUTIONARY") if cfg.intent else fresh
    made.append(decisions("intent", fresh, "stmt_id", intent.intent("text")))

    # what the batch teaches
    counts = relation_schema.counted(offered.select("phrase", F.col("h").alias("h"), F.col("t").alias("t"), F.col("h_type").alias("head_type"), F.col("t_type").alias("tail_type"))).withColumn("batch_id", F.lit(k))
    counts = settled(counts)
    support = settled(state.table("support").unionByName(counts))
    schema = induced(support, state, cfg) if not counts.isEmpty() else state.newest("relations", "relation").withColumn("swaps", F.lit(None).cast("map<string,boolean>"))
    passed = schema.where("verdict = 'PASS'").select("relation")
    aliases = settled(schema_aliases(schema, state))
    made.append(decisions("schema_review", schema, "relation", "verdict"))
    kinds = event_schema.register(event_track.as_structs(fresh).unionByName(event_track.as_structs(indexed(state))), cfg) if cfg.events else state.spark.createDataFrame([], TABLES["event_types"])

    # its own facts under what is registered now
    final = typed_under(guidance.constrain(offered.drop("head", "relation", "tail", "head_type", "tail_type", "swapped", "unseen").withColumnsRenamed({"h_type": "head_type", "t_type": "tail_type"}), aliases.join(passed, "relation", "left_semi")))
    if recheck and cfg.logic:
        vetted = logic.signatures(final, schema.where("verdict = 'PASS'"))
        late = vetted.where("not fits")
        made.append(decisions("logic", late, "stmt_id", F.lit("signature")))
        final = vetted.where("fits")
    facts = final.select(*graph.KEY, F.lit(None).cast("timestamp_ntz").alias("valid_time"), F.lit(None).cast("array<bigint>").alias("ord"), "stmt_id")
    told = relationalize.facts(event_track.as_structs(fresh)).select(F.col("head"), "relation", "tail", F.lit(None).cast("timestamp_ntz").alias("valid_time"), F.lit(None).cast("array<bigint>").alias("ord"), F.col("head").alias("stmt_id"))
    up, down = state_changes(event_track.state_facts(changes, cfg.coref), active, cfg)
    # dealt by edge once, so that rows are sorted once for the duplicates and the join
    new = facts.unionByName(told).repartition(*graph.KEY).dropDuplicates(graph.KEY).join(active.select(*graph.KEY), graph.KEY, "left_anti").unionByName(up)
    log = new.select(*graph.KEY, F.lit("ACTIVE").alias("status"), F.lit(1).alias("seq"), "stmt_id", "valid_time", "ord").unionByName(down.select(*graph.KEY, F.lit("DEPRECATED").alias("status"), F.lit(0).alias("seq"), F.col("by_stmt").alias("stmt_id"), F.col("at").alias("valid_time"), F.lit(None).cast("array<bigint>").alias("ord")))
    all_made = made[0]
    for m in made[1:]:
        all_made = all_made.unionByName(m)
    tables = {
        "log": log,
        "profiles": names.select("entity", "type", "norm", F.col("surface").alias("alias"), "n"),
        "support": counts.drop("batch_id"),
        "aliases": aliases,
        "relations": schema,
        "event_types": kinds,
        "event_index": fresh.select(F.col("stmt_id").alias("id"), "trigger", "subject", "object", F.col("valid_time").alias("at")),
        "decisions": all_made,
    }
    state.store.commit(k, {n: df.withColumn("batch_id", F.lit(k)).select(*columns(n)) for n, df in tables.items()}, parent=state.k)
    return State(state.store, k)


def typed_under(rows: DataFrame) -> DataFrame:
    """Constrained candidates with head_type and tail_type turned as their heads and tails are; the text's own kept as h_type, t_type."""
    turned = F.coalesce("swapped", F.lit(False))
    kept = rows.withColumnsRenamed({"head_type": "h_type", "tail_type": "t_type"})
    return kept.withColumn("head_type", F.when(turned, F.col("t_type")).otherwise(F.col("h_type"))).withColumn("tail_type", F.when(turned, F.col("h_type")).otherwise(F.col("t_type")))


def as_told(rows: DataFrame) -> DataFrame:
    """h and t of candidates whose head or tail an extractor has changed, in the order of the text again."""
    turned = F.coalesce("swapped", F.lit(False))
    return rows.withColumn("h", F.when(turned, F.col("tail")).otherwise(F.col("head"))).withColumn("t", F.when(turned, F.col("head")).otherwise(F.col("tail")))


def indexed(state: State) -> DataFrame:
    """The registry's events in the form of parsed ones."""
    return state.table("event_index").select(F.col("id").alias("stmt_id"), "trigger", F.col("subject").alias("alias"), F.lit(None).cast("string").alias("qualifier"), "object", F.col("at").alias("valid_time"), "batch_id")


def new_events(parsed: DataFrame, state: State, cfg: LoopConfig, guided: bool) -> tuple[DataFrame, list[DataFrame]]:
    """Events of the batch that are neither another's double nor in the index, and whose roles fit."""
    rows = parsed.withColumn("subject", F.concat_ws(" ", "alias", "qualifier") if cfg.coref else F.col("alias"))
    form = rows.select(F.col("stmt_id").alias("id"), "trigger", "subject", "object", F.col("valid_time").alias("at"))
    twins = settled(event_coref.doubles(form, cfg))
    notes = [decisions("event_pair", twins, "id", F.lit("MERGE"))]
    rest = rows.join(twins.select(F.col("id").alias("stmt_id")), "stmt_id", "left_anti")
    if guided:
        left = form.join(twins.select("id"), "id", "left_anti")
        seen = settled(event_coref.matches(left, state.table("event_index"), cfg).where("aligned"))
        notes.append(decisions("event_alignment", seen, "id", F.lit("ALIGNED")))
        rest = rest.join(seen.select(F.col("id").alias("stmt_id")), "stmt_id", "left_anti")
        fits = logic.roles(event_track.as_structs(rest).select("event_id", "trigger", "roles"), state.newest("event_types", "trigger").where("verdict = 'PASS'"))
        wrong = settled(fits.where("not fits").select(F.col("event_id").alias("stmt_id")))
        notes.append(decisions("roles", wrong, "stmt_id", F.lit("REJECTED")))
        rest = rest.join(wrong, "stmt_id", "left_anti")
    return settled(rest), notes


def state_changes(facts: DataFrame, active: DataFrame, cfg: LoopConfig) -> tuple[DataFrame, DataFrame]:
    """(added, retired) state facts: only the heads that the batch speaks of are read from the graph."""
    own = active.where(F.col("relation").isin(*event_track.STATE_RELATIONS)).join(facts.select("head").distinct(), "head", "left_semi")
    cols = [*graph.KEY, "valid_time", "ord", "stmt_id"]
    if not (cfg.intent and cfg.events):
        first = facts.groupBy(*graph.KEY).agg(F.min_by(F.struct("valid_time", "ord", "stmt_id"), F.struct("valid_time", "ord")).alias("x")).select(*graph.KEY, "x.*")
        return first.join(own.select(*graph.KEY), graph.KEY, "left_anti").select(*cols), own.limit(0).withColumn("by_stmt", F.lit("")).withColumn("at", F.col("valid_time"))
    change = graph.latest(facts)
    down = settled(intent.targets(change, own))
    stale = own.select("head", "relation", F.struct("valid_time", "ord").alias("_have"))
    newer = change.join(stale, ["head", "relation"], "left").where(F.col("_have").isNull() | (F.col("_have") <= F.struct("valid_time", "ord"))).drop("_have")
    return settled(newer.join(own.select(*graph.KEY), graph.KEY, "left_anti").select(*cols)), down


def induced(support: DataFrame, state: State, cfg: LoopConfig) -> DataFrame:
    """Schemas over all counts so far, under the names that earlier batches registered."""
    rows = settled(relation_schema.signed(support))
    mapping = relation_schema.canonicalise(rows, state.newest("aliases", "alias").select("alias", "relation", "swapped"))
    total = support.groupBy("phrase", "head_type", "tail_type").agg(F.sum("n").alias("n"))
    proposed = relation_schema.propose(rows, mapping, cfg, total)
    way = mapping.groupBy("relation").agg(F.map_from_entries(F.collect_list(F.struct("alias", "swapped"))).alias("swaps"))
    return settled(proposed.join(way, "relation"))


def schema_aliases(schema: DataFrame, state: State) -> DataFrame:
    """(alias, relation, swapped) of all classes, pooled ones too, so that a name keeps its class when that passes later."""
    return schema.select("relation", F.explode("swaps").alias("alias", "swapped")).select("alias", "relation", "swapped")


def run(stmts: DataFrame, root: str, cfg: LoopConfig | None = None, batches: list[int] | None = None, **how) -> State:
    """Batches of stmts (stmt_id, text, seq, batch_id) in order, each one commit under root."""
    cfg = cfg or LoopConfig()
    state = State(Store(stmts.sparkSession, root), -1)
    for k in batches if batches is not None else range(cfg.windows):
        state = step(state, stmts.where(F.col("batch_id") == k), k, cfg, **how)
    return state


def cost(state: State) -> DataFrame:
    """(batch_id, kind, decided, requests): decisions of every point, and how many different items they were about."""
    return state.table("decisions").groupBy("batch_id", "kind").agg(F.count("*").alias("decided"), F.countDistinct("item").alias("requests"))
