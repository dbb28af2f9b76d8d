"""Relation schemas induced from accepted facts.

Everything here works on the vocabulary of relation names with counts, never on facts: a batch adds its counts once,
and all counts so far are looked at again, so a name that was too rare waits in the pool until it isn't.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgflow.config import LoopConfig
from kgflow.coref.cluster import components
from kgflow.functions.text import cosine, hashed_ngrams
from kgflow.session import settled

AUXILIARY = ("is", "was", "has", "with", "by", "of", "in")
#: Share of facts that have to keep to "one tail per head" (or the reverse) for that to count as a relation's way.
REGULAR = 0.95


def stem(name: Column | str) -> Column:
    """The words of a relation name that carry meaning; the name itself if none does."""
    parts = F.filter(F.split(name, "_"), lambda w: ~w.isin(*AUXILIARY))
    name = F.col(name) if isinstance(name, str) else name
    return F.when(F.size(parts) > 0, F.array_join(parts, "_")).otherwise(name)


def support(facts: DataFrame) -> DataFrame:
    """(phrase, batch_id, support, heads): keyed by batch, so that a repeated batch does not count twice."""
    return facts.groupBy("phrase", "batch_id").agg(F.count("*").alias("support"), F.countDistinct("h").alias("heads"))


def counted(facts: DataFrame) -> DataFrame:
    """(phrase, head_type, tail_type, n, heads, tails) of facts (phrase, h, t, head_type, tail_type), one row per name and pair of types."""
    return facts.groupBy("phrase", "head_type", "tail_type").agg(F.count("*").alias("n"), F.countDistinct("h").alias("heads"), F.countDistinct("t").alias("tails"))


def signatures(facts: DataFrame) -> DataFrame:
    return signed(counted(facts))


def signed(counts: DataFrame) -> DataFrame:
    """(phrase, support, heads, tails, head_type, tail_type, share): the dominant pair of types per name, over the counts of all batches."""
    total = counts.groupBy("phrase", "head_type", "tail_type").agg(F.sum("n").alias("n"), F.sum("heads").alias("heads"), F.sum("tails").alias("tails"))
    every = Window.partitionBy("phrase")
    first = F.row_number().over(every.orderBy(F.desc("n"), "head_type", "tail_type"))
    rows = total.withColumn("support", F.sum("n").over(every)).withColumn("r", first).where("r = 1")
    return rows.select("phrase", "support", "heads", "tails", "head_type", "tail_type", F.round(F.col("n") / F.col("support"), 6).alias("share"), (F.col("heads") >= REGULAR * F.col("n")).alias("one_tail"), (F.col("tails") >= REGULAR * F.col("n")).alias("one_head"))


def clusters(rows: DataFrame, least: float) -> DataFrame:
    """rows with cluster: names on the same two types, in either direction, whose vectors are within a cosine of least, by components."""
    v = settled(rows.select("phrase", F.least("head_type", "tail_type").alias("lo"), F.greatest("head_type", "tail_type").alias("hi"), hashed_ngrams(stem("phrase")).alias("v")))
    near = v.alias("x").join(v.alias("y"), (F.col("x.lo") == F.col("y.lo")) & (F.col("x.hi") == F.col("y.hi")) & (F.col("x.phrase") < F.col("y.phrase"))).where(cosine("x.v", "y.v") >= least)
    labels = components(near.select(F.col("x.phrase").alias("a"), F.col("y.phrase").alias("b")))
    return rows.join(labels, F.col("phrase") == F.col("node"), "left").withColumn("cluster", F.coalesce("label", "phrase")).drop("node", "label")


def with_inverses(rows: DataFrame) -> DataFrame:
    """rows with class: a cluster and the one that says the same the other way round. That is so if each is the only cluster from one
    type to the other, and where one gives every head one tail, the other gives every tail one head."""
    way = F.when(F.col("lo") != F.col("hi"), F.col("lo") == F.col("head_type"))
    lead = Window.partitionBy("cluster").orderBy(F.desc("support"), "phrase")
    top = rows.withColumn("lo", F.least("head_type", "tail_type")).withColumn("hi", F.greatest("head_type", "tail_type")).withColumn("r", F.row_number().over(lead)).where("r = 1").withColumn("forward", way)
    mixed = rows.groupBy("cluster").agg(F.countDistinct("head_type", "tail_type").alias("ways")).where("ways > 1").select("cluster")
    lone = top.join(mixed, "cluster", "left_anti").where("forward is not null")
    per = lone.groupBy("lo", "hi").agg(F.count_if("forward").alias("a"), F.count_if(~F.col("forward")).alias("b"), F.min("cluster").alias("class"), F.max(F.when(F.col("forward"), F.struct("one_tail", "one_head"))).alias("x"), F.max(F.when(~F.col("forward"), F.struct("one_tail", "one_head"))).alias("y"))
    mirrored = ((F.col("x.one_tail") & F.col("y.one_head")) | (F.col("x.one_head") & F.col("y.one_tail"))) & (F.col("a") == 1) & (F.col("b") == 1)
    turned = lone.select("cluster", "lo", "hi").join(per.where(mirrored), ["lo", "hi"]).select("cluster", "class")
    return rows.join(turned, "cluster", "left").withColumn("class", F.coalesce("class", "cluster"))


def canonicalise(rows: DataFrame, known: DataFrame | None = None, least: float = 0.8) -> DataFrame:
    """(alias, relation, swapped, support, class): names of one meaning under the name that is used most, or, where an earlier batch
    registered one (known: alias, relation, swapped), under that one and in its direction."""
    grouped = with_inverses(settled(clusters(settled(rows), least)))
    if known is not None:
        grouped = grouped.join(known.select(F.col("alias").alias("phrase"), F.col("relation").alias("old"), F.col("swapped").alias("old_swapped")), "phrase", "left")
    else:
        grouped = grouped.withColumn("old", F.lit(None).cast("string")).withColumn("old_swapped", F.lit(None).cast("boolean"))
    lead = Window.partitionBy("class").orderBy(F.col("old").isNull(), F.desc("support"), "phrase").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    first = lambda c: F.first(c).over(lead)
    name, turned = F.coalesce(first("old"), first("phrase")), F.coalesce(first("old_swapped"), F.lit(False))
    way = F.when(turned, first("tail_type")).otherwise(first("head_type"))
    swapped = (F.col("head_type") != F.col("tail_type")) & (way != F.col("head_type"))
    out = grouped.select(F.col("phrase").alias("alias"), F.coalesce("old", name).alias("relation"), F.coalesce("old_swapped", swapped).alias("swapped"), "support", "class")
    return settled(out)  # a vocabulary


def coherence(mapping: DataFrame, dim: int = 64) -> DataFrame:
    """(relation, coherence): mean pairwise cosine of the names in a class that run in one direction; 1 for single names."""
    v = settled(mapping.select("relation", "swapped", "alias", hashed_ngrams(stem("alias"), dim).alias("v")))
    pairs = v.alias("x").join(v.alias("y"), ["relation", "swapped"]).where("x.alias < y.alias").groupBy("relation").agg(F.round(F.avg(cosine("x.v", "y.v")), 6).alias("c"))
    return mapping.select("relation").distinct().join(pairs, "relation", "left").select("relation", F.coalesce("c", F.lit(1.0)).alias("coherence"))


def propose(rows: DataFrame, mapping: DataFrame, cfg: LoopConfig, counts: DataFrame | None = None) -> DataFrame:
    """(relation, support, heads, share, aliases, domain, range, coherence, verdict) per class. The end that the other one determines has
    one type in a schema, the one that most facts have; the other end has all types seen with it. So a relation that gives
    every head one tail has one range and may have several domains, and the reverse. The review passes classes with enough support
    and heads, coherent names, and a type of the determined end that most facts have; others wait in the pool."""
    joined = settled(mapping.join(rows.select(F.col("phrase").alias("alias"), "heads", "share", "one_tail", "one_head", F.col("head_type").alias("ht"), F.col("tail_type").alias("tt")), "alias"))
    turn = lambda a, b: F.when(F.col("swapped"), F.col(b)).otherwise(F.col(a))
    classes = joined.groupBy("relation").agg(
        F.sum("support").alias("support"), F.max("heads").alias("heads"), F.array_sort(F.collect_set("alias")).alias("aliases"),
        F.max_by(F.struct(turn("one_tail", "one_head").alias("tail"), turn("one_head", "one_tail").alias("head")), F.struct("support", "alias")).alias("one"),
    )
    pairs = joined.select("alias", "relation", "swapped", "ht", "tt", F.col("support").alias("n")) if counts is None else mapping.select("alias", "relation", "swapped").join(counts.select(F.col("phrase").alias("alias"), F.col("head_type").alias("ht"), F.col("tail_type").alias("tt"), "n"), "alias")
    cells = pairs.groupBy("relation", turn("ht", "tt").alias("d"), turn("tt", "ht").alias("r")).agg(F.sum("n").alias("n")).join(classes.select("relation", (F.col("one.head") & ~F.col("one.tail")).alias("by_tail")), "relation")
    fixed, free = F.when(F.col("by_tail"), F.col("d")).otherwise(F.col("r")), F.when(F.col("by_tail"), F.col("r")).otherwise(F.col("d"))
    per = cells.groupBy("relation", "by_tail", fixed.alias("fixed")).agg(F.sum("n").alias("n"), F.array_sort(F.collect_set(free)).alias("free"))
    top = per.groupBy("relation", "by_tail").agg(F.max_by(F.struct("fixed", "free", "n"), F.struct("n", "fixed")).alias("x"), F.sum("n").alias("all"))
    one, many = F.array("x.fixed"), F.col("x.free")
    schema = top.select("relation", F.when(F.col("by_tail"), one).otherwise(many).alias("domain"), F.when(F.col("by_tail"), many).otherwise(one).alias("range"), F.round(F.col("x.n") / F.col("all"), 6).alias("share"))
    out = classes.drop("one").join(schema, "relation").join(coherence(mapping), "relation")
    ok = (F.col("support") > cfg.theta_relation) & (F.col("heads") >= cfg.review_heads) & (F.col("share") >= cfg.review_type_share) & (F.col("coherence") >= cfg.coherence_min)
    return out.withColumn("verdict", F.when(ok, "PASS").otherwise("POOL"))


def retry(pool: DataFrame, support_by_batch: DataFrame, theta: int) -> DataFrame:
    """Pooled phrases whose support over all batches now exceeds theta: (phrase, support)."""
    return pool.select("phrase").distinct().join(support_by_batch, "phrase").groupBy("phrase").agg(F.sum("support").alias("support")).where(F.col("support") > theta)


def traits(edges: DataFrame) -> DataFrame:
    """(relation, edges, symmetric_share, functional_share) of edges (head, relation, tail)."""
    e = edges.select("head", "relation", "tail").distinct()
    turned = e.select(F.col("tail").alias("head"), "relation", F.col("head").alias("tail"), F.lit(1).alias("back"))
    sym = e.join(turned, ["head", "relation", "tail"], "left").groupBy("relation").agg(F.count("*").alias("edges"), F.round(F.avg(F.coalesce("back", F.lit(0))), 6).alias("symmetric_share"))
    fun = e.groupBy("relation", "head").agg(F.count("*").alias("n")).groupBy("relation").agg(F.round(F.avg((F.col("n") == 1).cast("int")), 6).alias("functional_share"))
    return sym.join(fun, "relation")
