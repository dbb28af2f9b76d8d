"""Entity coreference: within a batch, and against the profiles of earlier batches."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgflow.coref.cluster import components
from kgflow.functions.ids import joined_id
from kgflow.functions.text import dot, hashed_ngrams, normalised, number_token, tokens
from kgflow.session import stored

KINDS = "customer|supplier|order|part"
#: What normalised() makes a known kind and one number of, in lower case: marks around and between them, zeros before the number.
NUMBERED = rf"^[^\p{{L}}\p{{N}}]*({KINDS})[^\p{{L}}\p{{N}}]*0*([0-9]+)[^\p{{L}}\p{{N}}]*$"


def canonical(name: Column | str) -> Column:
    """Numbered names of known kinds in their normal form; other names in lower case."""
    name = F.col(name) if isinstance(name, str) else name
    return F.trim(F.regexp_replace(F.lower(name), NUMBERED, "$1 $2"))


def kind_of(name: Column | str) -> Column:
    name = F.col(name) if isinstance(name, str) else name
    return F.nullif(F.regexp_extract(name, rf"^({KINDS}) [0-9]+$", 1), F.lit(""))


def infer_types(names: DataFrame, lexicon: DataFrame, name: str = "name") -> DataFrame:
    """names with a column type: by prefix, then by the lexicon (name, type) of known profiles, else value."""
    known = lexicon.groupBy(F.col("name").alias(name)).agg(F.min("type").alias("_t"))
    return names.join(known, name, "left").withColumn("type", F.coalesce(kind_of(name), "_t", F.lit("value"))).drop("_t")


def pair_verdict(a: Column | str, b: Column | str) -> Column:
    """MERGE: equal normal forms; HIERARCHY: the words of one strictly inside the other's and no
    number that conflicts; else SEPARATE."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    ta, tb = F.array_distinct(tokens(a)), F.array_distinct(tokens(b))
    both = F.size(F.array_intersect(ta, tb))
    inside = (both == F.least(F.size(ta), F.size(tb))) & (F.size(tokens(a)) != F.size(tokens(b)))
    return F.when(normalised(a) == normalised(b), "MERGE").when(inside, "HIERARCHY").otherwise("SEPARATE")


def block_pairs(surfaces: DataFrame, surface: str = "surface") -> DataFrame:
    """(a, b) distinct surfaces, a before b, that may merge or lie one in the other: forms that are equal, or of which
    one's words are all among the other's, and whose first numbers don't differ. A surface asks by its rarest word, and is met by those that have that word, so
    common words make no large blocks, and no pair is lost, whatever the size of a block."""
    own = surfaces.select(F.col(surface).alias("s")).distinct().select("s", F.array_distinct(tokens("s")).alias("w")).where("size(w) > 0")
    number = F.regexp_extract(normalised("s"), r"([0-9]+)", 1)
    own = own.withColumn("first", number)
    each = own.select("s", F.explode("w").alias("word"))
    often = each.groupBy("word").agg(F.count("*").alias("n"))
    rarest = each.join(often, "word").groupBy("s").agg(F.min(F.struct("n", "word"))["word"].alias("word"))
    asks = rarest.join(own, "s").select(F.col("s").alias("x"), F.col("w").alias("wx"), "first", "word")
    has = each.join(own, "s").select(F.col("s").alias("y"), F.col("w").alias("wy"), "first", "word")
    pairs = asks.join(has, ["word", "first"]).where("x <> y").where(F.size(F.array_except("wx", "wy")) == 0)
    return pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def intra(surfaces: DataFrame, surface: str = "surface") -> DataFrame:
    """(surface, cluster): least surface of each group joined by MERGE verdicts."""
    merged = block_pairs(surfaces, surface).where(pair_verdict("a", "b") == "MERGE")
    labels = components(merged)
    own = surfaces.select(F.col(surface).alias("surface")).distinct()
    return own.join(labels, F.col("surface") == F.col("node"), "left").select("surface", F.coalesce("label", "surface").alias("cluster"))


def cross(clusters: DataFrame, profiles: DataFrame) -> DataFrame:
    """clusters (cluster, norm, type) with entity_id and reused: the id of a profile (entity_id, norm, type)
    with the same type and normal form, whose numbers then agree as well, else a new id."""
    old = profiles.groupBy("norm", "type").agg(F.min("entity_id").alias("_old"))
    minted = joined_id("type", "norm")
    return clusters.join(old, ["norm", "type"], "left").withColumn("entity_id", F.coalesce("_old", minted)).withColumn("reused", F.col("_old").isNotNull()).drop("_old")


def align(typed: DataFrame, profiles: DataFrame, cfg) -> DataFrame:
    """typed (surface, norm, type) with entity and reused, against profiles (entity, type, norm). The profile of the same form and
    type is taken; for other names the profile_top most similar ones of the same type, number and first two letters are
    candidates, and the best is taken if it is similar enough; else the name is a new entity."""
    # dealt by name once, so that rows are sorted once for the minimum and the join
    exact = profiles.select("norm", "type", "entity").repartition("norm", "type").groupBy("norm", "type").agg(F.min("entity").alias("_same"))
    first = stored(typed.join(exact, ["norm", "type"], "left"))
    key = [F.col("type").alias("type"), F.coalesce(number_token("norm"), F.lit("")).alias("number"), F.substring("norm", 1, 2).alias("start")]
    open_ = first.where("_same is null").select(*key, "norm")
    near = open_.join(profiles.select(*key, "entity", F.col("norm").alias("old")), ["type", "number", "start"])
    scored = near.select("type", "norm", "entity", "old").distinct().select("type", "norm", "entity", F.round(dot(hashed_ngrams("norm"), hashed_ngrams("old")), 6).alias("score"))
    rank = F.row_number().over(Window.partitionBy("type", "norm").orderBy(F.desc("score"), "entity"))
    top = scored.withColumn("r", rank).where(F.col("r") <= cfg.profile_top)
    best = top.where((F.col("r") == 1) & (F.col("score") >= cfg.reuse_min)).select("type", "norm", F.col("entity").alias("_near"))
    out = first.join(stored(best), ["type", "norm"], "left")
    return out.withColumn("entity", F.coalesce("_same", "_near", "norm")).withColumn("reused", F.coalesce("_same", "_near").isNotNull()).drop("_same", "_near")
