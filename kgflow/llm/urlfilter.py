"""URL filters as a sort-merge range join, in DataFrame functions only.

A rule (host, path prefix, verdict) covers its host and all subdomains where the url's path
starts with the prefix. Host labels are reversed and joined to the path by a separator below
every character, so each rule turns into the interval of all keys that start with its key.
Intervals of prefixes are disjoint or nested. A url asks one key per suffix of its host. Rules
and asked keys are sorted together; the sweep carries, from the last rule at or before a key,
the stack of rules nested around it, and the longest stack entry that the key starts with is
the rule in force.

The sweep runs in salted lanes: keys are dealt evenly by their salt and every lane gets all
rules as sorted rows, so a hot host never meets in one task, and the rules are neither
broadcast nor held in memory.

Edge cases: a null url or one without ``://`` has empty host and path and takes the default
verdict for hostless urls; of repeated rules with one key the verdict ``block`` wins; of
equally long rules the deeper host wins; repeated pages are judged one by one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Ends the host part of a key; sorts below every label character.
END = "\u0001"

#: Rules of the query (fixed values): host, path prefix, verdict.
RULES = (
    ("com", "/", "allow"),
    ("example.com", "/en/", "block"),
    ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"),
    ("net", "/fr/", "block"),
)


def host_of(url: Column) -> Column:
    rest = F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1)
    return F.coalesce(F.translate(rest, UPPER, LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def _key(labels: Column, path: Column) -> Column:
    return F.concat(F.array_join(F.reverse(labels), "."), F.lit(END), path)


def judge(pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow", hostless: str = "block", lanes: int | None = None) -> DataFrame:
    """(id, host, path, rule, verdict) for every row of pages; rules: (host, path, verdict)."""
    spark = pages.sparkSession
    lanes = lanes or max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))
    named = (
        rules.select(F.translate("host", UPPER, LOWER).alias("rh"), F.coalesce("path", F.lit("")).alias("rp"), "verdict")
        .where("rh is not null")
        .groupBy("rh", "rp")
        .agg(F.max("verdict").alias("rv"))  # block sorts after allow
        .withColumn("key", _key(F.split("rh", r"\."), F.col("rp")))
    )
    # the stack around each rule: rules whose key is a prefix of its own, found by asking every
    # prefix length of the key, an equi-join instead of a theta join
    prefixes = named.select(F.col("key").alias("of"), F.explode(F.transform(F.sequence(F.lit(1), F.length("key")), lambda n: F.substring("key", F.lit(1), n))).alias("key"))
    stacks = (
        prefixes.join(named, "key")
        .groupBy("of")
        .agg(F.array_sort(F.collect_list(F.struct(F.length("key").alias("depth"), "key", F.concat("rh", "rp").alias("rule"), F.length("rh").alias("reach"), F.col("rv").alias("verdict")))).alias("stack"))
        .select(F.col("of").alias("key"), "stack")
    )
    src = pages.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url"))
    src = src.select("id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    labels = F.split("host", r"\.")
    # every page keeps one row, with all the keys it asks, until the lanes
    asked = src.withColumn("row_key", F.xxhash64("id", "host", "path")).withColumn("labels", labels)
    asked = asked.select(
        "id", "host", "path", F.pmod(F.col("row_key"), F.lit(lanes)).cast("int").alias("lane"),
        F.explode(F.transform(F.sequence(F.lit(1), F.size("labels")), lambda n: F.struct(n.alias("n"), _key(F.slice("labels", -n, n), F.col("path")).alias("key")))).alias("q"),
    )
    stack_type = stacks.schema["stack"].dataType
    swept = (
        asked.select("lane", F.col("q.key").alias("key"), F.lit(1).alias("side"), "id", "host", "path", F.col("q.n").alias("n"), F.lit(None).cast(stack_type).alias("stack"))
        .unionByName(
            stacks.select(F.explode(F.sequence(F.lit(0), F.lit(lanes - 1))).alias("lane"), "key", F.lit(0).alias("side"), F.lit(None).cast("long").alias("id"), F.lit(None).cast("string").alias("host"), F.lit(None).cast("string").alias("path"), F.lit(0).alias("n"), "stack")
        )
        .withColumn("active", F.last("stack", ignorenulls=True).over(Window.partitionBy("lane").orderBy("key", "side").rowsBetween(Window.unboundedPreceding, Window.currentRow)))
        .where("side = 1")
    )
    hit = F.try_element_at(F.filter("active", lambda s: F.col("key").startswith(s["key"])), F.lit(-1))
    best = F.struct(F.length(hit["rule"]).alias("size"), hit["reach"].alias("reach"), hit["rule"].alias("rule"), hit["verdict"].alias("verdict"))
    # the asked keys of a row share its lane; n = 1 carries the row, so equal rows stay apart by count
    judged = (
        swept.withColumn("best", F.when(hit.isNotNull(), best))
        .groupBy("lane", "id", "host", "path")
        .agg(F.max("best").alias("best"), F.sum((F.col("n") == 1).cast("int")).alias("copies"))
        .withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies"))))
    )
    fallback = F.when(F.col("host") == "", F.lit(hostless)).otherwise(F.lit(default))
    return judged.select(F.col("id").alias(id_col), "host", "path", F.col("best.rule").alias("rule"), F.coalesce(F.col("best.verdict"), fallback).alias("verdict"))


def rule_table(spark, rules=RULES) -> DataFrame:
    rows = ", ".join("('{}', '{}', '{}')".format(*(str(x).replace("'", "''") for x in r)) for r in rules)
    return spark.sql(f"SELECT * FROM VALUES {rows} AS r(host, path, verdict)")


ORACLE = r"""
WITH rules(rh, rp, rv) AS (VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
parts AS (
  SELECT page_id, row_number() OVER () AS rn,
    CASE WHEN url LIKE '%://%' THEN translate(regexp_extract(substr(url, strpos(url, '://') + 3), '^[^/?#]*', 0), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') ELSE '' END AS host,
    CASE WHEN url LIKE '%://%' THEN regexp_extract(substr(url, strpos(url, '://') + 3), '^[^/?#]*([^?#]*)', 1) ELSE '' END AS path
  FROM pages),
hits AS (
  SELECT p.*, rh || rp AS rule, rv, row_number() OVER (PARTITION BY rn ORDER BY length(rh || rp) DESC NULLS LAST, length(rh) DESC) AS pick
  FROM parts p LEFT JOIN rules r ON (p.host = rh OR ends_with(p.host, '.' || rh)) AND starts_with(p.path, rp))
SELECT page_id, host, path, rule, coalesce(rv, CASE WHEN host = '' THEN 'block' ELSE 'allow' END) AS verdict FROM hits WHERE pick = 1
"""
