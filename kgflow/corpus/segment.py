"""Statements and structural facts out of raw text tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

ANCHOR = r'<a[^>]*href="([^"]*)"'
LICENSE = r"(?i)(MIT|Apache|General Public|CC BY[A-Z-]*)[ ,]*(?:License|[0-9])"
EMAIL = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}"


def page_facts(pages: DataFrame) -> DataFrame:
    """(page_id, relation, tail): host, title, language and links of every page."""
    host = pages.select("page_id", F.lit("host").alias("relation"), F.regexp_extract("url", r"://([^/?#]*)", 1).alias("tail"))
    title = pages.select("page_id", F.lit("title").alias("relation"), F.regexp_extract("html", r"<title>([^<]*)</title>", 1).alias("tail"))
    links = pages.select("page_id", F.lit("links_to").alias("relation"), F.explode(F.regexp_extract_all("html", F.lit(ANCHOR), F.lit(1))).alias("tail"))
    return host.unionByName(title).unionByName(links).where("tail <> ''")


def license_facts(documents: DataFrame) -> DataFrame:
    """(doc_id, relation, tail): license that a document names."""
    return documents.select("doc_id", F.lit("licensed_under").alias("relation"), F.lower(F.regexp_extract("text", LICENSE, 1)).alias("tail")).where("tail <> ''")


def contact_facts(documents: DataFrame) -> DataFrame:
    """(doc_id, relation, tail): first contact address, hashed; never in clear."""
    found = F.regexp_extract("text", EMAIL, 0)
    return documents.select("doc_id", F.lit("contact_hash").alias("relation"), F.md5(F.lower(found)).alias("tail"), found.alias("f")).where("f <> ''").drop("f")


def conversation_facts(conversations: DataFrame) -> DataFrame:
    """(conv_id, turn, relation, tail): roles, and which turn a turn follows."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    rows = conversations.withColumn("before", F.lag("turn").over(w))
    role = rows.select("conv_id", "turn", F.lit("has_role").alias("relation"), F.col("role").alias("tail"))
    return role.unionByName(rows.where("before is not null").select("conv_id", "turn", F.lit("follows").alias("relation"), F.col("before").cast("string").alias("tail")))


def sentences(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, seg_no, text) of every sentence-like segment."""
    parts = F.split(F.coalesce(text_col, F.lit("")), r"(?<=[.!?])\s+")
    return df.select(id_col, F.posexplode(parts).alias("seg_no", "text")).where("trim(text) <> ''")


def trusted(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """Documents that no label calls toxic or of low quality."""
    bad = labels.where("toxic = 1 or quality = 0").select("doc_id")
    return documents.join(bad, "doc_id", "left_anti")


#: Characters between the words by which passages are looked up.
BETWEEN = r"[^\p{L}\p{N}]+"


def containing(documents: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id) of documents that hold a benchmark passage character for character. Anchored on the longest
    word inside the passage: with a separator on both sides it is a whole word of every text that holds the
    passage, whatever stands around that, so texts meet passages by an equi-join. Passages without such
    a word are compared with every text."""
    parts = F.split("text", BETWEEN)
    inner = F.filter(F.slice(parts, 2, F.greatest(F.size(parts) - 2, F.lit(0))), lambda w: w != "")
    longest = F.array_max(F.transform(inner, lambda w: F.struct(F.length(w).alias("n"), w.alias("w"))))["w"]
    # the text itself goes only where a passage's word stands, once per passage
    items = benchmark.where("text is not null").select(F.col("text").alias("passage"), longest.alias("w")).distinct()
    probe = documents.select("doc_id", F.explode(F.array_distinct(F.split("text", BETWEEN))).alias("w"))
    held = F.expr("instr(text, passage) > 0")
    met = probe.join(items.where("w is not null"), "w").select("doc_id", "passage").distinct()
    anchored = documents.join(met, "doc_id").where(held).select("doc_id")
    rest = documents.join(items.where("w is null"), held).select("doc_id")
    return anchored.unionByName(rest).distinct()
