"""A corpus run: toxicity, line dedup, near-dedup, decontamination, tokens.

Each stage takes (spark, docs, sf_dir), works on all rows that the stage before kept, and returns
the rows that it keeps; all but the last return the columns of documents. The checks of a
stage are those of its operator; null and empty texts pass every filter.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgflow.llm import bpe, decontam, lines, neardup, toxicity
from kgflow.session import removed, shared_dir, ship

#: Similarity, in percent, from which documents are near-duplicates.
NEAR_PERCENT = 80


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents more likely toxic than not go; the model is fitted on labelled rows of this stage's input."""
    ship(spark)
    model = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.score(docs, model).where(~F.col("_toxic")).drop("_severity", "_grade", "_toxic")


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of three-line windows go, and with them documents of which no line is left."""
    ship(spark)
    out = lines.deduplicate(docs)
    left = (F.col("_removed") == 0) | (F.col("_removed") < F.col("_lines"))
    size = F.when(F.col("_removed") > 0, F.char_length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars"))
    return out.where(left).withColumn("n_chars", size).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of every group of near-duplicates the document with the least id stays."""
    ship(spark)
    gone = neardup.label_documents(docs, NEAR_PERCENT).where(~F.col("kept")).select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage go."""
    ship(spark)
    return decontam.contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).where(F.size("_found") == 0).select(*docs.columns)


def count_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What is left, encoded and decoded: (doc_id, n_tokens, ids_sha256, decoded_sha256)."""
    ship(spark)
    return bpe.round_trip_digests(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("line dedup", drop_repeated_lines),
    ("near-dedup", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("tokens", count_tokens),
]

#: No SQL: the fitted model, the banding and the tokenizer have none; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each stage's rows are written to the shared folder and read again. A
    stage's folder goes when the next one's is written; the last one's stays, as the result reads it."""
    folder = f"{shared_dir(spark)}/corpus-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
        if k:
            removed(spark, f"{folder}/{k - 1}")
    return docs
