"""Readers of the given tables, and of exchange formats for triples."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, WriterCommitMessage

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
TRIPLE = "head string, relation string, tail string"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"unknown table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def table_stream(spark: SparkSession, sf_dir: str, name: str, files_per_trigger: int = 1) -> DataFrame:
    """The same table as a stream of its files."""
    schema = table(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)


def triples_from_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(TRIPLE).json(path)


def triples_from_csv(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(TRIPLE).option("header", True).option("escape", '"').option("multiLine", True).csv(path)


def statements_from_text(spark: SparkSession, path: str) -> DataFrame:
    """One statement per line; ids from file and content, so that re-reading gives the same ids."""
    raw = spark.read.text(path).select("value", F.input_file_name().alias("file"))
    return raw.where(F.trim("value") != "").select(F.md5(F.concat_ws("|", "file", "value")).alias("stmt_id"), F.col("value").alias("text"))


def to_lines(triples: DataFrame) -> DataFrame:
    """Triples as lines <head> <relation> "tail" . with percent-escaped names."""
    name = lambda c: F.concat(F.lit("<urn:kg:"), F.replace(F.url_encode(F.col(c)), F.lit("+"), F.lit("%20")), F.lit(">"))
    text = F.concat(F.lit('"'), F.regexp_replace(F.regexp_replace(F.regexp_replace("tail", r"\\", r"\\\\"), '"', r'\\"'), "\n", r"\\n"), F.lit('"'))
    return triples.select(F.concat_ws(" ", name("head"), name("relation"), text, F.lit(".")).alias("value"))


def from_lines(lines: DataFrame) -> DataFrame:
    """The reverse of to_lines; lines of another form are dropped."""
    form = r'^<urn:kg:([^>]*)> <urn:kg:([^>]*)> "((?:[^"\\]|\\.)*)" \.$'
    part = lambda i: F.regexp_extract("value", form, i)
    plain = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(part(3), r"\\\\", "\u0001"), r"\\n", "\n"), r'\\"', '"'), "\u0001", r"\\")
    return lines.where(F.col("value").rlike(form)).select(F.url_decode(part(1)).alias("head"), F.url_decode(part(2)).alias("relation"), plain.alias("tail"))


class LineTriples(DataSource):
    """spark.read.format('kgtriples').option('path', file).load(): lines of one local or shared file."""

    @classmethod
    def name(cls) -> str:
        return "kgtriples"

    def schema(self) -> str:
        return "value string"

    def reader(self, schema) -> DataSourceReader:
        path = self.options["path"]

        class Reader(DataSourceReader):
            def read(self, partition):
                with open(path, encoding="utf-8") as f:
                    for line in f:
                        yield (line.rstrip("\n"),)

        return Reader()

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        path = self.options["path"]

        class Writer(DataSourceWriter):
            def write(self, rows) -> WriterCommitMessage:
                import os
                import uuid

                os.makedirs(path, exist_ok=True)
                with open(f"{path}/part-{uuid.uuid4().hex}.nt", "w", encoding="utf-8") as f:
                    f.writelines(r[0] + "\n" for r in rows)
                return WriterCommitMessage()

        return Writer()
