"""Functions that SQL users get beside the built-in ones: a scalar UDF, a UDTF, an aggregate of vectors, samples."""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kgflow.functions.ids import h32


@F.pandas_udf(T.StringType())
def folded(text: pd.Series) -> pd.Series:
    """Lower case without accents; null stays null. Unicode decomposition has no built-in function."""
    plain = lambda t: "".join(c for c in unicodedata.normalize("NFD", t.lower()) if unicodedata.category(c) != "Mn")
    return text.map(lambda t: None if t is None else plain(t))


@F.udtf(returnType=T.StructType([T.StructField("no", T.IntegerType()), T.StructField("statement", T.StringType())]))
class ExtractStatements:
    """The non-blank lines of a text, numbered from 0 as they stand; a null text has none."""

    def eval(self, text: str) -> Iterator[tuple[int, str]]:
        for i, line in enumerate((text or "").split("\n")):
            if line.strip():
                yield i, line


def register(spark: SparkSession) -> None:
    """folded(), extract_statements() and cosine() for spark.sql()."""
    spark.udf.register("folded", folded)
    spark.udtf.register("extract_statements", ExtractStatements)
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE
      RETURN try_divide(aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x), sqrt(aggregate(a, 0D, (s, x) -> s + x * x)) * sqrt(aggregate(b, 0D, (s, x) -> s + x * x)))""")


def centroid(df: DataFrame, by: list[str], vec: str, digits: int = 6) -> DataFrame:
    """Mean vector per group, by averages of places: partial sums on the map side, whatever the size of a group."""
    places = df.select(*by, F.posexplode(vec).alias("_at", "_x")).groupBy(*by, "_at").agg(F.avg(F.col("_x").cast("double")).alias("_m"))
    rows = F.array_sort(F.collect_list(F.struct("_at", F.round("_m", digits).alias("_m"))))
    return places.groupBy(*by).agg(F.transform(rows, lambda x: x["_m"]).alias("centroid"))


def sample(df: DataFrame, kind: str, key: str, one_in: int) -> DataFrame:
    """About one row in so many, by md5 of the key: the same rows in every engine and run."""
    return df.where(h32(kind, key) % one_in == 0)


def spot_check(df: DataFrame, strata: list[str], kind: str, key: str, each: int) -> DataFrame:
    """So many rows of each stratum, the least by md5 of the key; a group limit before the exchange."""
    from kgflow.operators.joins import topk

    return topk(df.withColumn("_h", h32(kind, key)), strata, [F.col("_h"), F.col(key)], each).drop("_h")


def nested_loop(small: DataFrame, other: DataFrame, condition: Column, most: int = 100_000) -> DataFrame:
    """Join under any condition. The first side is broadcast, and is counted before: more rows than so many are refused."""
    n = small.limit(most + 1).count()
    if n > most:
        raise ValueError(f"over {most} rows on the side that every row would be compared with")
    return other.join(F.broadcast(small), condition)
