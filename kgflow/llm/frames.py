"""Columns by position, so that the names of a caller's columns never meet an operator's own."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def place(df: DataFrame, name: str) -> int:
    """Position of a column: the exact name first, else one that differs in case only, as Spark resolves it."""
    if name in df.columns:
        return df.columns.index(name)
    close = [i for i, c in enumerate(df.columns) if c.lower() == name.lower()]
    if not close:
        raise ValueError(f"no column {name} among {df.columns}")
    return close[0]


def by_position(df: DataFrame) -> DataFrame:
    """df with its columns renamed c0, c1, ..."""
    return df.toDF(*(f"c{i}" for i in range(len(df.columns))))


def column(df: DataFrame, name: str) -> Column:
    """The column of by_position(df) that name stands for."""
    return F.col(f"c{place(df, name)}")


def id_and_text(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id long, text string), whatever else df has."""
    return by_position(df).select(column(df, id_col).cast("long").alias("id"), column(df, text_col).cast("string").alias("text"))


def restored(out: DataFrame, names: Sequence[str], added: Sequence[str]) -> DataFrame:
    """The columns c0, c1, ... of out under their names again, then the added ones; a caller's column
    that has the name of an added one, in any case, is replaced by it."""
    taken = {a.lower() for a in added}
    return out.select(*(F.col(f"c{i}").alias(n) for i, n in enumerate(names) if n.lower() not in taken), *added)
