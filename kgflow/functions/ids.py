"""Identifiers: md5 only, so that any engine can check them."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def h32(kind: str, key: Column | str) -> Column:
    """First 32 bits of md5('kind:key') as a bigint; slices and plants by it."""
    key = F.col(key) if isinstance(key, str) else key
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{kind}:"), key.cast("string"))), 1, 8), 16, 10).cast("bigint")


def joined_id(*parts: Column | str) -> Column:
    """md5 of the parts, with the separator doubled inside them and null apart from empty."""
    cols = [F.col(p) if isinstance(p, str) else p for p in parts]
    return F.md5(F.array_join(F.array(*(F.coalesce(F.concat(F.lit("="), F.replace(c.cast("string"), F.lit("|"), F.lit("||"))), F.lit("-")) for c in cols)), "|"))


def edge_id(head="head", relation="relation", tail="tail") -> Column:
    return joined_id(head, relation, tail)


def bucket(key: Column | str, n: int) -> Column:
    key = F.col(key) if isinstance(key, str) else key
    return F.pmod(F.xxhash64(key), F.lit(n)).cast("int")
