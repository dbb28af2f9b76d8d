"""Names, n-grams, vectors and similarities as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def normalised(x: Column | str) -> Column:
    """Lower case, marks to spaces, leading zeros of numbers dropped, one space between tokens."""
    marks = F.regexp_replace(F.lower(_c(x)), r"[^\p{L}\p{N}]+", " ")
    split = F.regexp_replace(marks, r"(?<=\p{L})(?=\p{N})", " ")
    return F.trim(F.regexp_replace(split, r"\b0+(?=[0-9])", ""))


def tokens(x: Column | str) -> Column:
    return F.filter(F.split(normalised(x), " "), lambda t: t != "")


def number_token(x: Column | str) -> Column:
    """The last number in a name, or null."""
    plain = _c(x).rlike(r"^[a-z]+ (0|[1-9][0-9]*)\z")  # in normal form as it is
    return F.when(plain, F.substring_index(_c(x), " ", -1)).otherwise(F.nullif(F.regexp_extract(normalised(x), r"([0-9]+)(?!.*[0-9])", 1), F.lit("")))


def ngrams(x: Column | str, n: int = 3) -> Column:
    padded = F.concat(F.lit("^"), _c(x), F.lit("$"))
    return F.transform(F.sequence(F.lit(1), F.greatest(F.length(padded) - n + 1, F.lit(1))), lambda i: F.substring(padded, i, F.lit(n)))


def bound(value: Column, body) -> Column:
    """body(value) with the value computed once: an expression that is named in a lambda is evaluated at every use of it."""
    return F.get(F.transform(F.array(value), body), 0)


def hashed_ngrams(x: Column | str, dim: int = 64, n: int = 3) -> Column:
    """Unit vector of hashed character n-gram counts, array<double>."""
    at = F.transform(ngrams(x, n), lambda g: F.pmod(F.conv(F.substring(F.md5(g), 1, 6), 16, 10).cast("bigint"), F.lit(dim)).cast("int"))
    counts = lambda places: F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda d: F.size(F.filter(places, lambda p: p == d)).cast("double"))
    return unit(bound(at, counts))


def dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(_c(a), _c(b), lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column | str) -> Column:
    return F.sqrt(dot(a, a))


def unit(a: Column | str) -> Column:
    over = lambda v: bound(norm(v), lambda size: F.transform(v, lambda x: F.when(size > 0, x.cast("double") / size).otherwise(0.0)))
    return bound(_c(a), over)


def cosine(a: Column | str, b: Column | str) -> Column:
    return F.try_divide(dot(a, b), norm(a) * norm(b))


def jaccard(a: Column | str, b: Column | str) -> Column:
    return F.try_divide(F.size(F.array_intersect(_c(a), _c(b))).cast("double"), F.size(F.array_union(_c(a), _c(b))).cast("double"))


def harmonic(p: Column | str, r: Column | str) -> Column:
    return F.try_divide(2 * _c(p) * _c(r), _c(p) + _c(r))


def jaro_winkler_prefix(a: Column | str, b: Column | str, most: int = 4) -> Column:
    """Length of the common prefix, up to most: the boost term of prefix-weighted similarities."""
    a, b = _c(a), _c(b)
    return F.size(F.filter(F.sequence(F.lit(1), F.lit(most)), lambda n: (F.length(a) >= n) & (F.length(b) >= n) & (F.substring(a, F.lit(1), n) == F.substring(b, F.lit(1), n))))
