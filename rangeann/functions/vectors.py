"""Vector distances and small vector builders as columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _column(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def _sum(c: Column) -> Column:
    return F.aggregate(c, F.lit(0.0), lambda a, x: a + x)


def l2_sq(a: Column | str, b: Column | str) -> Column:
    return _sum(F.zip_with(_column(a), _column(b), lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))))


def l2(a: Column | str, b: Column | str) -> Column:
    return F.sqrt(l2_sq(a, b))


def inner_product(a: Column | str, b: Column | str) -> Column:
    return _sum(F.zip_with(_column(a), _column(b), lambda x, y: x.cast("double") * y.cast("double")))


def cosine(a: Column | str, b: Column | str) -> Column:
    return inner_product(a, b) / F.sqrt(inner_product(a, a) * inner_product(b, b))


def letter_counts(text: Column | str) -> Column:
    """26 counts of lower-case letters."""
    t = _column(text)
    return F.array(*[(F.length(t) - F.length(F.replace(t, F.lit(c), F.lit("")))).cast("float") for c in "abcdefghijklmnopqrstuvwxyz"])
