"""String similarities in [0, 1], as column expressions, and their mean."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

NATIVE_CHARS = 62
"""Longest second string whose common subsequence fits the bits of a long."""


def _longest(a: Column, b: Column) -> Column:
    return F.greatest(F.length(a), F.length(b))


def lev_sim(a: Column, b: Column) -> Column:
    """1 - distance / longer length; two empty strings are equal."""
    n = _longest(a, b)
    return F.when(n == 0, 1.0).otherwise(1 - F.levenshtein(a, b) / n)


def _units(x: Column, unit: str, q: int) -> Column:
    if unit == "char":
        return F.array_distinct(F.split(x, ""))
    if unit == "token":
        return F.array_distinct(F.filter(F.split(x, " "), lambda w: w != ""))
    n = F.length(x) - (q - 1)
    return F.when(n < 1, F.array_distinct(F.array(x))).otherwise(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.substring(x, i, F.lit(q)))))


def jaccard_sim(a: Column, b: Column, unit: str = "char", q: int = 2) -> Column:
    """Shared over all of the two sets of characters, q-grams or tokens; two empty strings are equal."""
    x, y = _units(a, unit, q), _units(b, unit, q)
    n = F.size(F.array_union(x, y))
    out = F.when(n == 0, 1.0).otherwise(F.size(F.array_intersect(x, y)) / n)
    return F.when((a == "") & (b == ""), 1.0).when((a == "") | (b == ""), 0.0).otherwise(out)


def lcs_length(a: Column, b: Column) -> Column:
    """Length of the longest common subsequence; ``b`` of at most NATIVE_CHARS characters.

    A bit for each character of ``b`` marks where the best length grows; a
    character of ``a`` updates all of them by one addition.
    """
    one, zero = F.lit(1).cast("long"), F.lit(0).cast("long")
    chars = F.split(b, "")

    def mask(c: Column) -> Column:
        hits = F.transform(chars, lambda x, i: F.when(x == c, F.call_function("shiftleft", one, i)).otherwise(zero))
        return F.aggregate(hits, zero, lambda s, x: s.bitwiseOR(x))

    def grow(row: Column, c: Column) -> Column:
        x = row.bitwiseOR(mask(c))
        return x.bitwiseAND(F.bitwise_not(x - F.shiftleft(row, 1).bitwiseOR(one)))

    full = F.call_function("shiftleft", one, F.length(b)) - 1
    return F.when((a == "") | (b == ""), 0).otherwise(F.bit_count(F.aggregate(F.split(a, ""), zero, grow).bitwiseAND(full)))


def _lcs_python(a: str, b: str) -> int:
    at: dict[str, int] = {}
    for k, c in enumerate(b):
        at[c] = at.get(c, 0) | 1 << k
    row = 0
    for c in a:
        x = row | at.get(c, 0)
        row = x & ~(x - (row << 1 | 1))
    return (row & ((1 << len(b)) - 1)).bit_count()


def lcs_length_arrow(a: Column, b: Column) -> Column:
    """As lcs_length, for strings of any length, by Arrow batches."""

    @F.pandas_udf("int")
    def run(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([None if p is None or q is None else _lcs_python(p, q) for p, q in zip(x, y, strict=True)], dtype="Int32")

    return run(a, b)


def lcs_sim(a: Column, b: Column, norm: str = "max", long: bool = False) -> Column:
    """Common subsequence over the longer length (norm max), the shorter (min), or twice over both (sum)."""
    n = lcs_length_arrow(a, b) if long else lcs_length(a, b)
    whole = {"max": _longest(a, b), "min": F.least(F.length(a), F.length(b)), "sum": (F.length(a) + F.length(b)) / 2}[norm]
    return F.when((a == "") & (b == ""), 1.0).when((a == "") | (b == ""), 0.0).otherwise(n / whole)


def matchability(lev: Column, jac: Column, lcs: Column, weights: tuple[float, float, float] = (1, 1, 1)) -> Column:
    """Weighted mean of the three, rounded so that ties are ties."""
    p, q, r = weights
    return F.round((lev * p + jac * q + lcs * r) / (p + q + r), 12)


def upper_bound(la: Column, lb: Column, jac: Column) -> Column:
    """No pair of such lengths and Jaccard similarity scores more: edits and subsequences are bounded by the lengths."""
    by_length = F.least(la, lb) / F.greatest(la, lb)
    return F.round((by_length * 2 + jac) / 3, 12)
