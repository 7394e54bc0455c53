"""Longest common subsequence and the ROUGE-L family."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


#: Most tokens whose places are bits of one long, with a carry.
BITS = 62


def _lcs_bits(a: str, b: str) -> Column:
    """LCS length where `a` has BITS tokens at most: a bit tells where the table's row does not grow, so each token of b takes a few word operations."""
    one = F.lit(1).cast("long")
    full = F.call_function("shiftleft", one, F.size(a)) - one

    def grow(v: Column, y: Column) -> Column:
        bits = lambda acc, k: acc.bitwiseOR(F.when(F.get(F.col(a), k) == y, F.call_function("shiftleft", one, k)).otherwise(F.lit(0).cast("long")))
        at = F.aggregate(F.sequence(F.lit(0), F.size(a) - 1), F.lit(0).cast("long"), bits)
        # the bits of `a` that match, met once
        step = lambda _, m: (v + v.bitwiseAND(m)).bitwiseOR(v.bitwiseAND(F.bitwise_not(m))).bitwiseAND(full)
        return F.aggregate(F.array(at), v, step)

    return F.aggregate(b, full, grow, lambda v: F.size(a) - F.bit_count(v))


def lcs_len(a: str, b: str) -> Column:
    """LCS length of two array columns, inside Catalyst: by bits of a long, or for longer arrays with one row of the table carried along."""

    def row(prev: Column, x: Column) -> Column:
        step = lambda acc, j: F.concat(acc, F.array(F.when(F.get(F.col(b), j - 1) == x, F.get(prev, j - 1) + 1).otherwise(F.greatest(F.get(prev, j), F.element_at(acc, -1)))))
        return F.aggregate(F.sequence(F.lit(1), F.size(b)), F.array(F.lit(0)), step)

    full = F.aggregate(a, F.array_repeat(F.lit(0), F.size(b) + 1), row, lambda r: F.element_at(r, -1))
    return F.when((F.size(a) < 1) | (F.size(b) < 1), F.lit(0)).when(F.size(a) <= BITS, _lcs_bits(a, b)).otherwise(full)


def lcs_words(a, b) -> int:
    """Bit-parallel LCS: one word operation for each token of b, whatever the length of a."""
    at: dict = {}
    for k, x in enumerate(a):
        at[x] = at.get(x, 0) | (1 << k)
    full = (1 << len(a)) - 1
    v = full
    for y in b:
        u = v & at.get(y, 0)
        v = ((v + u) | (v - u)) & full
    return len(a) - bin(v).count("1")


@F.pandas_udf(T.IntegerType())
def lcs_len_arrow(a: pd.Series, b: pd.Series) -> pd.Series:
    """The same length by Arrow batches; the default for many or long rows."""
    return pd.Series([0 if x is None or y is None else lcs_words(x, y) for x, y in zip(a, b)])


def bag_bound(a: str, b: str) -> Column:
    """Tokens of b that a can match as a multiset: an upper bound of the LCS."""
    count = lambda arr, x: F.size(F.filter(arr, lambda y: y == x))
    return F.aggregate(F.array_distinct(b), F.lit(0), lambda acc, x: acc + F.least(count(F.col(a), x), count(F.col(b), x)))


def recall(lcs: Column, ref: str) -> Column:
    """ROUGE-L as used for copying: LCS over the length of the reference; null without one."""
    return F.when(F.size(ref) > 0, lcs / F.size(ref))


def prf(lcs: Column, gen: str, ref: str) -> tuple[Column, Column, Column]:
    p = F.when(F.size(gen) > 0, lcs / F.size(gen)).otherwise(0.0)
    r = F.when(F.size(ref) > 0, lcs / F.size(ref)).otherwise(0.0)
    return p, r, F.when(p + r > 0, 2 * p * r / (p + r)).otherwise(0.0)
