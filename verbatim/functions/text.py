"""Token, n-gram and hash expressions; plain Columns, so Catalyst sees through them."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def tokens(text: str | Column, kind: str = "ws") -> Column:
    """array<string>: `ws` = lower case, split on white space; `word` also drops punctuation; `char` = characters."""
    low = F.lower(F.col(text) if isinstance(text, str) else text)
    if kind == "char":
        return F.filter(F.split(low, ""), lambda x: x != "")
    if kind == "word":
        low = F.regexp_replace(low, r"[^\p{L}\p{N}\s]+", "")
    return F.filter(F.split(low, r"\s+"), lambda x: x != "")


def first_tokens(text: str | Column, n: int) -> Column:
    """The first tokens (`ws`) of a text, n at least where it has as many; what follows is not split."""
    low = F.lower(F.col(text) if isinstance(text, str) else text)
    # of n + 2 pieces the first may be empty and the last is the rest
    return F.filter(F.slice(F.split(low, r"\s+", n + 2), 1, n + 1), lambda x: x != "")


def hash32(seed: str, key: str | Column) -> Column:
    """A 32-bit number from seed and key, the same in every engine that has md5."""
    key = F.col(key) if isinstance(key, str) else key
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), key.cast("string"))), 1, 8), 16, 10).cast("long")


def uniform(seed: str, key: str | Column) -> Column:
    return hash32(seed, key) / float(1 << 32)


def grams(toks: str, n: int) -> Column:
    """array<string> of the n-grams of an array column, tokens joined by one space."""
    size = F.size(toks)
    at = F.when(size >= n, F.sequence(F.lit(1), size - n + 1)).otherwise(F.array().cast("array<int>"))
    return F.transform(at, lambda k: F.array_join(F.slice(toks, k, F.lit(n)), " "))
