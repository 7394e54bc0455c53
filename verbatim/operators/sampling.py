"""Samples and splits that depend on keys alone, so any layout and any retry gives the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import grams, hash32, uniform


def sample_docs(df: DataFrame, k: int, seed: str = "sample", key: str = "doc_id") -> DataFrame:
    """k rows with the smallest hashes: a top-k, merged on the driver; for very large k use `sample_fraction`."""
    return df.withColumn("_h", hash32(seed, key)).orderBy("_h", key).limit(k).drop("_h")


def sample_fraction(df: DataFrame, share: float, seed: str = "sample", key: str = "doc_id") -> DataFrame:
    """About `share` of the rows: a filter, without a sort."""
    return df.where(uniform(seed, key) < share)


def split(df: DataFrame, seed: str = "split", parts: int = 2, key: str = "doc_id") -> DataFrame:
    """`df` with part: `seen` for one of `parts` hash buckets of the key, else `held`."""
    return df.withColumn("part", F.when(hash32(seed, key) % parts == 0, "seen").otherwise("held"))


def seen(df: DataFrame) -> DataFrame:
    return split(df).where("part = 'seen'").drop("part")


def held(df: DataFrame, guard: str = "none", n: int = 11) -> DataFrame:
    """Held-out rows of df(doc_id, text, tk); `text` drops texts that are also seen, `grams` also any that share an n-gram."""
    s = split(df)
    out = s.where("part = 'held'").drop("part")
    if guard in ("text", "grams"):
        out = out.join(s.where("part = 'seen'").select(F.md5("text").alias("_m")).distinct(), F.md5("text") == F.col("_m"), "left_anti")
    if guard == "grams":
        known = s.where("part = 'seen'").select(F.explode(grams("tk", n)).alias("_g")).select(F.xxhash64("_g").alias("_x")).distinct()
        mine = out.select("doc_id", F.explode(grams("tk", n)).alias("_g")).select("doc_id", F.xxhash64("_g").alias("_x"))
        out = out.join(mine.join(known, "_x", "left_semi").select("doc_id").distinct(), "doc_id", "left_anti")
    return out
