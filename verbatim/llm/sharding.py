"""Sharding by a Feistel permutation of global row numbers.

A balanced-enough Feistel network over the smallest power of two that holds the row count is
a bijection; numbers that fall beyond the count are walked on along their cycle until they
come back. Position p goes to shard p mod k, slot p div k, so counts differ by one at most
and anyone who knows (row count, seed) computes shard and slot of a row number, or with
`unpermute` the row number at a slot, without any data.

Defined results: null texts count no bytes and have the checksum of the empty text; equal
rows are interchangeable; null keys come first; an empty table gives an empty result; other
columns are carried along untouched, but columns of the input that are called shard or slot
are replaced (names that begin with `__index` are the function's own).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

ROUNDS = 6


def _mix(x: np.ndarray, key: int) -> np.ndarray:
    """A 64-bit finaliser of multiply and shift steps."""
    with np.errstate(over="ignore"):
        x = (x + np.uint64(key)) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def _network(x: np.ndarray, n: int, seed: int, back: bool) -> np.ndarray:
    bits = max(2, (n - 1).bit_length())
    low = bits // 2
    mask_low, mask_high = np.uint64((1 << low) - 1), np.uint64((1 << (bits - low)) - 1)
    left, right = x >> np.uint64(low), x & mask_low
    for r in reversed(range(ROUNDS)) if back else range(ROUNDS):
        key = (seed * 1_000_003 + r * 7_919) % (1 << 63)
        if r % 2 == 0:
            left = left ^ (_mix(right, key) & mask_high)
        else:
            right = right ^ (_mix(left, key) & mask_low)
    return (left << np.uint64(low)) | right


def permute(rows, n: int, seed: int, back: bool = False) -> np.ndarray:
    """The place in 0..n-1 of each row number in 0..n-1."""
    out = np.asarray(rows).astype(np.uint64)
    walk = np.ones(len(out), dtype=bool)
    while walk.any():
        out[walk] = _network(out[walk], n, seed, back)
        walk = out >= n
    return out.astype(np.int64)


def unpermute(places, n: int, seed: int) -> np.ndarray:
    return permute(places, n, seed, back=True)


def shard(df: DataFrame, keys: list[Column], shards: int = 16, seed: int = 1) -> DataFrame:
    """`df` with shard int and slot long. `keys` fix the global row numbers; all columns travel."""
    numbered = C.global_index(df, keys, "__index_row")
    n = numbered.select(F.max("__index_row")).first()[0]
    n = 0 if n is None else n + 1

    @F.pandas_udf("long")
    def place(row: pd.Series) -> pd.Series:
        return pd.Series(permute(row.to_numpy(), n, seed))

    placed = numbered.withColumn("__index_at", place("__index_row"))
    return placed.withColumn("shard", (F.col("__index_at") % shards).cast("int")).withColumn("slot", F.floor(F.col("__index_at") / shards).cast("long")).drop("__index_row", "__index_at")


def write_shards(sharded: DataFrame, path: str) -> None:
    """One folder for each shard, rows in slot order within each file."""
    sharded.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Law `rows` over 16 shards; texts are reduced to size and checksum before anything moves."""
    text = C.text_or_empty("text")
    slim = C.table(spark, sf_dir, "documents").select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).cast("long").alias("text_crc32"), F.xxhash64("text").alias("_h"))
    out = shard(slim, [F.col("doc_id"), F.col("text_crc32"), F.col("size"), F.col("_h")])
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
