"""Segments: a prefix that is shown and the reference that follows it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _cut(df: DataFrame, start: Column, n: int, m: int) -> DataFrame:
    return df.select(
        F.concat_ws("-", "doc_id", start.cast("string")).alias("seg_id"), "doc_id", start.cast("int").alias("start"),
        F.slice("tk", start + 1, F.lit(n)).alias("prefix"), F.slice("tk", start + n + 1, F.lit(m)).alias("reference"),
    )


def head_segment(df: DataFrame, n: int = 64, m: int = 32) -> DataFrame:
    """The first n and next m tokens of df(doc_id, tk); shorter documents have no segment."""
    return _cut(df.where(F.size("tk") >= n + m), F.lit(0), n, m)


def stride_segments(df: DataFrame, n: int, m: int, stride: int) -> DataFrame:
    """Every window of n + m tokens that starts at a multiple of `stride`."""
    d = df.where(F.size("tk") >= n + m).withColumn("_at", F.explode(F.sequence(F.lit(0), F.size("tk") - (n + m), F.lit(stride))))
    return _cut(d, F.col("_at"), n, m)
