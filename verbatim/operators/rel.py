"""Relational operators that Spark has no single call for."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.store import fits


def asof(left: DataFrame, right: DataFrame, key: str, at: str, value: str, out: str) -> DataFrame:
    """For each row of left(key, at), the latest `value` of right(key, at) at or before it: a union and one window, no join."""
    l = left.withColumn("_side", F.lit(1)).withColumn("_v", F.lit(None).cast(right.schema[value].dataType))  # noqa: E741
    r = right.select(key, at, F.col(value).alias("_v"), F.lit(0).alias("_side"))
    w = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return l.unionByName(r, allowMissingColumns=True).withColumn(out, F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_side", "_v")


def band_join(left: DataFrame, right: DataFrame, a: str, b: str, width: int) -> DataFrame:
    """Pairs with |a - b| <= width: an equi-join on bins of that width, three for each right row, then the exact test."""
    l = left.withColumn("_bin", F.floor(F.col(a) / width))  # noqa: E741
    r = right.withColumn("_bin", F.explode(F.array(*[F.floor(F.col(b) / width) + k for k in (-1, 0, 1)])))
    return l.join(r, "_bin").where(F.abs(F.col(a) - F.col(b)) <= width).drop("_bin")


def containing(left: DataFrame, right: DataFrame, text: str, part: str) -> DataFrame:
    """Pairs whose `part` stands somewhere in `text`. A right side that fits is broadcast to one pass; a larger one meets the words of the texts by its longest inner word (which white space fences in, so the text has it whole), and only parts without one are broadcast."""
    if fits(right):
        return left.join(F.broadcast(right), F.col(text).contains(F.col(part)))
    words = F.split(F.col(part), "[ \t\n\x0b\f\r]+")
    inner = F.slice(words, F.lit(2), F.greatest(F.size(words) - 2, F.lit(0)))
    longest = F.array_max(F.transform(inner, lambda w: F.struct(F.length(w).alias("n"), w.alias("w"))))["w"]
    keyed = right.withColumn("_w", longest)
    each = left.select("*", F.explode(F.array_distinct(F.split(F.col(text), "[ \t\n\x0b\f\r]+"))).alias("_w"))
    met = each.join(keyed.where("_w is not null"), "_w").where(F.col(text).contains(F.col(part))).drop("_w")
    rest = keyed.where("_w is null").drop("_w")
    if not fits(rest):
        raise ValueError("too many parts of fewer than three words")
    return met.unionByName(left.join(F.broadcast(rest), F.col(text).contains(F.col(part))))


def top_per(df: DataFrame, by: str, k: int, *order: Column) -> DataFrame:
    w = Window.partitionBy(by).orderBy(*order)
    return df.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= k).drop("_r")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda acc, x: acc + x)


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def _matrix(vectors, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """Vectors of length one as rows, and which rows are not such vectors: null, of another length, zero, or with null or non-finite components."""
    m = np.full((len(vectors), dim), np.nan)
    for i, v in enumerate(vectors):
        if v is not None and len(v) == dim:
            m[i] = np.asarray(v, dtype=np.float64)
    norm = np.linalg.norm(m, axis=1)
    bad = ~(np.isfinite(norm) & (norm > 1e-150))
    m[bad] = 0.0
    return m / np.where(bad, 1.0, norm)[:, None], bad


def near_candidates(rows: DataFrame, asked: list, k: int, slack: float = 2e-6, at_once: int = 512) -> DataFrame:
    """(i, b, embedding): for row i of asked [(id, vector), ...], the rows(b, embedding) of another id that may be among its k of highest cosine, rounded to six places.

    A task multiplies matrices and keeps what is no more than `slack` below the k-th best that it has seen; what has no cosine is always kept, for the exact expression to judge.
    """
    dim = next((len(v) for _, v in asked if v is not None), 0)
    ids = np.array([i for i, _ in asked], dtype=np.int64)
    sent = rows.sparkSession.sparkContext.broadcast((ids, *_matrix([v for _, v in asked], dim)))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, q, q_bad = sent.value
        best = np.full((len(ids), k), -np.inf)
        for batch in batches:
            for at in range(0, len(batch), at_once):
                part = batch.iloc[at : at + at_once]
                b, b_bad = _matrix(part["embedding"].tolist(), dim)
                other = ids[:, None] != part["b"].to_numpy()[None, :]
                none = q_bad[:, None] | b_bad[None, :]
                near = np.where(other & ~none, q @ b.T, -np.inf)
                best = -np.partition(-np.concatenate([best, near], axis=1), k - 1, axis=1)[:, :k]
                i, j = np.nonzero(other & (none | (near >= best.min(axis=1)[:, None] - slack)))
                yield pd.DataFrame({"i": i, "b": part["b"].to_numpy()[j], "embedding": part["embedding"].to_numpy()[j]})

    return rows.where("b is not null").mapInPandas(run, f"i long, b long, embedding {rows.schema['embedding'].dataType.simpleString()}")
