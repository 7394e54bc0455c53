"""Reworded twins of segments.

A `Rewriter` is any function from segments to (seg_id, rewrite). The stand-in keeps two of
three words and replaces the others by another word that the corpus has after the word
before: the wording changes, the flow of the language stays.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import rouge
from ..functions.text import hash32

Rewriter = Callable[[DataFrame], DataFrame]


def successors(counts: DataFrame, most: int = 16) -> DataFrame:
    """(ctx, options): the `most` most frequent words after each word, in that order."""
    at = Window.partitionBy("ctx").orderBy(F.col("cnt").desc(), "tok")
    d = counts.where("ord = 1").withColumn("_r", F.row_number().over(at)).where(F.col("_r") <= most)
    return d.groupBy("ctx").agg(F.sort_array(F.collect_list(F.struct("_r", "tok"))).alias("_o")).select("ctx", F.col("_o.tok").alias("options"))


def asked(segs: DataFrame) -> DataFrame:
    """(ctx): the words whose successors `substitute` looks up, those before positions 1, 4, 7, ..."""
    return segs.select(F.posexplode("reference").alias("pos", "ctx")).where("pos % 3 = 0").select("ctx").distinct()


def substitute(segs: DataFrame, counts: DataFrame, seed: str = "rewrite", most: int = 16) -> DataFrame:
    """(seg_id, rewrite). Positions 1, 4, 7, ... change; each looks only at the original word before it, so all change at once. Of the counts, only the words of `asked` are used."""
    d = segs.select("seg_id", F.posexplode("reference").alias("pos", "tok"), "reference")
    d = d.withColumn("ctx", F.get("reference", F.col("pos") - 1)).drop("reference")
    d = d.join(successors(counts, most), "ctx", "left")
    other = F.filter(F.col("options"), lambda x: x != F.col("tok"))
    pick = F.get(other, (hash32(seed, F.concat_ws(":", "seg_id", F.col("pos").cast("string"))) % F.size(other)).cast("int"))
    new = F.when((F.col("pos") % 3 == 1) & (F.size(other) > 0), pick).otherwise(F.col("tok"))
    return d.withColumn("_n", new).groupBy("seg_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "_n"))), lambda x: x["_n"]).alias("rewrite"))


def rewrite(segs: DataFrame, rewriter: Rewriter) -> DataFrame:
    """Pairs (pair_id, doc_id, prompt, original, rewrite); a segment whose twin is the same is dropped."""
    j = segs.join(rewriter(segs), "seg_id")
    return j.select(F.col("seg_id").alias("pair_id"), "doc_id", F.col("prefix").alias("prompt"), F.col("reference").alias("original"), "rewrite").where("original <> rewrite")


def cosine_bags(a: str, b: str):
    """Cosine of the token counts of two array columns."""
    vocab = F.array_union(a, b)
    count = lambda arr, x: F.size(F.filter(arr, lambda y: y == x)).cast("double")
    dot = F.aggregate(vocab, F.lit(0.0), lambda acc, x: acc + count(F.col(a), x) * count(F.col(b), x))
    norm = lambda arr: F.sqrt(F.aggregate(F.array_distinct(arr), F.lit(0.0), lambda acc, x: acc + count(F.col(arr), x) * count(F.col(arr), x)))
    return dot / (norm(a) * norm(b))


def gate(pairs: DataFrame, most_overlap: float = 0.9, least_cosine: float = 0.3) -> DataFrame:
    """Pairs with overlap, cosine, and ok: reworded enough and still about the same."""
    d = pairs.withColumn("overlap", rouge.lcs_len_arrow("rewrite", "original") / F.size("original")).withColumn("cosine", cosine_bags("original", "rewrite"))
    return d.withColumn("ok", (F.col("overlap") <= most_overlap) & (F.col("cosine") >= least_cosine))
