"""Which segments a model can recite: probing, scoring and selection."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import rouge
from ..functions.text import hash32
from . import decode


def probe(segs: DataFrame, best: DataFrame, steps: int, strategy: str = "auto") -> DataFrame:
    """segs(seg_id, prefix, reference, ...) with generated, lcs, rouge_l."""
    made = decode.greedy(segs.select(F.col("seg_id").alias("id"), F.col("prefix").alias("given")), best, steps, strategy=strategy)
    return score(segs.join(made.withColumnRenamed("id", "seg_id"), "seg_id"))


def score(df: DataFrame, arrow: bool = True) -> DataFrame:
    """df(generated, reference) with lcs and rouge_l (over the reference's length, however short the output)."""
    lcs = rouge.lcs_len_arrow("generated", "reference") if arrow else rouge.lcs_len("generated", "reference")
    return df.withColumn("lcs", lcs).withColumn("rouge_l", F.when(F.size("reference") > 0, F.col("lcs") / F.size("reference")))


def top_segments(probes: DataFrame, k: int, by: str | None = None) -> DataFrame:
    """The k highest scores, the smaller id first on a tie; `by` gives each model its own k."""
    order = [F.col("rouge_l").desc(), F.col("seg_id")]
    if by is None:
        return probes.orderBy(*order).limit(k)
    return probes.withColumn("_r", F.row_number().over(Window.partitionBy(by).orderBy(*order))).where(F.col("_r") <= k).drop("_r")


def above(probes: DataFrame, least: float = 0.9) -> DataFrame:
    return probes.where(F.col("rouge_l") >= least)


def random_segments(segs: DataFrame, k: int, seed: str = "random") -> DataFrame:
    """The ablation: k segments by hash, whatever the model recites."""
    return segs.withColumn("_h", hash32(seed, "seg_id")).orderBy("_h", "seg_id").limit(k).drop("_h")


def extraction_ratio(probes: DataFrame, over: float = 0.5, *by: str) -> DataFrame:
    """n, extraction (percent of items with a score strictly above `over`) and mean_rouge_l."""
    return probes.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(F.when(F.col("rouge_l") > over, 100.0).otherwise(0.0)), 6).alias("extraction"), F.round(F.avg("rouge_l"), 6).alias("mean_rouge_l"))


def extraction_curve(probes: DataFrame, steps: int = 10) -> DataFrame:
    """The ratio at thresholds 0, 1/steps, ..., 1: one pass, each row counted at the thresholds below it."""
    taus = F.transform(F.sequence(F.lit(0), F.lit(steps)), lambda k: k / F.lit(float(steps)))
    d = probes.select("rouge_l", F.explode(taus).alias("tau"))
    return d.groupBy("tau").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(F.when(F.col("rouge_l") > F.col("tau"), 100.0).otherwise(0.0)), 6).alias("extraction"))
