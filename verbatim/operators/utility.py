"""What a model still can do: choice, numbers, short answers, constraints, comparisons; and likelihood shifts."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from ..functions.text import hash32
from ..plans.store import numbered, tiles
from . import lm


def cloze(items: DataFrame, tail: int = 4, options: int = 4) -> DataFrame:
    """(item_id, opt, stem, option, gold) from items(item_id, tk): the own tail, and those of the next items by hash.

    Items stand in rings of about a thousand; the tails of the next ones are leads, and past
    the end of a ring its first ones follow.
    """
    d = items.where(F.size("tk") > 2 * tail).select("item_id", F.slice("tk", F.lit(1), F.size("tk") - tail).alias("stem"), F.slice("tk", F.size("tk") - tail + 1, F.lit(tail)).alias("end"), hash32("cloze", "item_id").alias("_h"))
    rings = max(1, d.count() // 1000)
    ring = Window.partitionBy(F.col("_h") % rings).orderBy("_h", "item_id")
    whole = ring.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    d = d.withColumn("_k", F.row_number().over(ring)).withColumn("_n", F.count(F.lit(1)).over(whole))
    heads = F.array(*[F.nth_value("end", k).over(whole) for k in range(1, options)])
    ends = F.array(*[F.lead("end", k).over(ring) if k else F.col("end") for k in range(options)])
    d = d.withColumn("_ends", ends).withColumn("_heads", heads)
    d = d.withColumn("opt", F.explode(F.sequence(F.lit(0), F.least(F.lit(options), F.col("_n").cast("int")) - 1)))
    wrapped = (F.col("_k") - 1 + F.col("opt") - F.col("_n")).cast("int")
    option = F.when(wrapped < 0, F.get("_ends", F.col("opt"))).otherwise(F.get("_heads", wrapped))
    return d.select("item_id", "opt", "stem", option.alias("option"), (F.col("opt") == 0).alias("gold"))


def _likeliest(told: DataFrame, *by: str) -> DataFrame:
    """told(by..., item_id, opt, nll) -> (by..., item_id, picked, correct): the option with the lowest NLL, the smaller number on a tie."""
    best = told.groupBy(*by, "item_id").agg(F.min(F.struct("nll", "opt")).alias("_b"))
    return best.select(*by, "item_id", F.col("_b.opt").alias("picked"), (F.col("_b.opt") == 0).alias("correct"))


def choice_accuracy(options: DataFrame, counts: DataFrame) -> DataFrame:
    """(item_id, picked, correct) by the interpolated model, each option scored after its stem."""
    d = options.withColumn("_id", F.concat_ws(":", "item_id", "opt"))
    nll = lm.sequence_nll(d, counts, "_id", "stem", "option").select("_id", F.round("nll", 9).alias("nll"))
    return _likeliest(d.join(nll, "_id"))


def choice_by_scores(scores: DataFrame, *by: str) -> DataFrame:
    """The same from scores(by..., seq_id = item:opt, logp) of policies."""
    parts = F.split("seq_id", ":")
    return _likeliest(scores.select(*by, parts[0].cast("long").alias("item_id"), parts[1].cast("int").alias("opt"), F.round(-F.col("logp"), 9).alias("nll")), *by)


def last_number(text: str | Column) -> Column:
    """The last number of a text, exact."""
    return F.try_element_at(F.regexp_extract_all(F.regexp_replace(text, ",", ""), F.lit(r"-?[0-9]+(?:\.[0-9]+)?"), F.lit(0)), F.lit(-1)).try_cast("decimal(18,2)")


def normal(text: str | Column) -> Column:
    return F.trim(F.regexp_replace(F.regexp_replace(F.lower(text), r"[^a-z0-9 ]", " "), " +", " "))


def constraints(outputs: DataFrame, least: int = 50, forbidden: str = "!", end: str | None = ".", kinds: int = 2, keyword: str | None = None) -> DataFrame:
    """(output_id, passed array<boolean>, ok) of outputs(output_id, text, tk): at least `least` words; no `forbidden`; the text ends with `end`; no more than `kinds` times as many words as different words; one of the words in the column `keyword` is used."""
    n = F.size("tk")
    checks = [n >= least, ~F.col("text").contains(forbidden)]
    checks += [] if end is None else [F.trim("text").endswith(end)]
    checks += [F.size(F.array_distinct("tk")) * kinds >= n]
    checks += [] if keyword is None else [F.arrays_overlap("tk", keyword)]
    return outputs.select("output_id", F.array(*checks).alias("passed")).withColumn("ok", F.forall("passed", lambda x: x))


def closeness(tk: str, answer: str) -> Column:
    """The judge's measure of an output: the share of its different words that the recorded answer has."""
    words = F.array_distinct(tk)
    return F.when(F.size(words) > 0, F.size(F.array_intersect(words, answer)) / F.size(words)).otherwise(0.0)


def _fit_gap(x: np.ndarray, w: np.ndarray, n: np.ndarray) -> float:
    """The win rate at gap 0 by a logistic fit on counts of gaps: Newton steps with a small ridge."""
    a, b = 0.0, 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-(a + b * x)))
        v = n * p * (1 - p) + 1e-9
        h = np.array([[v.sum(), (v * x).sum()], [(v * x).sum(), (v * x * x).sum()]]) + 1e-6 * np.eye(2)
        da, db = np.linalg.solve(h, [(w - n * p).sum(), ((w - n * p) * x).sum()])
        a, b = a + da, b + db
        if abs(da) + abs(db) < 1e-10:
            break
    return float(1 / (1 + np.exp(-a)))


@F.pandas_udf(DoubleType())
def rate_at_no_gap(g: pd.Series, w: pd.Series, n: pd.Series) -> float:
    """Grouped aggregate over bins (gap, wins, count): the length-controlled win rate of each group."""
    return _fit_gap(g.to_numpy(float), w.to_numpy(float), n.to_numpy(float)) if len(g) else float("nan")


def controlled_win_rate(duels: DataFrame, *by: str, bins: int = 41) -> DataFrame:
    """(by..., n, win_rate) of duels(win 0..1, gap): the win rate at no length gap. Gaps are counted in at most `bins` bins first, so a group is never more than those."""
    g = F.round(F.greatest(F.lit(-4.0), F.least(F.lit(4.0), F.col("gap"))) * (bins // 8)) / (bins // 8)
    d = duels.groupBy(*by, g.alias("g")).agg(F.sum("win").alias("w"), F.count(F.lit(1)).alias("n"))
    return d.groupBy(*by).agg(rate_at_no_gap("g", "w", F.col("n").cast("double")).alias("win_rate"))


def nll_shift(before: DataFrame, after: DataFrame) -> DataFrame:
    """(id, n_tokens, before, after, shift): NLL a token under two models."""
    b = before.select("id", "n_tokens", (F.col("nll") / F.col("n_tokens")).alias("before"))
    a = after.select("id", (F.col("nll") / F.col("n_tokens")).alias("after"))
    return b.join(a, "id").withColumn("shift", F.col("after") - F.col("before"))


def shift_by_band(shifts: DataFrame, bands: int = 10) -> DataFrame:
    """(band, n, before, shift): mean shift by tenths of the NLL before, numbered over range partitions."""
    d = numbered(shifts.select("id", F.round("before", 9).alias("before"), "shift"), [F.col("before"), F.col("id")], "_i")
    d = d.withColumn("band", tiles(F.col("_i"), d.count(), bands))
    return d.groupBy("band").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("before"), 6).alias("before"), F.round(F.avg("shift"), 6).alias("shift"))
