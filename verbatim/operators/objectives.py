"""Losses over sequence log-probabilities: what they are worth, and their slope for each sequence.

Every gradient is a sum of coefficient * gradient of ln p(sequence), so an objective only says
which coefficient each sequence has, given the log-probabilities under policy and reference.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BETA = 0.1


def softplus(x: Column) -> Column:
    return F.log1p(F.exp(-F.abs(x))) + F.greatest(x, F.lit(0.0))


def preference_loss(scores: DataFrame, beta: float = BETA) -> DataFrame:
    """scores(pair_id, side chosen/rejected, logp, logp_ref) -> pair_id, margin, loss, reward_chosen, reward_rejected."""
    ratio = F.col("logp") - F.col("logp_ref")
    d = scores.groupBy("pair_id").agg(F.max(F.when(F.col("side") == "chosen", ratio)).alias("_c"), F.max(F.when(F.col("side") == "rejected", ratio)).alias("_r"))
    d = d.withColumn("margin", beta * (F.col("_c") - F.col("_r")))
    return d.select("pair_id", "margin", softplus(-F.col("margin")).alias("loss"), (beta * F.col("_c")).alias("reward_chosen"), (beta * F.col("_r")).alias("reward_rejected"))


def diagnostics(losses: DataFrame) -> DataFrame:
    """n, mean loss, mean margin, and the share of pairs with a positive margin."""
    return losses.agg(F.count(F.lit(1)).alias("n"), F.avg("loss").alias("loss"), F.avg("margin").alias("margin"), F.avg(F.when(F.col("margin") > 0, 1.0).otherwise(0.0)).alias("accuracy"))


def _softplus(x):
    return np.logaddexp(0.0, x)


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -60, 60)))


@dataclass(frozen=True)
class Preference:
    """-ln sigma(beta * difference of the log-ratios of chosen and rejected)."""

    beta: float = BETA
    roles = ("chosen", "rejected")

    def terms(self, d: dict) -> tuple[float, dict]:
        m = self.beta * ((d["chosen"][0] - d["chosen"][1]) - (d["rejected"][0] - d["rejected"][1]))
        c = self.beta * float(_sigmoid(-m))
        return float(_softplus(-m)), {"chosen": -c, "rejected": c}


@dataclass(frozen=True)
class GradientAscent:
    """Lower the likelihood of `forget`; `retain` pulls back with weight lam. Unbounded, so steps are clipped."""

    lam: float = 1.0
    roles = ("forget", "retain")

    def terms(self, d: dict) -> tuple[float, dict]:
        loss, c = 0.0, {}
        if "forget" in d:
            loss, c["forget"] = loss + d["forget"][0], 1.0
        if "retain" in d:
            loss, c["retain"] = loss - self.lam * d["retain"][0], -self.lam
        return loss, c


@dataclass(frozen=True)
class NegativePreference:
    """(2 / beta) * softplus(beta * log-ratio) on `forget`: bounded below; `retain` as above."""

    beta: float = BETA
    lam: float = 1.0
    roles = ("forget", "retain")

    def terms(self, d: dict) -> tuple[float, dict]:
        loss, c = 0.0, {}
        if "forget" in d:
            x = self.beta * (d["forget"][0] - d["forget"][1])
            loss, c["forget"] = loss + 2 / self.beta * float(_softplus(x)), 2 * float(_sigmoid(x))
        if "retain" in d:
            loss, c["retain"] = loss - self.lam * d["retain"][0], -self.lam
        return loss, c


@dataclass(frozen=True)
class NextToken:
    """Negative log-likelihood of `text`: continued training on rewrites, or supervised tuning."""

    roles = ("text",)

    def terms(self, d: dict) -> tuple[float, dict]:
        return -d["text"][0], {"text": -1.0}
