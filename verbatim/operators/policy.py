"""A log-linear policy on top of the n-gram model, and everything it is tuned on.

ln p(w | h) = ln p_ref(w | h) + sum of theta over the features of (h, w) - ln Z(h), over a
candidate set: the successors of the context at any order, frequent words, and the target.
Contexts come from the given text, never from theta, so candidates, their reference
log-probabilities and features are laid out once, a row a sequence, and each tuning step is
one pass over those rows.

A directive adds features to those of the plain context: what was tuned without one holds
under each directive too, and a directive's own weights say how it differs.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import hash32
from . import lm
from .lm import FLOOR, MIX, positions

#: Frequent words that are candidates; hash buckets of the lexical features.
FREQUENT, BUCKETS = 30, 32
DIRECTIVES = ("", "reuse=allowed", "reuse=forbidden")
#: Shared features of a candidate: its highest order (0-3), and whether that context has one successor.
SHARED = 5


def n_features(lexical: bool) -> int:
    return SHARED * len(DIRECTIVES) + (BUCKETS * BUCKETS if lexical else 0)


def frequent(counts: DataFrame) -> DataFrame:
    """(tok, p): the most frequent words and their weighted share, a top-k of order 0."""
    zero = lm.model(counts).where("ord = 0").orderBy(F.col("cnt").desc(), "tok").limit(FREQUENT)
    return zero.select("tok", (F.lit(MIX[0]) * F.col("cnt") / F.col("total")).alias("p"))


def candidates(df: DataFrame, counts: DataFrame, ident: str, given: str, text: str) -> DataFrame:
    """(ident, pos, cand, hi, single, logp_ref, target, prev): rows of the candidate set of each position. Order 0 is met by token alone."""
    p = positions(df, ident, given, text)
    c = lm.model(counts)
    weight = F.element_at(F.array(*[F.lit(w) for w in MIX]), F.col("ord") + 1)
    told = p.where("ord > 0").select(ident, "pos", "ord", "ctx").join(c.where("ord > 0").withColumnRenamed("tok", "cand"), ["ord", "ctx"])
    told = told.select(ident, "pos", "cand", "ord", F.col("n_next").alias("_next"), (weight * F.col("cnt") / F.col("total")).alias("_p"))
    zero = c.where("ord = 0").select(F.col("tok").alias("cand"), (F.lit(MIX[0]) * F.col("cnt") / F.col("total")).alias("_p0"))
    places = p.where("ord = 0").select(ident, "pos", F.col("tok").alias("target"))
    often = frequent(counts).agg(F.sort_array(F.collect_list("tok")).alias("_often"))
    extra = places.crossJoin(F.broadcast(often)).select(ident, "pos", F.explode(F.array_union("_often", F.array("target"))).alias("cand"))
    none = extra.select(ident, "pos", "cand", F.lit(0).alias("ord"), F.lit(0).cast("long").alias("_next"), F.lit(0.0).alias("_p"))
    every = told.unionByName(none).groupBy(ident, "pos", "cand").agg(F.sum("_p").alias("_p"), F.max("ord").alias("hi"), F.max(F.struct("ord", "_next")).alias("_h"))
    every = every.join(zero, "cand", "left").join(places, [ident, "pos"])
    prev = p.where("ord = 1").select(ident, "pos", F.col("ctx").alias("prev"))
    every = every.join(prev, [ident, "pos"], "left")
    mass = F.greatest(F.col("_p") + F.coalesce("_p0", F.lit(0.0)), F.lit(FLOOR))
    return every.select(ident, "pos", "cand", "hi", ((F.col("_h._next") == 1) & (F.col("hi") > 0)).alias("single"), F.log(mass).alias("logp_ref"), (F.col("cand") == F.col("target")).alias("target"), F.coalesce("prev", F.lit("")).alias("prev"))


def design(seqs: DataFrame, counts: DataFrame, lexical: bool = False) -> DataFrame:
    """seqs(seq_id, directive, given, text) -> (seq_id, positions array<struct<logp, feats, target>>), a row a sequence.

    feats are feature numbers: shared ones, again crossed with a directive, then lexical buckets.
    Candidates of a position other than its target that have equal features are one entry with
    the log of their whole mass: the normaliser and the gradient are those of all of them.
    """
    c = candidates(seqs.select("seq_id", "given", "text"), counts, "seq_id", "given", "text")
    where = seqs.select("seq_id", F.coalesce("directive", F.lit("")).alias("directive"))
    c = c.join(where, "seq_id")
    base = F.element_at(F.create_map(*[x for k, d in enumerate(DIRECTIVES) for x in (F.lit(d), F.lit(k * SHARED))]), F.col("directive"))
    none = F.array().cast("array<int>")
    plain = F.when(F.col("single"), F.array(F.col("hi"), F.lit(SHARED - 1))).otherwise(F.array("hi"))
    feats = [plain, F.when(base > 0, F.transform(plain, lambda f: f + base)).otherwise(none)]
    if lexical:
        cell = hash32("ctx", "prev") % BUCKETS * BUCKETS + hash32("tok", "cand") % BUCKETS
        feats.append(F.array((F.lit(SHARED * len(DIRECTIVES)) + cell).cast("int")))
    c = c.withColumn("feats", F.concat(*feats))
    c = c.groupBy("seq_id", "pos", "feats", "target").agg(F.min("cand").alias("cand"), F.log(F.sum(F.exp("logp_ref"))).alias("logp_ref"))
    per = c.groupBy("seq_id", "pos").agg(F.sort_array(F.collect_list(F.struct("cand", "logp_ref", "feats", "target"))).alias("_c"))
    per = per.select("seq_id", F.struct("pos", F.col("_c.logp_ref").alias("logp"), F.col("_c.feats").alias("feats"), (F.array_position("_c.target", True) - 1).cast("int").alias("target")).alias("_p"))
    return per.groupBy("seq_id").agg(F.sort_array(F.collect_list("_p")).alias("positions"))


@dataclass
class Policy:
    """Weights of a tuned model and the settings that made it."""

    theta: np.ndarray
    lexical: bool = False
    settings: dict = field(default_factory=dict)

    def save(self, spark: SparkSession, path: str) -> None:
        rows = [(int(k), float(v)) for k, v in enumerate(self.theta)]
        df = spark.createDataFrame(rows, "feature int, w double").withColumn("settings", F.lit(json.dumps(self.settings | {"lexical": self.lexical})))
        df.coalesce(1).write.mode("overwrite").parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Policy:
        rows = spark.read.parquet(path).orderBy("feature").collect()
        settings = json.loads(rows[0]["settings"])
        return cls(np.array([r["w"] for r in rows]), settings.pop("lexical"), settings)


def identity(lexical: bool = False) -> Policy:
    """The untuned model."""
    return Policy(np.zeros(n_features(lexical)), lexical)


def widened(start: Policy, lexical: bool) -> Policy:
    """`start` with room for lexical weights."""
    missing = n_features(lexical) - len(start.theta)
    return start if missing <= 0 else Policy(np.r_[start.theta, np.zeros(missing)], lexical, start.settings)


def prompt_only(segs: DataFrame, directive: str) -> DataFrame:
    """The untuned model with a directive put before the prefix."""
    return segs.withColumn("prefix", F.concat(F.array(F.lit(directive)), "prefix"))
