"""Preference records: default direction, directive variants, mixture with generic pairs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import hash32, tokens

ALLOW, FORBID = "reuse=allowed", "reuse=forbidden"
FIELDS = ["pair_id", "directive", "prompt", "chosen", "rejected", "origin"]


def to_preferences(pairs: DataFrame) -> DataFrame:
    """The rewrite is chosen, the original rejected."""
    return pairs.select("pair_id", F.lit(None).cast("string").alias("directive"), "prompt", F.col("rewrite").alias("chosen"), F.col("original").alias("rejected"), F.lit("rewrite").alias("origin"))


def _swap(pairs: DataFrame, allowed: Column, directive: Column) -> DataFrame:
    return pairs.select(
        "pair_id", directive.alias("directive"), "prompt", F.when(allowed, F.col("original")).otherwise(F.col("rewrite")).alias("chosen"),
        F.when(allowed, F.col("rewrite")).otherwise(F.col("original")).alias("rejected"), F.lit("rewrite").alias("origin"),
    )


def with_directives(pairs: DataFrame, seed: str = "directive", p_allow: float = 0.5) -> DataFrame:
    """A random directive for each pair; where reuse is allowed the roles swap."""
    allowed = hash32(seed, "pair_id") % 1000 < round(1000 * p_allow)
    return _swap(pairs, allowed, F.when(allowed, ALLOW).otherwise(FORBID))


def with_catalog(pairs: DataFrame, catalog: DataFrame, seed: str = "directive") -> DataFrame:
    """Directives from catalog(slot 0..n-1, directive, allow boolean): several wordings a direction."""
    n = catalog.count()
    d = pairs.withColumn("slot", (hash32(seed, "pair_id") % n).cast("int")).join(F.broadcast(catalog), "slot")
    return _swap(d, F.col("allow"), F.col("directive"))


def generic(conversations: DataFrame) -> DataFrame:
    """Generic pairs: a user turn's own answer against the answer that another conversation gave (the next one by hash)."""
    turn = Window.partitionBy("conv_id").orderBy("turn")
    d = conversations.select("conv_id", "turn", "role", tokens("text").alias("tk"))
    d = d.withColumn("_role", F.lead("role").over(turn)).withColumn("_answer", F.lead("tk").over(turn)).where("role = 'user' and _role = 'assistant'")
    # one answer stands for each conversation, so that the ring is a row a conversation
    own = d.groupBy("conv_id").agg(F.min_by("_answer", "turn").alias("_a")).withColumn("_h", hash32("ring", "conv_id"))
    rings = max(1, own.count() // 1000)  # rings of about a thousand conversations: no task sees them all
    ring = Window.partitionBy(F.col("_h") % rings).orderBy("_h", "conv_id")
    own = own.withColumn("_other", F.lead("_a").over(ring)).withColumn("_first", F.first("_a").over(ring)).select("conv_id", F.coalesce("_other", "_first").alias("_other"))
    j = d.join(own, "conv_id").where("_answer <> _other")
    return j.select(F.concat_ws("-", F.lit("g"), "conv_id", "turn").alias("pair_id"), F.lit(None).cast("string").alias("directive"), F.col("tk").alias("prompt"), F.col("_answer").alias("chosen"), F.col("_other").alias("rejected"), F.lit("generic").alias("origin"))


def mix(prefs: DataFrame, extra: DataFrame, share: float = 0.9, seed: str = "mix") -> DataFrame:
    """All of `prefs`, and so many generic pairs that rewrites are `share` of the whole."""
    n = round(prefs.count() * (1 - share) / share) if share > 0 else extra.count()
    some = extra.withColumn("_h", hash32(seed, "pair_id")).orderBy("_h", "pair_id").limit(n).drop("_h")
    return prefs.select(*FIELDS).unionByName(some.select(*FIELDS))
