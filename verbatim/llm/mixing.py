"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

Each document draws an exponential key, -ln(u) / quality weight, with u from an md5 of its
id, so reruns agree. A source's word target is met by whole epochs first; what is left is
met by the documents with the smallest keys, prefix-summed in key order.

No task sorts a whole source: keys fall into monotone bins, bin sums locate the bin in which
the budget ends, bins before it are taken whole, and only that one bin is sorted.

Defined results: null text has size 0, null source is a source of its own (last), an empty
source or table takes nothing, rows that share an id are told apart by a text hash, equal
rows are interchangeable.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common as C

#: Weights of the sources in code point order, repeating; share of all words; most epochs.
WEIGHTS, SHARE, MOST = (5, 2, 1), 1.5, 2
BINS = 1024


def uniform(key: Column, seed: int) -> Column:
    """In (0, 1), from 52 bits of an md5 of seed and key."""
    bits = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(key.cast("string"), F.lit("")))), 1, 13), 16, 10).cast("double")
    return (bits + 0.5) / float(1 << 52)


def targets(sizes: DataFrame) -> DataFrame:
    """(source, source_size) -> with rank, weight and target; one row a source.

    Sharing out by weight, capping at MOST times the size and sharing the excess again ends at
    a water level: sources in order of cap / weight are capped while their cap is below the
    level that the others would have.
    """
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in WEIGHTS]), (F.col("_r") % len(WEIGHTS) + 1).cast("int"))
    t = C.global_index(sizes, [F.col("source").cast("binary").asc_nulls_last()], "_r")
    t = t.withColumn("_w", weight).withColumn("_cap", F.lit(float(MOST)) * F.col("source_size"))
    t = C.global_index(t, [F.col("_cap") / F.col("_w"), F.col("_r")], "_i", {"_before": F.col("_cap"), "_light": F.col("_w")})
    every = t.agg(F.sum("source_size").alias("n"), F.sum("_w").alias("w")).first()
    total, heavy = float(every["n"] or 0), float(every["w"] or 0.0)
    t = t.withColumn("_level", (F.lit(SHARE * total) - F.col("_before")) / (F.lit(heavy) - F.col("_light")))
    over = t.where(F.col("_level") * F.col("_w") <= F.col("_cap"))
    level = over.agg(F.min(F.struct(F.col("_cap") / F.col("_w"), F.col("_r"), F.col("_level")))["_level"].alias("l")).first()["l"]
    filled = F.col("_cap") if level is None else F.lit(level) * F.col("_w")
    return t.select("source", "source_size", F.round(F.least(F.col("_cap"), filled), 6).alias("target"))


def n_words(text: Column) -> Column:
    """Words of a text, each replaced by one letter and counted so: no array of words is made."""
    blank = " \t\n\x0b\x0c\r"
    return F.length(F.regexp_replace(F.btrim(text, F.lit(blank)), r"[^\x20\x09-\x0D]+[\x20\x09-\x0D]*", "x")).cast("long")


def keyed(docs: DataFrame, quality: DataFrame | None, seed: int) -> DataFrame:
    """`docs` with _h (text hash), _size, _k (exponential key) and _b (the key's bin).

    quality: (doc_id, weight double > 0), one row an id; documents without one weigh 1.
    """
    d = docs.withColumn("_h", F.xxhash64("text")).withColumn("_size", n_words(C.text_or_empty("text")))
    if quality is not None:
        d = d.join(C.maybe_broadcast(quality.select(F.col("doc_id").alias("_qid"), F.col("weight").alias("_q"))), F.col("doc_id") == F.col("_qid"), "left").drop("_qid")
    else:
        d = d.withColumn("_q", F.lit(1.0))
    d = d.withColumn("_k", -F.log(uniform(F.col("doc_id"), seed)) / F.coalesce("_q", F.lit(1.0))).drop("_q")
    return d.withColumn("_b", F.least(F.floor((1 - F.exp(-F.col("_k"))) * BINS), F.lit(BINS - 1)).cast("int"))


def plan(rows: DataFrame) -> DataFrame:
    """From keyed rows, for each source (_src): source_size, target, _e (epochs) and what the fraction takes: bins before _eb, and in it keys up to _last."""
    d = C.cut(rows.select("source", "_size", "_k", "_b", "doc_id", "_h"))
    bins = C.cut(d.groupBy("source", "_b").agg(F.sum("_size").alias("_n")))
    t = targets(bins.groupBy("source").agg(F.sum("_n").alias("source_size")))
    whole = F.when(F.col("source_size") > 0, F.least(F.floor(F.col("target") / F.col("source_size")), F.lit(MOST))).otherwise(0)
    t = t.withColumn("_e", whole.cast("long")).withColumn("_left", F.col("target") - F.col("_e") * F.col("source_size")).withColumnRenamed("source", "_src")
    at = Window.partitionBy("source").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    at_bin = bins.withColumn("_pre", F.coalesce(F.sum("_n").over(at), F.lit(0)))
    edge = at_bin.join(t, F.col("source").eqNullSafe(F.col("_src"))).where(f"_pre <= _left and _e < {MOST}").groupBy("source").agg(F.max(F.struct("_b", "_pre")).alias("_x"))
    edge = edge.select(F.col("source").alias("_es"), F.col("_x._b").alias("_eb"), F.col("_x._pre").alias("_ep"))
    t = C.cut(t.join(edge, F.col("_src").eqNullSafe(F.col("_es")), "left").drop("_es"))
    order = Window.partitionBy("source").orderBy("_k", "doc_id", "_h").rowsBetween(Window.unboundedPreceding, -1)
    inside = d.join(C.maybe_broadcast(t.select("_src", "_eb", "_ep", "_left")), F.col("source").eqNullSafe(F.col("_src")) & (F.col("_b") == F.col("_eb")))
    inside = inside.withColumn("_at", F.col("_ep") + F.coalesce(F.sum("_size").over(order), F.lit(0))).where(F.col("_at") + F.col("_size") / 2 <= F.col("_left"))
    last = inside.groupBy(F.col("source").alias("_ls")).agg(F.max(F.struct("_k", "doc_id", "_h")).alias("_last"))
    return C.cut(t.join(last, F.col("_src").eqNullSafe(F.col("_ls")), "left").select("_src", "source_size", "target", "_e", "_eb", "_last"))


@C.carrying("doc_id", "text", "source")
def mix(docs: DataFrame, quality: DataFrame | None = None, seed: int = 17, with_text: bool = True) -> DataFrame:
    """`docs` with _size, source_size, target and _copies (long): how often the mix takes each row.

    Only the plan, a row for each source, travels to the documents. Without texts, their rows
    are read once and cut off.
    """
    rows = keyed(docs, quality, seed)
    rows = rows if with_text else C.cut(rows.drop("text"))
    j = rows.join(C.maybe_broadcast(plan(rows)), F.col("source").eqNullSafe(F.col("_src")))
    taken = (F.col("_b") < F.col("_eb")) | ((F.col("_b") == F.col("_eb")) & (F.struct("_k", "doc_id", "_h") <= F.col("_last")))
    return j.withColumn("_copies", F.col("_e") + F.coalesce(taken, F.lit(False)).cast("long")).drop("_h", "_k", "_b", "_src", "_e", "_eb", "_last")


@C.carrying("doc_id", "text", "source")
def mixed(docs: DataFrame, quality: DataFrame | None = None, seed: int = 17) -> DataFrame:
    """The mix itself: each row of `docs` as often as it is taken."""
    d = mix(docs, quality, seed)
    return d.withColumn("_x", F.explode(F.array_repeat(F.lit(1), F.col("_copies").cast("int")))).select(*docs.columns)


def quality_weights(labels: DataFrame) -> DataFrame:
    """Good documents are twice as likely to be drawn, bad ones half as likely."""
    return labels.groupBy("doc_id").agg(F.max("quality").alias("_q")).select("doc_id", F.when(F.col("_q") >= 1, 2.0).when(F.col("_q") <= 0, 0.5).otherwise(1.0).alias("weight"))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents with the words that the mix takes of each."""
    docs = C.table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    out = mix(docs, quality_weights(C.table(spark, sf_dir, "labels")), with_text=False)
    return out.select("doc_id", F.col("_size").alias("size"), "source_size", "target", (F.col("_copies") * F.col("_size")).alias("taken"))


def oracle() -> str:
    """The same rule in DuckDB, with one plain window for each source."""
    w = ", ".join(f"{float(x)}" for x in WEIGHTS)
    return rf"""
WITH q AS (SELECT doc_id, CASE WHEN max(quality) >= 1 THEN 2.0::DOUBLE WHEN max(quality) <= 0 THEN 0.5 ELSE 1.0 END AS weight FROM labels GROUP BY 1),
d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
    -ln((('0x' || substr(md5('17:' || doc_id), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0) / coalesce(weight, 1.0) AS k
  FROM documents LEFT JOIN q USING (doc_id)),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY 1),
r AS (SELECT *, row_number() OVER (ORDER BY encode(source) NULLS LAST) - 1 AS rk FROM s),
c AS (SELECT *, [{w}][(rk % {len(WEIGHTS)} + 1)::BIGINT]::DOUBLE AS w, {float(MOST)} * source_size AS cap FROM r),
l AS (
  SELECT *, ({SHARE} * sum(source_size) OVER () - coalesce(sum(cap) OVER (ORDER BY cap / w, rk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
    / sum(w) OVER (ORDER BY cap / w, rk ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS lev FROM c),
v AS (SELECT arg_min(lev, cap / w) AS lev FROM l WHERE lev * w <= cap),
t AS (SELECT source, source_size, round(least(cap, coalesce((SELECT lev FROM v) * w, cap)), 6) AS target FROM l),
e AS (SELECT *, CASE WHEN source_size > 0 THEN least(floor(target / source_size), {MOST})::BIGINT ELSE 0 END AS e FROM t),
p AS (
  SELECT d.doc_id, d.size, e.source_size, e.target, e.e, e.target - e.e * e.source_size AS rest,
    coalesce(sum(d.size) OVER (PARTITION BY d.source ORDER BY k, d.doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS pre
  FROM d JOIN e ON d.source IS NOT DISTINCT FROM e.source)
SELECT doc_id, size, source_size, target::DOUBLE AS target, ((e + CASE WHEN e < {MOST} AND pre + size / 2.0 <= rest THEN 1 ELSE 0 END) * size)::BIGINT AS taken FROM p
"""
