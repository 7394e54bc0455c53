"""URL filters: host and path rules, and logistic regression on hashed character n-grams.

The rules label a bounded sample of the urls they fit; a logistic regression over hashed
character n-grams of host and path learns from that small table and judges the urls that no
rule fits.

Defined results: a null url or one without `://` has empty host and path, and is judged by
the model like any other; without labelled urls of both kinds the verdict is the kind there
is, or allow.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

# The rules of the query, verdict and pattern.
RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))

#: Most labelled urls for the fit (the ones with the smallest hashes), hash buckets, n-gram lengths.
MAX_LABELLED, DIM, GRAMS = 20_000, 1 << 15, (2, 3, 4, 5)


def parts(url: Column) -> tuple[Column, Column]:
    """(host, path): after the first `://` to `/`, `?`, `#` or end, A-Z lower-cased; then to `?`, `#` or end."""
    at = F.coalesce(F.locate("://", url), F.lit(0))
    rest = F.when(at > 0, F.substr(url, at + 3)).otherwise("")
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(F.substr(rest, F.length(host) + 1), r"^([^?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def rule_for(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, null where none does."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, text in sorted(rules, key=lambda r: len(r[1])):
        h, slash, p = text.partition("/")
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(slash + p)
        rule, verdict = F.when(fits, text).otherwise(rule), F.when(fits, kind).otherwise(verdict)
    return rule, verdict


def _grams(hosts, paths) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row number and bucket of every n-gram, and each row's count, for a batch at once."""
    rows = [b"\x02" + str(h).encode() + b"\x03" + str(p).encode() + b"\x04" for h, p in zip(hosts, paths)]
    size = np.array([len(r) for r in rows], dtype=np.int64)
    data = np.frombuffer(b"".join(rows), dtype=np.uint8).astype(np.uint64)
    owner = np.repeat(np.arange(len(rows)), size)
    # n-grams of the host and of the path are different features
    side = (np.cumsum(data == 3) - np.cumsum(data == 2) >= 0).astype(np.uint64)
    who, what = [], []
    with np.errstate(over="ignore"):
        for n in GRAMS:
            if len(data) < n:
                continue
            h = np.full(len(data) - n + 1, n, dtype=np.uint64) + side[: len(data) - n + 1] * np.uint64(977)
            for k in range(n):
                h = (h ^ data[k : len(data) - n + 1 + k]) * np.uint64(0x100000001B3)
            h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
            inside = owner[: len(h)] == owner[n - 1 :]
            who.append(owner[: len(h)][inside])
            what.append(((h >> np.uint64(33)) % np.uint64(DIM))[inside].astype(np.int64))
    who, what = np.concatenate(who or [owner[:0]]), np.concatenate(what or [owner[:0]])
    return who, what, np.sqrt(np.maximum(np.bincount(who, minlength=len(rows)), 1))


def fit(hosts, paths, blocked, rounds: int = 300, rate: float = 4.0, l2: float = 1e-4) -> tuple[np.ndarray, float]:
    """Weights and bias by full-batch gradient steps with momentum; the same rows give the same weights."""
    y = np.asarray(blocked, dtype=float)
    if len(set(y)) < 2:
        return np.zeros(DIM), (1.0 if len(y) and y[0] else -1.0)
    who, what, norm = _grams(hosts, paths)
    value = 1.0 / norm[who]
    w, b, vw, vb = np.zeros(DIM), 0.0, np.zeros(DIM), 0.0
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-(np.bincount(who, w[what] * value, len(y)) + b)))
        g = (p - y) / len(y)
        vw = 0.9 * vw - rate * (np.bincount(what, g[who] * value, DIM) + l2 * w)
        vb = 0.9 * vb - rate * g.sum()
        w, b = w + vw, b + vb
    return w, b


def score(hosts, paths, model: tuple[np.ndarray, float]) -> np.ndarray:
    """Probability that each url is to be blocked."""
    if not len(hosts):
        return np.zeros(0)
    who, what, norm = _grams(hosts, paths)
    return 1 / (1 + np.exp(-(np.bincount(who, model[0][what], len(hosts)) / norm + model[1])))


def labelled(pages: DataFrame, rules=RULES, most: int = MAX_LABELLED) -> DataFrame:
    """The small labelled table: at most `most` distinct urls (host, path) that a rule fits."""
    host, path = parts(F.col("url"))
    d = pages.select(host.alias("host"), path.alias("path"))
    d = d.withColumn("verdict", rule_for(F.col("host"), F.col("path"), rules)[1]).where("verdict is not null").distinct()
    return d.orderBy(F.xxhash64("host", "path"), "host", "path").limit(most)


def judge(pages: DataFrame, rules=RULES, most: int = MAX_LABELLED) -> DataFrame:
    """page_id, host, path, rule, verdict, p_block for every row of pages(page_id, url)."""
    small = labelled(pages, rules, most).toPandas()
    model = fit(small["host"], small["path"], small["verdict"] == "block")

    @F.pandas_udf("double")
    def p_block(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for h, p in batches:
            yield pd.Series(score(h, p, model))

    host, path = parts(F.col("url"))
    d = pages.select("page_id", host.alias("host"), path.alias("path"))
    rule, verdict = rule_for(F.col("host"), F.col("path"), rules)
    d = d.withColumn("rule", rule).withColumn("_v", verdict).withColumn("p_block", p_block("host", "path"))
    return d.withColumn("verdict", F.coalesce("_v", F.when(F.col("p_block") >= 0.5, "block").otherwise("allow"))).drop("_v")


def op3_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(C.table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")
