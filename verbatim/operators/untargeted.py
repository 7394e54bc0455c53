"""How much of free writing is found word for word in a corpus.

outputs: (output_id, task, tk array<string>); corpus: (doc_id, tk). The corpus side is a set of
n-grams, the output side counts positions. For a range of lengths, `scan` sends the outputs'
n-grams of all lengths to the corpus in one pass (they are few next to it); `cascade` takes a
pass for each length and looks for n-grams of n + 1 only where two n-grams in a row were found.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import grams
from ..plans.store import cut, small


def occurrences(outputs: DataFrame, n: int) -> DataFrame:
    """(output_id, task, pos, gram)."""
    return outputs.select("output_id", "task", F.posexplode(grams("tk", n)).alias("pos", "gram"))


def found(wanted: DataFrame, corpus: DataFrame, grams_of: Column) -> DataFrame:
    """The distinct grams of wanted(gram) that the corpus holds, in one pass over it; the wanted ones travel if they fit."""
    w = cut(wanted.select("gram").distinct())
    return corpus.select(F.explode(grams_of).alias("gram")).join(small(w), "gram", "left_semi").distinct()


def matches(outputs: DataFrame, corpus: DataFrame, n: int) -> DataFrame:
    """(output_id, task, pos, hit) for each n-gram position."""
    occ = occurrences(outputs, n)
    return occ.join(found(occ, corpus, grams("tk", n)).withColumn("_hit", F.lit(True)), "gram", "left").select("output_id", "task", "pos", F.coalesce("_hit", F.lit(False)).alias("hit"))


def overlap(outputs: DataFrame, corpus: DataFrame, n: int) -> DataFrame:
    """(output_id, task, n, positions, matched, ratio) of outputs with n tokens or more."""
    return _ratio(matches(outputs, corpus, n).withColumn("n", F.lit(n)))


def _ratio(m: DataFrame) -> DataFrame:
    d = m.groupBy("output_id", "task", "n").agg(F.count(F.lit(1)).alias("positions"), F.sum(F.col("hit").cast("long")).alias("matched"))
    return d.select("output_id", "task", "n", "positions", "matched", (F.col("matched") / F.col("positions")).alias("ratio"))


def overlap_range(outputs: DataFrame, corpus: DataFrame, lo: int = 5, hi: int = 11, strategy: str = "scan") -> DataFrame:
    """`overlap` for every n from lo to hi."""
    if strategy == "scan":
        of = lambda n: F.transform(grams("tk", n), lambda g: F.struct(F.lit(n).alias("n"), g.alias("gram")))
        occ = outputs.select("output_id", "task", F.explode(F.flatten(F.array(*[of(n) for n in range(lo, hi + 1)]))).alias("_g")).select("output_id", "task", "_g.n", "_g.gram")
        # n-grams of different lengths differ, so one set holds them all
        have = found(occ, corpus, F.flatten(F.array(*[grams("tk", n) for n in range(lo, hi + 1)])))
        hit = occ.join(have.withColumn("_hit", F.lit(True)), "gram", "left")
        return _ratio(hit.select("output_id", "task", "n", F.coalesce("_hit", F.lit(False)).alias("hit")))
    parts, alive = [], None
    for n in range(lo, hi + 1):
        if alive is None:
            m = matches(outputs, corpus, n)
        else:
            occ = occurrences(outputs, n)
            at = Window.partitionBy("output_id").orderBy("pos")
            two = alive.withColumn("_both", F.col("hit") & F.lead("hit").over(at)).where("_both").select("output_id", "pos")
            asked = occ.join(two, ["output_id", "pos"], "left_semi")
            hits = found(asked, corpus, grams("tk", n)).withColumn("_hit", F.lit(True))
            m = occ.join(hits, "gram", "left").select("output_id", "task", "pos", F.coalesce("_hit", F.lit(False)).alias("hit"))
        alive = cut(m)
        parts.append(_ratio(alive.withColumn("n", F.lit(n))))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def creativity_index(ratios: DataFrame) -> DataFrame:
    """(output_id, task, ci, n_lengths): the mean of 1 - ratio over the lengths that the output has."""
    return ratios.groupBy("output_id", "task").agg(F.round(F.avg(1 - F.col("ratio")), 6).alias("ci"), F.count(F.lit(1)).alias("n_lengths"))


def score(ratios: DataFrame, *over: str, n: int = 11) -> DataFrame:
    """(over..., task, outputs, score, micro): percent of n-gram positions found; means of outputs, of positions, and of tasks (task null)."""
    d = ratios.where(F.col("n") == n)
    by = d.groupBy(*over, "task").agg(F.count(F.lit(1)).alias("outputs"), F.avg("ratio").alias("_s"), F.sum("matched").alias("_m"), F.sum("positions").alias("_p"))
    by = by.select(*over, "task", "outputs", (100 * F.col("_s")).alias("score"), (100 * F.col("_m") / F.col("_p")).alias("micro"))
    every = by.groupBy(*over).agg(F.lit(None).cast("string").alias("task"), F.sum("outputs").alias("outputs"), F.avg("score").alias("score"), F.avg("micro").alias("micro"))
    return by.unionByName(every).select(*over, "task", "outputs", F.round("score", 6).alias("score"), F.round("micro", 6).alias("micro"))


def creativity_table(ratios: DataFrame, *by: str, short: int = 5, long: int = 11) -> DataFrame:
    """(by..., task, outputs, ci, short, long): for each task the mean index, and percent of short and long n-grams found."""
    each = ratios.groupBy(*by, "task", "output_id").agg(F.avg(1 - F.col("ratio")).alias("ci"), *[F.max(F.when(F.col("n") == n, F.col("ratio"))).alias(name) for n, name in ((short, "_s"), (long, "_l"))])
    return each.groupBy(*by, "task").agg(F.count(F.lit(1)).alias("outputs"), F.round(F.avg("ci"), 6).alias("ci"), F.round(100 * F.avg("_s"), 6).alias("short"), F.round(100 * F.avg("_l"), 6).alias("long"))


def coverage(outputs: DataFrame, corpus: DataFrame, n: int) -> DataFrame:
    """(output_id, n_tokens, covered, share): tokens inside some n-gram that was found."""
    hit = matches(outputs, corpus, n).where("hit").select("output_id", F.explode(F.sequence(F.col("pos"), F.col("pos") + n - 1)).alias("at")).distinct()
    d = outputs.select("output_id", F.size("tk").alias("n_tokens")).where(f"n_tokens >= {n}")
    d = d.join(hit.groupBy("output_id").agg(F.count(F.lit(1)).alias("covered")), "output_id", "left")
    return d.select("output_id", "n_tokens", F.coalesce("covered", F.lit(0)).alias("covered"), F.round(F.coalesce("covered", F.lit(0)) / F.col("n_tokens"), 6).alias("share"))


def runs(outputs: DataFrame, corpus: DataFrame, n: int = 5) -> DataFrame:
    """(output_id, start, tokens): every stretch of tokens whose n-grams are all found."""
    at = Window.partitionBy("output_id").orderBy("pos")
    d = matches(outputs, corpus, n).where("hit").withColumn("_island", F.col("pos") - F.row_number().over(at))
    d = d.groupBy("output_id", "_island").agg(F.min("pos").alias("start"), (F.count(F.lit(1)) + n - 1).alias("tokens"))
    return d.select("output_id", F.col("start").cast("int").alias("start"), F.col("tokens").cast("long").alias("tokens"))


def longest_run(outputs: DataFrame, corpus: DataFrame, n: int = 5) -> DataFrame:
    """(output_id, start, tokens): the longest stretch of `runs`, the first on a tie."""
    best = runs(outputs, corpus, n).groupBy("output_id").agg(F.max(F.struct("tokens", (-F.col("start")).alias("_s"))).alias("_b"))
    return best.select("output_id", (-F.col("_b._s")).cast("int").alias("start"), F.col("_b.tokens").alias("tokens"))


def decomposition(before: DataFrame, after: DataFrame, *by: str) -> DataFrame:
    """(by..., n, before, after, change, share): mean ratios by length, and each length's share of the change of the index."""
    key = [*by, "n"]
    b = before.groupBy(*key).agg(F.avg("ratio").alias("before"))
    a = after.groupBy(*key).agg(F.avg("ratio").alias("after"))
    d = b.join(a, key).withColumn("change", F.col("after") - F.col("before"))
    # as many rows as lengths
    total = F.sum("change").over(Window.partitionBy(*by))
    return d.withColumn("share", F.when(total != 0, F.col("change") / total)).select(*key, *[F.round(c, 6).alias(c) for c in ("before", "after", "change", "share")])


def build_index(corpus: DataFrame, path: str, lengths: tuple[int, ...] = (5, 11), buckets: int = 16) -> None:
    """Distinct gram hashes of the corpus by length and bucket: one shuffle for many later look-ups."""
    parts = [corpus.select(F.lit(n).alias("n"), F.explode(grams("tk", n)).alias("_g")).select("n", F.xxhash64("_g").alias("h")) for n in lengths]
    d = parts[0]
    for p in parts[1:]:
        d = d.unionByName(p)
    d.distinct().withColumn("bucket", F.pmod("h", F.lit(buckets)).cast("int")).repartition("n", "bucket").write.mode("overwrite").partitionBy("n", "bucket").parquet(path)


def look_up(outputs: DataFrame, index: DataFrame, n: int, buckets: int = 16) -> DataFrame:
    """`matches` against a built index; only the outputs move, and only their buckets are read."""
    occ = occurrences(outputs, n).withColumn("h", F.xxhash64("gram")).withColumn("bucket", F.pmod("h", F.lit(buckets)).cast("int"))
    have = index.where(F.col("n") == n).select("bucket", "h", F.lit(True).alias("_hit"))
    return occ.join(have, ["bucket", "h"], "left").select("output_id", "task", "pos", F.coalesce("_hit", F.lit(False)).alias("hit"))
