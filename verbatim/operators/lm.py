"""An n-gram language model held in tables: the stand-in for a neural target model.

counts: (ord, ctx, tok, cnt), ctx being the `ord` tokens before tok joined by a space; a model
also has total and n_next, the tokens and the different tokens after each context, so that
nothing groups by context again. The empty context of order 0 is one context for all tokens:
nothing here deals or sorts order 0 by context.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.store import fits, small

ORDERS = 4
#: Weights of the relative frequencies at orders 0, 1, 2, 3, and the probability of what was never seen.
MIX, FLOOR = (0.1, 0.2, 0.3, 0.4), 1e-6


def _shifted(df: DataFrame, keep: list[str], toks: str, orders: int) -> DataFrame:
    """(keep..., i, _t0, _t1, ...): every token with the tokens before it, null where there are none. Shifted arrays are laid side by side, so no lambda runs for a token."""
    d = df.where(F.size(toks) > 0).select(*keep, F.col(toks).alias("_t0"))
    for k in range(1, orders):
        d = d.withColumn(f"_t{k}", F.slice(F.concat(F.array_repeat(F.lit(None).cast("string"), k), "_t0"), F.lit(1), F.size("_t0")))
    d = d.select(*keep, F.posexplode(F.arrays_zip(*[f"_t{k}" for k in range(orders)])).alias("i", "_z"))
    return d.select(*keep, "i", *[F.col(f"_z._t{k}").alias(f"_t{k}") for k in range(orders)])


def _ctx(order: int) -> Column:
    """The `order` tokens before a token of `_shifted`, joined; null where one is missing."""
    return F.concat(*[x for k in range(order, 0, -1) for x in (F.col(f"_t{k}"), F.lit(" "))][:-1]) if order else F.lit("")


def _places(df: DataFrame, keep: list[str], toks: str, orders: int) -> DataFrame:
    """(keep..., i, ord, ctx, tok): every token at every order that its place allows."""
    rows = [x for o in range(orders) for x in (F.lit(o), _ctx(o))]
    d = _shifted(df, keep, toks, orders).select(*keep, "i", F.stack(F.lit(orders), *rows).alias("ord", "ctx"), F.col("_t0").alias("tok"))
    return d.where("ctx is not null")


def fit(docs: DataFrame, orders: int = ORDERS, min_count: int = 1, part: tuple[int, int] = (0, 1)) -> DataFrame:
    """Counts over df(tk); contexts never cross a document. Only the longest contexts are counted from the text, one row a token; those of each lower order are sums of the order above, so shuffles hold a token once and then only what differs.

    part (k, n): only contexts whose last word falls to part k of n; the empty context is part 0's.
    """
    k_part, n_parts = part
    d = _shifted(docs, [], "tk", orders).where("_t1 is not null") if orders > 1 else None
    if d is not None and n_parts > 1:
        d = d.where(F.pmod(F.xxhash64("_t1"), F.lit(n_parts)) == k_part)
    levels, schema = [], "ord int, ctx string, tok string, cnt long"
    for o in range(orders - 1, 0, -1):
        words = [f"_t{k}" for k in range(o, -1, -1)]
        d = d.groupBy(*words).agg(F.count(F.lit(1)).alias("cnt") if o == orders - 1 else F.sum("cnt").alias("cnt"))
        # a condition on the count too, so that it isn't moved below the sum: all orders read one shuffle
        levels.append(d.where(_ctx(o).isNotNull() | (F.col("cnt") < 0)).select(F.lit(o).alias("ord"), _ctx(o).alias("ctx"), F.col("_t0").alias("tok"), "cnt"))
    if not k_part:
        levels.append(docs.select(F.explode("tk").alias("tok")).groupBy("tok").agg(F.count(F.lit(1)).alias("cnt")).select(F.lit(0).alias("ord"), F.lit("").alias("ctx"), "tok", "cnt"))
    out = levels[0] if levels else docs.sparkSession.createDataFrame([], schema)
    for x in levels[1:]:
        out = out.unionByName(x)
    return out if min_count <= 1 else out.where(F.col("cnt") >= min_count)


def after(docs: DataFrame, words: DataFrame) -> DataFrame:
    """The counts of order 1 over df(tk) whose context is in words(ctx): where few words are asked for, no table of all counts is made."""
    asked = small(words.select(F.col("ctx").alias("_t1")).where("_t1 is not null").distinct())
    d = _shifted(docs, [], "tk", 2).where("_t1 is not null").join(asked, "_t1", "left_semi")
    d = d.groupBy("_t1", "_t0").agg(F.count(F.lit(1)).alias("cnt"))
    return d.select(F.lit(1).alias("ord"), F.col("_t1").alias("ctx"), F.col("_t0").alias("tok"), "cnt")


def model(counts: DataFrame) -> DataFrame:
    """counts with total and n_next of each context. A context's rows meet their total by a join that may split a hot context; order 0 gets its one total by broadcast."""
    if "total" in counts.columns:
        return counts
    sums = [F.sum("cnt").alias("total"), F.count(F.lit(1)).alias("n_next")]
    near, zero = counts.where("ord > 0"), counts.where("ord = 0")
    near = near.join(near.groupBy("ord", "ctx").agg(*sums), ["ord", "ctx"])
    zero = zero.crossJoin(F.broadcast(zero.agg(*sums)))
    return near.unionByName(zero).select("ord", "ctx", "tok", "cnt", "total", "n_next")


def best_next(counts: DataFrame) -> DataFrame:
    """(ord, ctx, tok, cnt, total, n_next): the likeliest successor of each context, the smaller token on a tie."""
    best = counts.groupBy("ord", "ctx").agg(F.min(F.struct((-F.col("cnt")).alias("c"), "tok")).alias("_b"), F.sum("cnt").alias("total"), F.count(F.lit(1)).alias("n_next"))
    return best.select("ord", "ctx", F.col("_b.tok").alias("tok"), (-F.col("_b.c")).alias("cnt"), "total", "n_next")


def without_echoes(best: DataFrame, zero: DataFrame | None = None) -> DataFrame:
    """`best` less the contexts whose shorter context says the same: backing off gives equal answers from fewer rows. A context and its shorter ones end alike, so parts of `fit` may be taken one by one; `zero` (ctx, tok) is then the empty context's answer."""
    b = best.select("ord", "ctx", "tok")
    shorter = b.select((F.col("ord") + 1).alias("_o"), F.col("ctx").alias("_c"), F.col("tok").alias("_t"))
    near = b.where("ord > 1").withColumn("_s", F.regexp_replace("ctx", r"^[^ ]* ", ""))
    near = near.join(shorter, (F.col("_o") == F.col("ord")) & (F.col("_c") == F.col("_s")), "left").where("_t is null or _t <> tok")
    # every context of one word backs off to the one empty context
    zero = F.broadcast((b.where("ord = 0") if zero is None else zero).select(F.col("tok").alias("_t")))
    one = b.where("ord = 1").crossJoin(zero).where("_t <> tok")
    return near.select("ord", "ctx", "tok").unionByName(one.select("ord", "ctx", "tok")).unionByName(b.where("ord = 0"))


def _nucleus_of_all(zero: DataFrame, temperature: float, top_p: float) -> DataFrame:
    """The nucleus of the empty context. Words with equal counts are equally likely, so the counts tell how many words it has; the driver sees a row for each different count (fewer than the root of twice the tokens), and the nucleus, which is one row of the table anyway."""
    groups = sorted(((r["cnt"], r["n"]) for r in zero.groupBy("cnt").agg(F.count(F.lit(1)).alias("n")).collect()), reverse=True)
    spark = zero.sparkSession
    schema = "ord int, ctx string, toks array<string>, cums array<double>, mass double"
    if not groups:
        return spark.createDataFrame([], schema)
    weight = np.array([float(c) for c, _ in groups]) ** (1.0 / temperature)
    n = np.array([k for _, k in groups])
    p = weight / (weight * n).sum()
    before = np.r_[0.0, np.cumsum(p * n)[:-1]]
    # of each group, the words before which the running mass, rounded to nine places, is below top_p
    take = np.clip(np.ceil((top_p - 5e-10 - before) / p), 0, n).astype(int)
    probs = np.repeat(p, take)
    toks = [r["tok"] for r in zero.orderBy(F.col("cnt").desc(), "tok").limit(int(take.sum())).collect()]
    return spark.createDataFrame([(0, "", toks, (np.cumsum(probs) / probs.sum()).tolist(), float(probs.sum()))], schema)


def nucleus_table(counts: DataFrame, temperature: float = 0.7, top_p: float = 0.9) -> DataFrame:
    """(ord, ctx, toks, cums, mass): the nucleus of each context's successors, the running share within it, and its mass."""
    key = ["ord", "ctx"]
    d = counts.where("ord > 0").withColumn("_w", F.pow(F.col("cnt").cast("double"), F.lit(1.0 / temperature)))
    every = Window.partitionBy(*key)
    at = every.orderBy(F.col("cnt").desc(), "tok")
    d = d.withColumn("_p", F.col("_w") / F.sum("_w").over(every)).withColumn("_r", F.row_number().over(at))
    d = d.withColumn("_before", F.coalesce(F.sum("_p").over(at.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
    d = d.where(F.round("_before", 9) < top_p)
    d = d.groupBy(*key).agg(F.sort_array(F.collect_list(F.struct("_r", "tok", (F.col("_before") + F.col("_p")).alias("c")))).alias("_x"), F.sum("_p").alias("mass"))
    d = d.select(*key, F.col("_x.tok").alias("toks"), F.transform("_x.c", lambda c: c / F.col("mass")).alias("cums"), "mass")
    return d.unionByName(_nucleus_of_all(counts.where("ord = 0"), temperature, top_p))


def without_repeats(nuclei: DataFrame) -> DataFrame:
    """(ctx, toks, cums) of a nucleus table less the contexts of one token whose shorter context has that token alone too: backing off draws the same from fewer rows. Works on the contexts of one part of `fit` alone."""
    one = nuclei.where((F.col("ord") > 0) & (F.size("toks") == 1)).select("ord", "ctx", "toks")
    shorter = one.select((F.col("ord") + 1).alias("_o"), F.col("ctx").alias("_c"), F.col("toks").alias("_t"))
    longer = one.where("ord > 1").withColumn("_s", F.regexp_replace("ctx", r"^[^ ]* ", ""))
    longer = longer.join(shorter, (F.col("_o") == F.col("ord")) & (F.col("_c") == F.col("_s")) & (F.col("_t") == F.col("toks")), "left_anti")
    rest = nuclei.where((F.col("ord") < 2) | (F.size("toks") > 1))
    return rest.select("ctx", "toks", "cums").unionByName(longer.select("ctx", "toks", F.array(F.lit(1.0)).alias("cums")))


def positions(df: DataFrame, ident: str, given: str, text: str, orders: int = ORDERS) -> DataFrame:
    """(ident, pos, ord, ctx, tok) for every token of `text` after the tokens of `given`, at every order."""
    d = df.select(ident, F.concat(given, text).alias("_all"), F.size(given).alias("_n"))
    d = _places(d, [ident, "_n"], "_all", orders).where("i >= _n")
    return d.select(ident, (F.col("i") - F.col("_n")).alias("pos"), "ord", "ctx", "tok")


def part_shares(df: DataFrame, plain: DataFrame, ident: str, given: str, text: str, part: tuple[int, int], mixes: list[tuple[float, ...]]) -> DataFrame:
    """(ident, pos, p0, p1, ...): what one part of the contexts, whose counts `plain` holds, adds to the probability of each token under each weighting. The orders of 1 and up of a token fall to one part, as they share their last word.

    Counts are met by (ord, ctx, tok) and totals by (ord, ctx), so that no count is dealt again with its context's total.
    """
    k_part, n_parts = part
    weight = lambda mix: F.element_at(F.array(*[F.lit(w) for w in mix]), F.col("ord") + 1)
    d = df.select(ident, F.concat(given, text).alias("_all"), F.size(given).alias("_n"))
    d = _shifted(d, [ident, "_n"], "_all", len(mixes[0])).where("i >= _n and _t1 is not null")
    if n_parts > 1:
        d = d.where(F.pmod(F.xxhash64("_t1"), F.lit(n_parts)) == k_part)
    rows = [x for o in range(1, len(mixes[0])) for x in (F.lit(o), _ctx(o))]
    p = d.select(ident, (F.col("i") - F.col("_n")).alias("pos"), F.stack(F.lit(len(mixes[0]) - 1), *rows).alias("ord", "ctx"), F.col("_t0").alias("tok")).where("ctx is not null")
    near = plain.where("ord > 0")
    hit = p.join(near, ["ord", "ctx", "tok"]).select(ident, "pos", "ord", "ctx", "cnt")
    hit = hit.join(near.groupBy("ord", "ctx").agg(F.sum("cnt").alias("total")), ["ord", "ctx"])
    return hit.groupBy(ident, "pos").agg(*[F.sum(weight(mix) * F.col("cnt") / F.col("total")).alias(f"p{k}") for k, mix in enumerate(mixes)])


def nll_of_shares(df: DataFrame, shares: DataFrame, zero: DataFrame, ident: str, text: str, mixes: list[tuple[float, ...]]) -> DataFrame:
    """(ident, n_tokens, nll0, nll1, ...) of the shares of all parts and the counts of order 0, zero(tok, cnt): what `sequence_nll` gives under each weighting."""
    p = df.select(ident, F.posexplode(text).alias("pos", "tok"))
    of = zero.crossJoin(F.broadcast(zero.agg(F.sum("cnt").alias("total")))).select("tok", (F.col("cnt") / F.col("total")).alias("_zero"))
    p = p.join(of, "tok", "left").join(shares, [ident, "pos"], "left")
    told = lambda k, mix: F.greatest(F.lit(mix[0]) * F.coalesce("_zero", F.lit(0.0)) + F.coalesce(f"p{k}", F.lit(0.0)), F.lit(FLOOR))
    return p.groupBy(ident).agg(F.count(F.lit(1)).alias("n_tokens"), *[F.sum(-F.log(told(k, mix))).alias(f"nll{k}") for k, mix in enumerate(mixes)])


def sequence_nll(df: DataFrame, counts: DataFrame, ident: str, given: str, text: str, mix: tuple[float, ...] = MIX) -> DataFrame:
    """(ident, n_tokens, nll): -sum of ln of the interpolated probabilities of the tokens of `text`. A token never seen after a context adds nothing there, so one join by (ord, ctx, tok) tells all."""
    p = positions(df, ident, given, text, len(mix))
    known, asked = model(counts).select("ord", "ctx", "tok", "cnt", "total"), p.select("ord", "ctx", "tok")
    if fits(asked):  # then only the counts that are asked for are dealt, not the table
        known = known.join(F.broadcast(asked), ["ord", "ctx", "tok"], "left_semi")
    hit = p.join(known, ["ord", "ctx", "tok"], "left")
    weight = F.element_at(F.array(*[F.lit(w) for w in mix]), F.col("ord") + 1)
    mass = hit.groupBy(ident, "pos").agg(F.sum(weight * F.coalesce(F.col("cnt") / F.col("total"), F.lit(0.0))).alias("_p"))
    return mass.groupBy(ident).agg(F.count(F.lit(1)).alias("n_tokens"), F.sum(-F.log(F.greatest("_p", F.lit(FLOOR)))).alias("nll"))
