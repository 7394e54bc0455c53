"""Decoding from n-gram tables: greedy, and temperature with nucleus sampling.

Strategies that give the same tokens: `broadcast`: the table, pruned of what backing off
repeats, travels once and each row walks alone; `frontier`: a table too large for that is
written once in buckets of its contexts, and only the contexts of the current step move to
it (a packed table is met by arrays instead, see `packed`); `doubling` (greedy only): the table's contexts form an automaton, whose jumps over 1, 2,
4, ... tokens are joined with themselves, so that 32 tokens take five joins; `recursive`
(greedy only): one recursive SQL statement, for small runs.
"""

from __future__ import annotations

import hashlib
import math
import uuid
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import uniform
from ..plans.store import BROADCAST_BYTES, PYTHON_BYTES, cut, drop, fits, keep, new_path, partitions, remember, sweep
from . import lm
from .packed import Packed

OUT = "string, generated array<string>"
#: About what a context of a packed table takes as a row.
ROW_BYTES = 96


def _uniform(seed: str, key: str) -> float:
    return int(hashlib.md5(f"{seed}:{key}".encode()).hexdigest()[:8], 16) / float(1 << 32)


def _draw(toks, cums, seed: str, key: str) -> str:
    return toks[min(bisect_left(cums, _uniform(seed, key)), len(toks) - 1)]


def _walk_all(df: DataFrame, known: dict, steps: int, orders: int, seed: str | None) -> DataFrame:
    sent = df.sparkSession.sparkContext.broadcast(known)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        table = sent.value
        for b in batches:
            made = []
            for ident, given in zip(b["id"], b["given"]):
                tail, out = list(given)[-(orders - 1) :], []
                for step in range(steps):
                    for k in range(len(tail), -1, -1):
                        if (hit := table.get(" ".join(tail[len(tail) - k :]))) is not None:
                            break
                    else:
                        break
                    tok = hit if seed is None else _draw(*hit, seed, f"{ident}:{step}")
                    out.append(tok)
                    tail = [*tail, tok][-(orders - 1) :]
                made.append(out)
            yield pd.DataFrame({"id": b["id"], "generated": made})

    return df.mapInPandas(run, f"id {OUT}")


def bucketed(table: DataFrame, key: str, buckets: int | None = None) -> DataFrame:
    """`table` written once in sorted buckets of `key`: a later join on it moves the other side only."""
    spark = table.sparkSession
    name = f"verbatim_{uuid.uuid4().hex}"
    n = buckets or partitions(spark)
    table.repartition(n, key).write.option("path", new_path(spark, "buckets")).option("compression", "zstd").bucketBy(n, key).sortBy(key).saveAsTable(name)
    return spark.table(name)


def _salted(k: Column) -> Column:
    return F.concat(F.lit("\x00"), k.cast("string"))


def _spread(table: DataFrame) -> DataFrame:
    """`table` in buckets of ctx, the empty context once for each bucket: it is every row's and must not be one partition's."""
    n = partitions(table.sparkSession)
    many = table.where("ctx = ''").withColumn("ctx", F.explode(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), _salted)))
    return bucketed(table.where("ctx <> ''").unionByName(many.select(table.columns)), "ctx", n)


def _last(toks: Column, n: int) -> Column:
    """The last n of an array, or all of a shorter one."""
    return F.slice(toks, F.greatest(F.size(toks) - (n - 1), F.lit(1)), F.lit(n))


def _asked(state: DataFrame) -> DataFrame:
    """Each row of state(id, tail, ...) once for each context that it backs off through: `_k` tokens, and `ctx`."""
    asked = F.transform(F.sequence(F.lit(0), F.size("tail")), lambda k: F.struct(k.alias("k"), F.array_join(F.slice("tail", F.size("tail") - k + 1, k), " ").alias("ctx")))
    each = state.withColumn("_a", F.explode(asked))
    n = partitions(state.sparkSession)
    return each.select(*state.columns, F.col("_a.k").alias("_k"), F.when(F.col("_a.k") > 0, F.col("_a.ctx")).otherwise(_salted(F.pmod(F.xxhash64("id"), F.lit(n)))).alias("ctx"))


def _travels(df: DataFrame) -> bool:
    """Whether the frontier of df travels to the buckets as they are."""
    return fits(df, BROADCAST_BYTES // 8)


def _frontier(df: DataFrame, table: DataFrame, steps: int, orders: int, pick, few: bool, every: int = 8) -> DataFrame:
    """table: (ctx, say) as `_spread` gives it; contexts of different orders differ, as an order is a number of tokens. pick(rows grouped by id, step) adds `_t`.

    A frontier that does not travel moves its last tokens only: each step's tokens lie in files, and are put together once at the end.
    """
    none = F.array().cast("array<string>")
    state = df.select("id", F.when(F.size("given") > 0, _last(F.col("given"), orders - 1)).otherwise(none).alias("tail"), none.alias("generated"))
    if few or not steps:
        for step in range(steps):
            met = pick(F.broadcast(_asked(state)).join(table, "ctx"), step)
            longer = F.concat("tail", F.array("_t"))
            state = met.select("id", _last(longer, orders - 1).alias("tail"), F.concat("generated", F.array("_t")).alias("generated"))
            if step % every == every - 1:
                state = cut(state)
                sweep(df.sparkSession)  # each step shuffles all texts so far
        return state.select("id", "generated")
    state, said = state.select("id", "tail"), []
    for step in range(steps):
        met = pick(_asked(state).join(table, "ctx").withColumn("generated", none), step)
        state = keep(met.select("id", _last(F.concat("tail", F.array("_t")), orders - 1).alias("tail"), "_t"))
        said.append(state)
        state = state.select("id", "tail")
    every_step = said[0].select("id", F.lit(0).alias("_n"), "_t")
    for step, s in enumerate(said[1:], 1):
        every_step = every_step.unionByName(s.select("id", F.lit(step).alias("_n"), "_t"))
    out = keep(every_step.groupBy("id").agg(F.sort_array(F.collect_list(F.struct("_n", "_t")))["_t"].alias("generated")))
    for s in said:
        drop(s)
    return out


def _walk_frontier(df: DataFrame, table: DataFrame, steps: int, orders: int) -> DataFrame:
    def pick(rows: DataFrame, step: int) -> DataFrame:
        return rows.groupBy("id").agg(F.max_by("say", "_k").alias("_t"), F.first("tail").alias("tail"), F.first("generated").alias("generated"))

    few, there = _travels(df), _spread(table)
    out = _frontier(df, there, steps, orders, pick, few)
    if not few and steps:
        drop(there)  # the tokens lie in files of their own
    return out


def _walk_drawn(df: DataFrame, table: DataFrame, steps: int, orders: int, seed: str) -> DataFrame:
    """table: (ctx, say). Each context draws where it meets the frontier, so tokens are dealt and nuclei are not; the empty context's nucleus, which may be most of all words, goes to the workers once and serves the rows that no other context meets.

    A frontier that fits is broadcast to the table as it lies; for others the table is written in buckets.
    """
    none = F.array().cast("array<string>")
    if not steps:
        return df.select("id", none.alias("generated"))
    spark = df.sparkSession
    zero = table.where("ctx = ''").select("say.toks", "say.cums").first()
    sent = spark.sparkContext.broadcast((list(zero["toks"]), list(zero["cums"]))) if zero else None

    @F.pandas_udf("string")
    def of_all(u: pd.Series) -> pd.Series:
        toks, cums = sent.value
        return pd.Series([None if math.isnan(x) else toks[min(bisect_left(cums, x), len(toks) - 1)] for x in u], dtype=object)

    state, said = keep(df.select("id", F.when(F.size("given") > 0, _last(F.col("given"), orders - 1)).otherwise(none).alias("tail"))), []
    start, near = state, table.where("ctx <> ''")
    few = fits(state, BROADCAST_BYTES // 4)
    there = near if few else bucketed(near, "ctx")
    for step in range(steps):
        u = uniform(seed, F.concat_ws(":", "id", F.lit(str(step))))
        own = state.select("id", "tail", u.alias("_u"))
        ends = F.transform(F.sequence(F.lit(0), F.size("tail")), lambda k: F.struct(k.alias("k"), F.array_join(F.slice("tail", F.size("tail") - k + 1, k), " ").alias("ctx")))
        asked = own.select("id", "_u", F.explode(ends).alias("_a")).where("_a.k > 0").select("id", "_u", F.col("_a.k").alias("_k"), F.col("_a.ctx").alias("ctx"))
        first = F.size(F.filter("say.cums", lambda c: c < F.col("_u")))
        met = (F.broadcast(asked) if few else asked).join(there, "ctx").select("id", "_k", F.get("say.toks", F.least(first, F.size("say.toks") - 1)).alias("_t"))
        met = met.groupBy("id").agg(F.max_by("_t", "_k").alias("_t"))
        all_of = own.join(met, "id", "left")
        if sent:
            all_of = all_of.withColumn("_t", F.coalesce("_t", of_all(F.when(F.col("_t").isNull(), F.col("_u")))))
        state = keep(all_of.select("id", _last(F.concat("tail", F.array_compact(F.array("_t"))), orders - 1).alias("tail"), "_t"))
        said.append(state)
        state = state.select("id", "tail")
    every = said[0].select("id", F.lit(0).alias("_n"), "_t")
    for step, s in enumerate(said[1:], 1):
        every = every.unionByName(s.select("id", F.lit(step).alias("_n"), "_t"))
    out = keep(every.groupBy("id").agg(F.array_compact(F.sort_array(F.collect_list(F.struct("_n", "_t")))["_t"]).alias("generated")))
    for s in [start, *said] if few else [start, *said, there]:
        drop(s)
    return out


def _ctx(toks: Column) -> Column:
    return F.array_join(toks, " ")


def _landing(df: DataFrame, toks: str, known: DataFrame, orders: int) -> DataFrame:
    """df with `_to`: the longest of the last tokens of `toks` that is a known context, the empty one at least."""
    for k in range(1, orders):
        mine = F.when(F.size(toks) >= k, _ctx(F.slice(toks, F.size(toks) - k + 1, F.lit(k))))
        df = df.withColumn("_c", mine).join(known.select(F.col("ctx").alias("_c"), F.lit(True).alias(f"_h{k}")), "_c", "left").withColumn(f"_c{k}", F.when(F.col(f"_h{k}"), F.col("_c"))).drop("_c")
    return df.withColumn("_to", F.coalesce(*[F.col(f"_c{k}") for k in range(orders - 1, 0, -1)], F.lit(""))).drop(*[f"_{x}{k}" for x in "hc" for k in range(1, orders)])


def _walk_doubling(df: DataFrame, table: DataFrame, steps: int, orders: int) -> DataFrame:
    """table: (ctx, say) with every known context. What follows a context depends on it alone, and where it leads does too: a longer known context at the next place would have shown in a longer one here.

    A row's own jump is made of those that the binary digits of `steps` name.
    """
    table = keep(table)
    known = table.select("ctx")
    one = table.withColumn("_w", F.concat(F.when(F.col("ctx") == "", F.array().cast("array<string>")).otherwise(F.split("ctx", " ")), F.array("say")))
    jump = keep(_landing(one, "_w", known, orders).select("ctx", F.array("say").alias("said"), F.col("_to").alias("to")))
    state = _landing(df.select("id", "given"), "given", known, orders).select("id", F.col("_to").alias("at"), F.array().cast("array<string>").alias("generated"))
    while True:
        used = steps & 1  # then the result reads these files later
        if used:
            state = state.join(jump, F.col("at") == F.col("ctx")).select("id", F.col("to").alias("at"), F.concat("generated", "said").alias("generated"))
        steps >>= 1
        if not steps:
            return state.select("id", "generated")
        then = jump.select(F.col("ctx").alias("_c"), F.col("said").alias("_s"), F.col("to").alias("_t"))
        longer = keep(jump.join(then, F.col("to") == F.col("_c")).select("ctx", F.concat("said", "_s").alias("said"), F.col("_t").alias("to")))
        if not used:
            drop(jump)
        jump = longer


def _walk_recursive(df: DataFrame, table: DataFrame, steps: int, orders: int) -> DataFrame:
    spark = df.sparkSession
    tag = uuid.uuid4().hex
    df.createOrReplaceTempView(f"given_{tag}")
    table.createOrReplaceTempView(f"best_{tag}")
    n = orders - 1
    last = lambda toks, k: f"array_join(slice({toks}, greatest(size({toks}) - {k - 1}, 1), {k}), ' ')"
    joins = " ".join(f"LEFT JOIN best_{tag} b{k} ON size(w.tail) >= {k} AND b{k}.ctx = {last('w.tail', k)}" for k in range(1, orders))
    pick = ", ".join(f"b{k}.say" for k in range(n, -1, -1))
    return spark.sql(f"""
        WITH RECURSIVE w(id, step, tail, generated) AS (
          SELECT id, 0, slice(given, greatest(size(given) - {n - 1}, 1), {n}), CAST(array() AS ARRAY<STRING>) FROM given_{tag}
          UNION ALL
          SELECT id, step + 1, slice(concat(tail, array(nx)), greatest(size(tail) - {n - 2}, 1), {n}), concat(generated, array(nx)) FROM (
            SELECT w.id, w.step, w.tail, w.generated, coalesce({pick}) AS nx FROM w {joins} LEFT JOIN best_{tag} b0 ON b0.ctx = '' WHERE w.step < {steps}))
        SELECT id, generated FROM w WHERE step = {steps}""")


def _run(df: DataFrame, table: DataFrame, steps: int, orders: int, strategy: str, seed: str | None) -> DataFrame:
    if strategy == "auto":
        strategy = "broadcast" if fits(table, PYTHON_BYTES) else "frontier"
    if strategy == "frontier":
        return _walk_frontier(df, table, steps, orders) if seed is None else _walk_drawn(df, table, steps, orders, seed)
    rows = table.collect()  # `fits` bounds it
    known = {r["ctx"]: r["say"] if seed is None else (list(r["say"]["toks"]), list(r["say"]["cums"])) for r in rows}
    return _walk_all(df, known, steps, orders, seed)


def _packed(df: DataFrame, table: Packed, steps: int, strategy: str, seed: str | None) -> DataFrame | None:
    """The frontier's walk over arrays; None where another strategy is asked for, the table is so small that rows walk alone sooner, or the frontier is too large for it."""
    if strategy not in ("auto", "frontier") or strategy == "auto" and table.contexts * ROW_BYTES <= PYTHON_BYTES:
        return None
    return table.walk(df, steps, seed)


def greedy(df: DataFrame, best: DataFrame | Packed, steps: int, orders: int = 4, strategy: str = "auto") -> DataFrame:
    """(id, generated) from df(id string, given array<string>) and best(ctx, tok), as rows or packed; `doubling` needs all contexts, echoes included."""
    if isinstance(best, Packed):
        if (out := _packed(df, best, steps, strategy, None)) is not None:
            return out
        best = best.rows()
    table = best.select("ctx", F.col("tok").alias("say"))
    if strategy == "doubling":
        return _walk_doubling(df, table, steps, orders)
    if strategy == "recursive":
        return _walk_recursive(df, table, steps, orders)
    return _run(df, table, steps, orders, strategy, None)


def nucleus(df: DataFrame, table: DataFrame | Packed, steps: int, orders: int = 4, strategy: str = "auto", seed: str = "draw") -> DataFrame:
    """(id, generated) by draws from `lm.nucleus_table`, as rows or packed; the draw of a step is a hash of (seed, id, step), so reruns agree."""
    if isinstance(table, Packed):
        if (out := _packed(df, table, steps, strategy, seed)) is not None:
            return out
        table = table.nuclei()
    return _run(df, table.select("ctx", F.struct("toks", "cums").alias("say")), steps, orders, strategy, seed)


def successor_table(counts: DataFrame, mix: tuple[float, ...], orders: int) -> DataFrame:
    """(ctx, ord, n_next, toks, ps, p0s): all successors of each context of order 1 and up, their weighted share at its order and at order 0."""
    c = lm.model(counts).where(F.col("ord") < orders)
    weight = F.element_at(F.array(*[F.lit(w) for w in mix]), F.col("ord") + 1)
    c = c.withColumn("_p", weight * F.col("cnt") / F.col("total"))
    zero = c.where("ord = 0").select(F.col("tok").alias("_t"), F.col("_p").alias("_p0"))
    near = c.where("ord > 0").join(zero, F.col("tok") == F.col("_t"))
    near = near.groupBy("ord", "ctx", "n_next").agg(F.sort_array(F.collect_list(F.struct((-F.col("cnt")).alias("_c"), "tok", "_p", "_p0"))).alias("_x"))
    return near.select("ctx", "ord", "n_next", F.col("_x.tok").alias("toks"), F.col("_x._p").alias("ps"), F.col("_x._p0").alias("p0s"))


class Successors:
    """What tuned decoding needs of a model, made once for many policies: its successor table (sent to the workers if it fits, else in buckets) and the frequent words."""

    def __init__(self, counts: DataFrame, orders: int = 4, strategy: str = "auto"):
        from . import policy as P

        spark = counts.sparkSession
        self.orders = orders
        self.often = [(r["tok"], r["p"]) for r in P.frequent(counts).collect()]
        table = cut(successor_table(counts, lm.MIX, orders))
        self.strategy = strategy if strategy != "auto" else "broadcast" if fits(table, PYTHON_BYTES) else "frontier"
        if self.strategy == "broadcast":
            self.sent = spark.sparkContext.broadcast({r["ctx"]: (r["ord"], r["n_next"], r["toks"], r["ps"], r["p0s"]) for r in table.collect()})
        else:
            # the empty context is every row's, so that none is lost where no other is known
            none = spark.createDataFrame([("", 0, 0, [], [], [])], "ctx string, ord int, n_next long, toks array<string>, ps array<double>, p0s array<double>")
            self.table = _spread(table.unionByName(none).select("ctx", F.struct("ord", "n_next", "toks", "ps", "p0s").alias("say")))


def _scorer(often, theta, base: int, lexical: bool, draw):
    """(contexts found, tail) -> the best token, or the nucleus (tokens, running shares) when drawing."""
    from . import policy as P

    bucket = lambda seed, x: int(hashlib.md5(f"{seed}:{x}".encode()).hexdigest()[:8], 16) % P.BUCKETS
    # the weight of each order, and of a context with one successor, with the directive's own on top
    lift = [float(theta[k] + (theta[base + k] if base else 0.0)) for k in range(P.SHARED)]

    def ranked(found, tail):
        cand = {t: [p0, 0, 0] for t, p0 in often}
        for order, n_next, toks, ps, p0s in sorted(found, key=lambda x: x[0]):
            for t, p, p0 in zip(toks, ps, p0s):
                c = cand.get(t)
                if c is None:
                    cand[t] = [p0 + p, order, n_next]
                else:
                    c[0], c[1], c[2] = c[0] + p, order, n_next
        row = bucket("ctx", tail[-1] if len(tail) else "") * P.BUCKETS if lexical else 0
        for t, (p, hi, n_next) in cand.items():
            s = math.log(max(p, lm.FLOOR)) + lift[hi] + (lift[P.SHARED - 1] if hi and n_next == 1 else 0.0)
            # rounded, so that equal scores tie in whatever order their parts were added
            yield round(-(s + (theta[P.SHARED * len(P.DIRECTIVES) + row + bucket("tok", t)] if lexical else 0.0)), 10), t

    if draw is None:
        return lambda found, tail: min(ranked(found, tail))[1]
    temperature, top_p, _ = draw

    def nucleus_of(found, tail):
        order = sorted(ranked(found, tail))
        s = np.array([-x for x, _ in order]) / temperature
        p = np.exp(s - s.max())
        p = p / p.sum()
        before = np.r_[0.0, np.cumsum(p)[:-1]]
        n = int((np.round(before, 9) < top_p).sum())
        return [t for _, t in order[:n]], (np.cumsum(p[:n]) / p[:n].sum()).tolist()

    return nucleus_of


#: Between a policy's name and an id, where both stand in one column.
MARK = "\x01"


def walked(df: DataFrame, known: Successors, settings: dict, steps: int, draw: tuple[float, float, str] | None = None) -> DataFrame:
    """(policy, id, generated) of df(policy, id, given) by many policies in one pass; settings: each one's weights and the directive it runs with. Greedy, or drawn by (temperature, top-p, seed): a draw depends on the id and not on the policy."""
    from . import policy as P

    made = {k: (np.asarray(theta), P.DIRECTIVES.index(directive) * P.SHARED) for k, (theta, directive) in settings.items()}
    orders, often = known.orders, known.often

    def scorers():
        return {k: _scorer(often, theta, base, len(theta) > P.n_features(False), draw) for k, (theta, base) in made.items()}

    if known.strategy == "broadcast":
        sent = known.sent

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            table, picks = sent.value, scorers()
            memo: dict = {}
            for b in batches:
                out = []
                for who, ident, given in zip(b["policy"], b["id"], b["given"]):
                    tail, said = list(given)[-(orders - 1) :], []
                    for step in range(steps):
                        k = (who, *tail)
                        if k not in memo:
                            memo[k] = picks[who]([x for n in range(1, len(tail) + 1) if (x := table.get(" ".join(tail[-n:])))], tail)
                        tok = memo[k] if draw is None else _draw(*memo[k], draw[2], f"{ident}:{step}")
                        said.append(tok)
                        tail = [*tail, tok][-(orders - 1) :]
                    out.append(said)
                yield pd.DataFrame({"policy": b["policy"], "id": b["id"], "generated": out})

        return df.select("policy", "id", "given").mapInPandas(run, f"policy string, id {OUT}")

    def pick(rows: DataFrame, step: int) -> DataFrame:
        @F.pandas_udf("string")
        def choose(ident: pd.Series, tail: pd.Series, found: pd.Series) -> pd.Series:
            picks, out = scorers(), []
            for i, t, f in zip(ident, tail, found):
                who, i = i.split(MARK, 1)
                best = picks[who]([(x["ord"], x["n_next"], x["toks"], x["ps"], x["p0s"]) for x in f if x["ord"]], list(t))
                out.append(best if draw is None else _draw(*best, draw[2], f"{i}:{step}"))
            return pd.Series(out, dtype=object)

        met = rows.groupBy("id").agg(F.collect_list("say").alias("_f"), F.first("tail").alias("tail"), F.first("generated").alias("generated"))
        return met.withColumn("_t", choose("id", "tail", "_f"))

    asked = df.select(F.concat("policy", F.lit(MARK), "id").alias("id"), "given")
    out = _frontier(asked, known.table, steps, orders, pick, _travels(asked), 4)
    parts = F.split("id", MARK, 2)
    return out.select(parts[0].alias("policy"), parts[1].alias("id"), "generated")


def tuned(df: DataFrame, known: Successors, theta, steps: int, directive: str = "", draw: tuple[float, float, str] | None = None) -> DataFrame:
    """(id, generated) by one policy."""
    return walked(df.withColumn("policy", F.lit("one")), known, {"one": (theta, directive)}, steps, draw).drop("policy")


def successors(key: tuple, counts: DataFrame, orders: int = 4) -> Successors:
    """`Successors` of a model, once for a session and key."""
    return remember((*key, "successors", orders), counts.sparkSession, lambda: Successors(counts, orders))
