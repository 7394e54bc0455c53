"""Worked examples, invariants and brute force for the methods and measures."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from verbatim.functions import rouge
from verbatim.functions.text import grams, tokens
from verbatim.operators import decode, lm, memorize, objectives, pairs, policy, report, sampling, segments, trainer, untargeted, utility

WORD = st.sampled_from("abcde")


def plain_lcs(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        new = [0]
        for j, y in enumerate(b):
            new.append(row[j] + 1 if x == y else max(row[j + 1], new[j]))
        row = new
    return row[-1]


@given(st.lists(WORD, max_size=40), st.lists(WORD, max_size=40))
@settings(max_examples=200, deadline=None)
def test_lcs_words(a, b):
    n = rouge.lcs_words(a, b)
    assert n == plain_lcs(a, b) == rouge.lcs_words(b, a)
    assert 0 <= n <= min(len(a), len(b)) and rouge.lcs_words(a, a) == len(a)


def test_lcs_columns_and_threshold(spark):
    ref = [f"r{k}" for k in range(32)]
    rows = [("basic", list("abcd"), list("bxd")), ("none", [], ref), ("half", ref[:16], ref), ("over", ref[:17], ref), ("both", [], [])]
    df = spark.createDataFrame(rows, "id string, generated array<string>, reference array<string>")
    df = df.withColumn("native", rouge.lcs_len("generated", "reference")).withColumn("bound", rouge.bag_bound("generated", "reference"))
    got = {r.id: r for r in memorize.score(df).collect()}
    assert {k: (r.lcs, r.native) for k, r in got.items()} == {"basic": (2, 2), "none": (0, 0), "half": (16, 16), "over": (17, 17), "both": (0, 0)}
    assert all(r.bound >= r.lcs for r in got.values())
    ratio = memorize.extraction_ratio(memorize.score(df.where("id in ('half', 'over')"))).first()
    assert (ratio.n, ratio.extraction) == (2, 50.0)


def test_overlap_examples(spark):
    words = [f"w{k}" for k in range(12)]
    corpus = spark.createDataFrame([(1, words)], "doc_id long, tk array<string>")
    partial = words[:6] + [f"x{k}" for k in range(6)]
    outs = spark.createDataFrame([("copy", "a", words), ("new", "a", [f"n{k}" for k in range(12)]), ("part", "b", partial), ("short", "b", words[:9])], "output_id string, task string, tk array<string>")
    ratios = untargeted.overlap_range(outs, corpus)
    ci = {r.output_id: (r.ci, r.n_lengths) for r in untargeted.creativity_index(ratios).collect()}
    assert ci == {"copy": (0.0, 7), "new": (1.0, 7), "part": (0.943878, 7), "short": (0.0, 5)}
    cascade = untargeted.overlap_range(outs, corpus, strategy="cascade")
    assert sorted(map(tuple, cascade.collect())) == sorted(map(tuple, ratios.collect()))
    for _, rows in ((k, [r for r in ratios.collect() if r.output_id == k]) for k in ci):
        by_n = [r.ratio for r in sorted(rows, key=lambda r: r.n)]
        assert by_n == sorted(by_n, reverse=True)
    assert {r.output_id: r.tokens for r in untargeted.longest_run(outs, corpus).collect()} == {"copy": 12, "part": 6, "short": 9}


def test_index_equals_scan(spark, tmp_path):
    words = [f"w{k}" for k in range(30)]
    corpus = spark.createDataFrame([(1, words)], "doc_id long, tk array<string>")
    outs = spark.createDataFrame([("a", "t", words[3:20]), ("b", "t", words[:6] + ["z"] * 6)], "output_id string, task string, tk array<string>")
    untargeted.build_index(corpus, str(tmp_path / "index"))
    key = lambda df: sorted(map(tuple, df.collect()))
    assert key(untargeted.look_up(outs, spark.read.parquet(str(tmp_path / "index")), 5)) == key(untargeted.matches(outs, corpus, 5))


def test_loss_examples(spark):
    rows = [("start", "chosen", -1.0, -1.0), ("start", "rejected", -2.0, -2.0), ("good", "chosen", 5.0, 0.0), ("good", "rejected", -5.0, 0.0), ("swap", "chosen", -5.0, 0.0), ("swap", "rejected", 5.0, 0.0)]
    out = {r.pair_id: round(r.loss, 6) for r in objectives.preference_loss(spark.createDataFrame(rows, "pair_id string, side string, logp double, logp_ref double")).collect()}
    assert out == {"start": 0.693147, "good": 0.313262, "swap": 1.313262}


def test_reduction_example(spark):
    got = report.reduction(report.published(spark)).where("model = 'base-A' and variant = 'tuned' and metric = 'writing'").first()
    assert got.reduction == 25.433526


def test_mix_share(spark):
    p = spark.createDataFrame([(f"p{k}", None, ["a"], ["b"], ["c"], "rewrite") for k in range(36)], "pair_id string, directive string, prompt array<string>, chosen array<string>, rejected array<string>, origin string")
    g = p.withColumn("pair_id", F.concat(F.lit("g"), "pair_id")).withColumn("origin", F.lit("generic"))
    assert {r.origin: r["count"] for r in pairs.mix(p, g, 0.9).groupBy("origin").count().collect()} == {"rewrite": 36, "generic": 4}
    x = p.select("pair_id", "prompt", F.array(F.lit("o")).alias("original"), F.array(F.lit("r")).alias("rewrite"))
    for r in pairs.with_directives(x).collect():
        assert r.chosen == (["o"] if r.directive == pairs.ALLOW else ["r"])


def tiny_counts(spark):
    docs = spark.createDataFrame([(["the", "cat", "sat", "on", "the", "mat"],), (["the", "cat", "ran", "to", "the", "dog"],), (["a", "dog", "sat", "on", "a", "mat"],)], "tk array<string>")
    return docs, lm.fit(docs)


def plain_greedy(docs, given, steps):
    count: dict = {}
    for d in docs:
        for i in range(len(d)):
            for o in range(min(i, 3) + 1):
                c = count.setdefault(tuple(d[i - o : i]), {})
                c[d[i]] = c.get(d[i], 0) + 1
    out = list(given)
    for _ in range(steps):
        for o in range(min(3, len(out)), -1, -1):
            c = count.get(tuple(out[len(out) - o :]))
            if c:
                out.append(min(c, key=lambda t: (-c[t], t)))
                break
    return out[len(given) :]


def test_decoding_strategies_agree(spark):
    docs, counts = tiny_counts(spark)
    rows = [r.tk for r in docs.collect()]
    best = lm.without_echoes(lm.best_next(counts))
    given = [["the"], [], ["on", "the"], ["unknown", "dog"]]
    df = spark.createDataFrame([(str(k), g) for k, g in enumerate(given)], "id string, given array<string>")
    want = {str(k): plain_greedy(rows, g, 7) for k, g in enumerate(given)}
    for strategy in ("broadcast", "frontier", "recursive"):
        assert {r.id: r.generated for r in decode.greedy(df, best, 7, strategy=strategy).collect()} == want
    for steps in (1, 4, 7):
        got = {r.id: r.generated for r in decode.greedy(df, lm.best_next(counts), steps, strategy="doubling").collect()}
        assert got == {k: v[:steps] for k, v in want.items()}
    table = lm.nucleus_table(counts)
    a, b = ({r.id: r.generated for r in decode.nucleus(df, table, 6, strategy=s).collect()} for s in ("broadcast", "frontier"))
    assert a == b
    theta = np.zeros(policy.n_features(False))
    for draw in (None, (0.7, 0.9, "draw")):
        a, b = ({r.id: r.generated for r in decode.tuned(df, decode.Successors(counts, strategy=s), theta, 5, draw=draw).collect()} for s in ("broadcast", "frontier"))
        assert a == b
    # a directive's weights come on top of the plain ones
    theta[:5], theta[5:10] = 1.0, -1.0
    known = decode.Successors(counts)
    zero = {r.id: r.generated for r in decode.tuned(df, known, np.zeros(15), 5).collect()}
    assert {r.id: r.generated for r in decode.tuned(df, known, theta, 5, pairs.ALLOW).collect()} == zero


def test_gradient_and_descent(spark):
    _, counts = tiny_counts(spark)
    rows = [("1/chosen", "1", "chosen", None, ["the"], ["cat", "ran"]), ("1/rejected", "1", "rejected", None, ["the"], ["cat", "sat"]), ("2/chosen", "2", "chosen", pairs.ALLOW, ["on"], ["a", "mat"]), ("2/rejected", "2", "rejected", pairs.ALLOW, ["on"], ["the", "mat"])]
    seqs = spark.createDataFrame(rows, "seq_id string, item_id string, role string, directive string, given array<string>, text array<string>")
    for lexical in (False, True):
        data = trainer.items(policy.design(seqs, counts, lexical), seqs.select("seq_id", "item_id", "role"))
        local = data.collect()
        for objective in (objectives.Preference(1.0),):
            theta = np.random.default_rng(1).normal(0, 0.3, policy.n_features(lexical))
            loss, grad, n = trainer.step(data, objective, theta)
            assert n == 2

            reference = np.random.default_rng(2).normal(0, 0.3, len(theta))
            loss, grad, _ = trainer.step(data, objective, theta, reference)

            def total(t, objective=objective, reference=reference):
                out = 0.0
                for r in local:
                    out += objective.terms({x["role"]: trainer.sequence_logp(x["positions"], t, False, reference)[:2] for x in r["parts"]})[0]
                return out / len(local)

            assert math.isclose(loss, total(theta))
            for k in np.flatnonzero(grad)[:12]:
                d = np.zeros_like(theta)
                d[k] = 1e-5
                assert abs((total(theta + d) - total(theta - d)) / 2e-5 - grad[k]) < 1e-5
        p, losses = trainer.fit(data, objectives.Preference(1.0), policy.identity(lexical), rate=0.5, steps=5)
        assert math.isclose(losses[0], math.log(2)) and losses[-1] < losses[0]
        # a chained fit starts from the last policy, which is its reference too
        q, chained = trainer.fit(data, objectives.Preference(1.0), p, rate=0.5, steps=2)
        assert math.isclose(chained[0], math.log(2)) and not np.array_equal(p.theta, q.theta)
        r, low = trainer.fit_lowrank(data, objectives.Preference(1.0), 2, 0.5, 2, start=policy.widened(p, True))
        assert lexical is False or math.isclose(low[0], math.log(2))


@pytest.mark.parametrize("objective", [objectives.GradientAscent(), objectives.NegativePreference(), objectives.NextToken(), objectives.Preference()])
def test_coefficients_are_slopes(objective):
    logp = {r: (-3.0 - k, -2.5) for k, r in enumerate(objective.roles)}
    _, coef = objective.terms(logp)
    for r in objective.roles:
        up, down = ({**logp, r: (logp[r][0] + e, logp[r][1])} for e in (1e-6, -1e-6))
        assert abs((objective.terms(up)[0] - objective.terms(down)[0]) / 2e-6 - coef[r]) < 1e-6


def test_policy_round_trip(spark, tmp_path):
    p = policy.Policy(np.arange(15.0), False, {"rate": 1.0})
    p.save(spark, str(tmp_path / "w"))
    q = policy.Policy.load(spark, str(tmp_path / "w"))
    assert (q.theta == p.theta).all() and q.settings == p.settings and q.lexical is False


def test_splits_and_layout(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet").withColumn("tk", tokens("text"))
    a = sorted(r.doc_id for r in sampling.sample_docs(d, 20).collect())
    assert a == sorted(r.doc_id for r in sampling.sample_docs(d.repartition(7), 20).collect())
    seen, held = sampling.seen(d), sampling.held(d, "grams")
    assert held.join(seen, "text", "left_semi").count() == 0
    g = lambda x: x.select(F.explode(grams("tk", 11)).alias("g"))
    assert g(held).join(g(seen), "g", "left_semi").count() == 0


def test_short_and_empty(spark):
    d = spark.createDataFrame([(1, [f"t{k}" for k in range(95)]), (2, [f"t{k}" for k in range(96)]), (3, [])], "doc_id long, tk array<string>")
    assert [r.doc_id for r in segments.head_segment(d).collect()] == [2]
    assert [r.start for r in segments.stride_segments(d, 10, 5, 40).where("doc_id = 2").orderBy("start").collect()] == [0, 40, 80]
    assert segments.head_segment(d.limit(0)).count() == 0


def test_utility_helpers(spark):
    df = spark.createDataFrame([("a 3, then 1,234.50 left",), ("none",), ("-7",)], "t string")
    assert [str(r[0]) for r in df.select(utility.last_number("t")).collect()] == ["1234.50", "None", "-7.00"]
    d = spark.createDataFrame([(float(k % 2), 0.0, k % 4 < 2) for k in range(40)], "win double, gap double, side boolean")
    assert abs(utility.controlled_win_rate(d).first().win_rate - 0.5) < 1e-9
    assert [abs(r.win_rate - 0.5) < 1e-9 for r in utility.controlled_win_rate(d, "side").collect()] == [True, True]


def test_all_successors_are_candidates(spark):
    """A context with very many successors: log-probabilities against all of them, and decoding that prefers a rare one."""
    n = 96
    docs = [["h", f"a{k:03d}"] for k in range(n) for _ in range(2)] + [["h", "zz", "yy"]] + [[f"f{k}"] * 9 for k in range(policy.FREQUENT)]
    counts = lm.fit(spark.createDataFrame([(d,) for d in docs], "tk array<string>"))
    seqs = spark.createDataFrame([("s", None, ["h"], ["zz"])], "seq_id string, directive string, given array<string>, text array<string>")
    total, after = sum(map(len, docs)), 2 * n + 1
    share = lambda one, two: 0.1 * one / total + 0.2 * two / after
    often = sorted({"h": after, **{f"f{k}": 9 for k in range(policy.FREQUENT)}}.items(), key=lambda x: (-x[1], x[0]))[: policy.FREQUENT]
    rest = sum(0.1 * c / total for _, c in often)
    theta = np.random.default_rng(2).normal(0, 0.5, policy.n_features(False))
    lift = lambda hi: math.exp(theta[hi])
    want = math.log(share(1, 1) * lift(1) / (lift(1) * (n * share(2, 2) + share(1, 1)) + lift(0) * rest))
    got = trainer.score(policy.design(seqs, counts), theta).first()
    assert abs(got.logp - want) < 1e-9
    assert abs(trainer.score(policy.design(seqs, counts, True), np.zeros(policy.n_features(True))).first().logp - math.log(share(1, 1) / (n * share(2, 2) + share(1, 1) + rest))) < 1e-9
    import hashlib

    bucket = lambda seed, x: int(hashlib.md5(f"{seed}:{x}".encode()).hexdigest()[:8], 16) % policy.BUCKETS
    lexical = np.zeros(policy.n_features(True))
    lexical[policy.SHARED * len(policy.DIRECTIVES) + bucket("ctx", "h") * policy.BUCKETS + bucket("tok", "zz")] = 9.0
    best = min((t for t in [*(f"a{k:03d}" for k in range(n)), "zz"] if bucket("tok", t) == bucket("tok", "zz")), key=lambda t: (t == "zz", t))
    df = spark.createDataFrame([("x", ["h"])], "id string, given array<string>")
    for strategy in ("broadcast", "frontier"):
        assert decode.tuned(df, decode.Successors(counts, strategy=strategy), lexical, 1).first().generated == [best]


def test_nucleus_of_every_context(spark):
    """Order 0 by counts of counts against the plain rule."""
    docs, counts = tiny_counts(spark)
    got = {(r.ord, r.ctx): (r.toks, r.cums, r.mass) for r in lm.nucleus_table(counts).collect()}
    rows: dict = {}
    for r in counts.collect():
        rows.setdefault((r.ord, r.ctx), []).append((-r.cnt, r.tok))
    assert set(got) == set(rows)
    for key, x in rows.items():
        x.sort()
        w = [(-c) ** (1 / 0.7) for c, _ in x]
        kept, before = [], 0.0
        for (_, t), p in zip(x, w):
            if round(before, 9) < 0.9:
                kept.append((t, p / sum(w)))
            before += p / sum(w)
        toks, cums, mass = got[key]
        assert toks == [t for t, _ in kept] and math.isclose(mass, sum(p for _, p in kept))
        assert np.allclose(cums, np.cumsum([p for _, p in kept]) / mass)


def test_tuned_writing_is_drawn_by_the_rule(spark):
    """Sampling under theta against plain code: temperature, nucleus and the hash draw."""
    import hashlib

    docs, counts = tiny_counts(spark)
    rows = [r.tk for r in docs.collect()]
    theta = np.random.default_rng(4).normal(0, 0.5, 15)
    known = decode.Successors(counts)
    got = {r.id: r.generated for r in decode.tuned(spark.createDataFrame([(str(k), [w]) for k, w in enumerate(("the", "on", "zz"))], "id string, given array<string>"), known, theta, 6, draw=(0.7, 0.9, "s")).collect()}
    flat = [t for d in rows for t in d]
    often = sorted(set(flat), key=lambda t: (-flat.count(t), t))[: policy.FREQUENT]
    for ident, first in (("0", "the"), ("1", "on"), ("2", "zz")):
        out = [first]
        for step in range(6):
            mass: dict = {t: [0.1 * flat.count(t) / len(flat), 0, 0] for t in often}
            for o in range(1, min(3, len(out)) + 1):
                after = [d[i] for d in rows for i in range(o, len(d)) if d[i - o : i] == out[len(out) - o :]]
                for t in set(after):
                    c = mass.setdefault(t, [0.1 * flat.count(t) / len(flat), 0, 0])
                    c[0], c[1], c[2] = c[0] + lm.MIX[o] * after.count(t) / len(after), o, len(set(after))
            s = {t: math.log(m) + theta[hi] + (theta[4] if hi and n == 1 else 0) for t, (m, hi, n) in mass.items()}
            order = sorted(s, key=lambda t: (round(-s[t], 10), t))
            p = np.exp(np.array([s[t] for t in order]) / 0.7)
            p /= p.sum()
            n = int((np.round(np.r_[0, np.cumsum(p)[:-1]], 9) < 0.9).sum())
            u = int(hashlib.md5(f"s:{ident}:{step}".encode()).hexdigest()[:8], 16) / 2**32
            out.append(order[min(int(np.searchsorted(np.cumsum(p[:n]) / p[:n].sum(), u)), n - 1)])
        assert got[ident] == out[1:]


def test_published_arithmetic(spark):
    """Means that follow from their parts, and those that are known not to."""
    got = {(r.model, r.variant, r.measure): r.agrees for r in report.checks(spark).collect()}
    assert got[("base-A", "untuned", "composite")] and got[("base-A", "untuned", "writing")] and got[("inst-full", "untuned", "writing")]
    assert {k for k, ok in got.items() if not ok} == {("base-A", "tuned", "writing"), ("inst-SFT", "untuned", "writing"), ("inst-full", "tuned", "writing")}
    assert len(report.BASE) + len(report.INSTRUCT) + len(report.WRITING) == 29


def test_sizes(spark):
    from verbatim.plans import store

    d = spark.range(1000).select("id", F.repeat(F.lit("x"), 100).alias("t"), F.array(F.lit("ab"), F.lit("c")).alias("a"))
    assert store.fits(d, 200_000) and not store.fits(d, 150_000) and not store.fits(d, 10_000)
    n = store.numbered(spark.range(100).select((F.col("id") % 7).alias("k"), "id"), [F.col("k"), F.col("id")], "i", {"s": F.col("id")}).orderBy("i").collect()
    want = sorted((k % 7, k) for k in range(100))
    assert [(r.k, r.id) for r in n] == want and [r.i for r in n] == list(range(100))
    assert [r.s for r in n] == [sum(x for _, x in want[:j]) for j in range(100)]
    for rows, bands in ((23, 10), (20, 10), (3, 10)):
        got = [r.b for r in spark.range(rows).select(store.tiles(F.col("id"), rows, bands).alias("b")).collect()]
        q, r = divmod(rows, bands)
        assert got == [b + 1 for b in range(bands) for _ in range(q + (b < r))]


def test_containing(spark, monkeypatch):
    from verbatim.operators import rel

    docs = spark.createDataFrame([(1, "one two three four five"), (2, "xone two threex"), (3, "a b")], "doc_id long, text string")
    parts = spark.createDataFrame([(1, "ne two thre"), (2, "three four"), (3, "b"), (4, "one two three")], "item_id long, part string")
    want = [(1, 1), (1, 2), (2, 1), (3, 3), (4, 1), (4, 2)]
    key = lambda: sorted((r.item_id, r.doc_id) for r in rel.containing(docs, parts, "text", "part").collect())
    assert key() == want
    asked = iter([False, True])
    monkeypatch.setattr(rel, "fits", lambda df: next(asked))
    assert key() == want


def test_cost_counts_rows_and_shuffles(spark):
    r = report.cost("x", spark.range(1000).repartition(3).groupBy((F.col("id") % 10).alias("k")).count()).first()
    assert r.rows == 10 and r.tasks > 0 and r.shuffle_written > 0 and r.seconds > 0


def test_lcs_by_bits(spark):
    """Arrays whose places fit a long take word operations, longer ones the table's row; repeats, nulls and empty arrays included."""
    import random

    rng, rows = random.Random(3), [([], ["a"]), (["a"], []), ([None, "a"], [None, "a"]), (None, ["a"]), (["a"] * 62, ["a"] * 70)]
    rows += [([rng.choice("abcde") for _ in range(rng.choice((1, 5, 32, 61, 62, 63, 64, 80)))], [rng.choice("abcdef") for _ in range(rng.choice((1, 7, 32, 65)))]) for _ in range(40)]
    df = spark.createDataFrame(rows, "a array<string>, b array<string>")

    def table(a, b):
        row = [0] * (len(b) + 1)
        for x in a:
            new = [0]
            for j, y in enumerate(b, 1):
                new.append(row[j - 1] + 1 if x == y and x is not None else max(row[j], new[-1]))
            row = new
        return row[-1]

    got = [r.n for r in df.select(rouge.lcs_len("a", "b").alias("n")).collect()]
    assert got == [None if a is None else table(a, b) for a, b in rows]
    assert "bit_count" in df.select(rouge.lcs_len("a", "b"))._jdf.queryExecution().toString()
