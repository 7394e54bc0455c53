"""Every query with an oracle against DuckDB on the smallest tables."""

import math
import os

import duckdb
import pytest

import __spark_entry__ as entry
from verbatim.queries import ORACLES, QUERIES


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else repr(round(v, 6) + 0.0)
    return str([plain(x) for x in v]) if isinstance(v, (list, tuple)) else str(v)


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{sf}/{f}'")
    return c


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, sf, con, name):
    df = QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted(tuple(plain(r[c]) for c in cols) for r in df.collect())
    cur = con.execute(ORACLES[name])
    names = [x[0] for x in cur.description]
    assert sorted(names) == cols
    at = [names.index(c) for c in cols]
    assert got == sorted(tuple(plain(r[k]) for k in at) for r in cur.fetchall())


@pytest.mark.parametrize("name", ["decode_nucleus", "cat_train", "cat_train_lowrank", "nll_shift_tuned", "cost_counters"])
def test_runs(spark, sf, name):
    assert QUERIES[name](spark, sf).count() > 0


COLUMNS = {"web", "book", "writing", "knowledge", "math", "reasoning", "composite", "quote", "passage", "constraints", "win_rate"}


def test_arms_are_all_there(spark, sf):
    """Every arm with every column, from the model that it starts from."""
    from verbatim.operators import experiments as X
    from verbatim.queries.tuning import material

    rows = QUERIES["arms_instruct"](spark, sf).collect()
    assert {(r.model, r.variant, r.directive) for r in rows} == set(X.INSTRUCT_ARMS)
    for arm in X.INSTRUCT_ARMS:
        assert {r.metric for r in rows if (r.model, r.variant, r.directive) == arm} == COLUMNS
    value = {(r.model, r.variant, r.metric): r.value for r in rows if not r.directive}
    assert value[("base", "untuned", "win_rate")] == 50.0  # against itself
    m = material(spark, sf)
    want = {r.metric: r.value for r in QUERIES["untuned_report"](spark, sf).collect()}
    assert {k: value[("base", "untuned", k)] for k in want} == want
    # each arm's first loss is that of no change, whatever it starts from
    for arm in ("tuned", "tuned, random segments", "tuned, directive", "tuned, mix", "tuned, directive and mix"):
        assert math.isclose(X.tune(m, arm, "full")[1][0], math.log(2), abs_tol=1e-9)
    full, sup = X.start_of(m, "full").theta, X.start_of(m, "supervised").theta
    assert sup.any() and not (full == sup).all()


def test_creativity_has_every_cell(spark, sf):
    rows = QUERIES["creativity_table"](spark, sf).collect()
    assert {(r.model, r.stage, r.task) for r in rows} == {(m, s, t) for m in ("base", "supervised", "full") for s in ("before", "after") for t in ("story", "poem", "speech")}
    change = QUERIES["creativity_change"](spark, sf).collect()
    assert {(r.model, r.n) for r in change} == {(m, n) for m in ("base", "supervised", "full") for n in range(5, 12)}


def test_seeds_and_sweep(spark, sf):
    """Two seeds and one share stand for five and four here; the forms are the same."""
    from verbatim.operators import experiments as X
    from verbatim.queries.tuning import material

    rows = X.seeds({k: material(spark, sf, seed=k) for k in (1, 2)}).collect()
    assert {(r.variant, r.metric, r.runs) for r in rows} == {(v, m, 2) for v in ("tuned", "tuned, random segments") for m in ("web", "book", "writing")}
    sweep = X.tradeoff(material(spark, sf), (0.9,)).collect()
    assert {(r["mode"], r.share) for r in sweep} == {("full", 0.9), ("lowrank", 0.9)} and {r.metric for r in sweep} == COLUMNS


def test_tuning_uses_seen_documents_only(spark, sf):
    from verbatim.operators import sampling
    from verbatim.queries import paper
    from verbatim.queries.tuning import material

    held = {r.doc_id for r in sampling.split(paper.docs(spark, sf)).where("part = 'held'").collect()}
    m = material(spark, sf)
    for df in (paper.chosen(spark, sf), m.pairs, m.random_pairs):
        assert df.count() and not held & {r.doc_id for r in df.collect()}
    for df in (m.forget, m.retain, m.web, m.book):
        assert not held & {int(r.seg_id.split("-")[0]) for r in df.collect()}


def test_fit_against_plain_descent(spark, sf):
    """Losses of three steps of every objective, recomputed from the design with slopes by finite differences."""
    import numpy as np

    from verbatim.operators import experiments as X
    from verbatim.operators import trainer
    from verbatim.queries import tuning

    m = tuning.material(spark, sf)
    for arm in ("tuned", "gradient ascent", "negative preference", "next token on rewrites"):
        data, objective = tuning._data(m, arm)
        parts = [[(x["role"], x["positions"]) for x in r["parts"]] for r in data.limit(6).collect()]
        local = data.sparkSession.createDataFrame(data.limit(6).collect(), data.schema)

        def loss(t, parts=parts, objective=objective):
            def logp(positions, w):
                total = 0.0
                for p in positions:
                    s = [b + sum(w[f] for f in fs) for b, fs in zip(p["logp"], p["feats"])]
                    top = max(s)
                    total += s[p["target"]] - top - math.log(sum(math.exp(x - top) for x in s))
                return total

            return sum(objective.terms({r: (logp(p, t), logp(p, np.zeros(len(t)))) for r, p in item})[0] for item in parts) / len(parts)

        theta, want = np.zeros(15), []
        for _ in range(3):
            want.append(loss(theta))
            g = np.zeros(15)
            for k in range(5):
                e = np.zeros(15)
                e[k] = 1e-5
                g[k] = (loss(theta + e) - loss(theta - e)) / 2e-5
            theta = np.clip(theta - X.RATE * g, -X.CLIP, X.CLIP)
        _, got = trainer.fit(local, objective, X.start_of(m, "base"), X.RATE, 3, tol=0, clip=X.CLIP)
        assert np.allclose(got, want, rtol=1e-4, atol=1e-4), arm


def test_entry(spark):
    assert entry.entry(spark).count() == 2
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_generic_pairs_are_whole_turns(spark, sf):
    from verbatim.operators import pairs
    from verbatim.queries.tuning import material

    got = {r.pair_id: (r.chosen, r.rejected) for r in material(spark, sf).generic.collect()}
    want = {r.pair_id: (r.chosen, r.rejected) for r in pairs.generic(spark.read.parquet(f"{sf}/conversations.parquet")).collect()}
    assert got and all(want[k] == v for k, v in got.items()) and max(len(a) for a, _ in got.values()) > 32
