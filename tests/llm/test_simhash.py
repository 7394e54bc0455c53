"""SimHash near-dedup against brute force."""

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import functions as F

import recall
from verbatim.llm import simhash


def plain_fingerprint(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    for c in "\t\n\x0b\x0c\r":
        low = low.replace(c, " ")
    words = [w for w in low.split(" ") if w]
    if not words:
        return 0
    shingles = [" ".join(words[k : k + 4]) for k in range(len(words) - 3)] or [" ".join(words)]
    votes = [0] * 64
    for s in shingles:
        h = xxhash.xxh64_intdigest(s.encode(), 42)
        for b in range(64):
            votes[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * votes[b] > len(shingles))


def plain_components(ids, fps, radius=4):
    f = np.array(fps, dtype=np.uint64)
    near = np.bitwise_count(f[:, None] ^ f[None, :]) <= radius
    label = list(ids)
    while True:
        new = [min(label[j] for j in np.flatnonzero(near[i])) for i in range(len(label))]
        if new == label:
            return label
        label = new


def test_fingerprint():
    for text in (None, "", " \n ", "One", "a b c", "A b C d", "a b c d e f a b c d e f", "x\x0by\x0cz\tq  r", "É é words of Ünïcode, here"):
        assert simhash.fingerprint(text) == plain_fingerprint(text)


def test_table_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = simhash.op1_simhash(spark, sf).collect()
    want = {r.doc_id: plain_fingerprint(r.text) for r in docs.collect()}
    got = {r.doc_id: (int(r.fingerprint, 16), r.component_id) for r in rows}
    assert len(rows) == len(want)
    assert {k: v[0] for k, v in got.items()} == want
    ids = sorted(want)
    assert [got[i][1] for i in ids] == plain_components(ids, [want[i] for i in ids])


def test_long_runs_take_the_whole_ball(spark):
    rng = np.random.default_rng(3)
    centres = rng.integers(0, 1 << 63, 6, dtype=np.uint64)
    fps = set()
    for c in centres:
        for _ in range(60):
            x = int(c)
            for b in rng.choice(64, rng.integers(0, 7), replace=False):
                x ^= 1 << int(b)
            fps.add(x)
    fps = sorted(fps)
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    df = spark.createDataFrame([(i, f) for i, f in enumerate(signed)], "doc_id long, fp long")
    want = plain_components(range(len(fps)), fps)
    for most in (2, 5, 64):
        got = {r.doc_id: r.component_id for r in simhash.components(df, most=most).collect()}
        assert [got[i] for i in range(len(fps))] == want


def test_odd_rows(spark):
    rows = [(3, None), (5, ""), (None, "some words are here today"), (7, "some words are here today"), (7, "some words are here today"), (9, "x " * 60000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS fp", "'z' AS component_id")
    out = simhash.components(simhash.fingerprints(df))
    got = sorted(((r.doc_id or -1, r.component_id) for r in out.collect()))
    assert got == [(-1, 7), (3, 3), (5, 3), (7, 7), (7, 7), (9, 9)]
    kept = sorted((r.doc_id or -1) for r in simhash.deduplicate(df).collect())
    assert kept == [-1, 3, 7, 9]
    assert simhash.components(simhash.fingerprints(df.limit(0))).count() == 0


def spread_edits(words, at, tag):
    """A copy of `words` with other words at the places `at`; each changes five shingles."""
    return [f"{tag}{k}" if k in at else w for k, w in enumerate(words)]


def plain_like(a, b):
    x, y = ({tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for w in (a.lower().split(), b.lower().split()))
    return len(x & y) / len(x | y)


def test_less_than_likeness_stays(spark):
    base = [f"w{k}" for k in range(400)]
    rows = [(1, " ".join(base)), (2, " ".join(spread_edits(base, range(20, 380, 24), "x"))), (3, " ".join(spread_edits(base, range(10, 390, 60), "y")))]
    assert 0.6 < plain_like(rows[0][1], rows[1][1]) < 0.8 <= plain_like(rows[0][1], rows[2][1])
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(r.doc_id for r in simhash.deduplicate(df).collect()) == [1, 2]


def test_every_group_of_a_component_is_deduplicated(spark):
    """Texts over one vocabulary meet in a component; near copies of each of its groups go, also where the smallest text is unlike them."""
    rng = np.random.default_rng(5)
    base = [f"w{k}" for k in range(300)]
    rows = []
    for g in range(6):  # the same words in another order: equal word fingerprints, unlike shingles
        words = base if g == 0 else [base[k] for k in rng.permutation(300)]
        rows += [(10 * g + c, " ".join(spread_edits(words, range(30 + 7 * c, 290, 120), f"e{g}{c}x") if c else words)) for c in range(4)]
    # a chain of edits: each text is like the next one, the far end is unlike the first
    for c in range(24):
        rows.append((100 + c, " ".join(f"c{k}" if k >= 8 * c else f"d{k}" for k in range(400))))
    text = dict(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    kept = sorted(r.doc_id for r in simhash.deduplicate(df).collect())
    assert [k for k in kept if k < 100] == [0, 10, 20, 30, 40, 50]
    assert plain_like(text[100], text[123]) < 0.6
    for k in text:
        smaller = [plain_like(text[k], text[j]) for j in text if j < k]
        assert max((plain_like(text[k], text[j]) for j in kept if j < k), default=0) < 0.8 if k in kept else max(smaller) >= 0.8


def test_texts_that_share_an_id(spark):
    w = lambda tag: [f"{tag}{k}" for k in range(200)]
    near = " ".join(spread_edits(w("a"), [100], "x"))
    rows = [(1, " ".join(w("a"))), (2, near), (2, " ".join(w("b"))), (3, " ".join(w("c"))), (3, " ".join(w("d"))), (3, " ".join(w("d"))), (4, " ".join(w("d")))]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("h1", F.lit("own"))
    out = simhash.deduplicate(df)
    assert out.columns == df.columns
    assert sorted((r.doc_id, r.text, r.h1) for r in out.collect()) == sorted((*rows[k], "own") for k in (0, 2, 3, 4))


def test_recall_of_the_stage(spark, sf):
    """Of all pairs that are 0.8 alike, between the given texts and edited ones, at most a tenth is kept whole; nothing goes that is like no other."""
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    edited = [(1_000_000 + d, " ".join(spread_edits(t.split(), range(30, len(t.split()), 60), f"e{d}x"))) for d, t in rows if len((t or "").split()) >= 100]
    found = recall.measured(spark, spark.createDataFrame(rows + edited, "doc_id long, text string"))
    assert found["0.8"]["pairs"] >= 60
    assert found["0.8"]["stage"] >= 0.9
    assert found["gone without a like text"] == 0


def test_kinds_shuffle_one_after_another(spark, monkeypatch):
    """The variants of one kind of fingerprint at a time are in shuffle files; links are those of each kind alone."""
    seen = []
    cut = simhash.C.cut
    monkeypatch.setattr(simhash.C, "cut", lambda df: seen.append(df.count()) or cut(df))
    rows = [(1, 0), (3, 0), (1 << 40, 0), (1 << 62, 1), ((1 << 62) + 7, 1), (-1, 1), (2, 1)]
    got = {frozenset((r.a, r.b)) for r in simhash.links(spark.createDataFrame(rows, "fp long, k int")).collect()}
    # 1, 3 and 1 << 40 are near each other; of the second kind -1 is near none, and 2 is near the other two but not near a 1
    assert len(seen) == 2
    parts = []
    for e in got:
        near = [p for p in parts if p & e]
        parts = [p for p in parts if not p & e] + [e.union(*near)]
    assert sorted(map(sorted, parts)) == [[1, 3, 1 << 40], [2, 1 << 62, (1 << 62) + 7]]


def test_labels_leave_few_links():
    """A run links labels, not their members; members of one label need none, and what a run is too long for is still marked by fingerprint."""
    frame = lambda rows: iter([pd.DataFrame(rows, columns=["key", "fp", "own"])])
    group = [(1, 16 + k, 16) for k in range(4)]
    links_of = lambda rows, most=9: sorted({tuple(map(int, x)) for part in simhash._runs(frame(rows), 4, most) for x in part})
    assert links_of(group) == []
    assert links_of([*group, (1, 20, 20), (1, 21, 20)]) == [(20, 16)]
    assert links_of([(2, 5, 5), (2, 7, 5), (3, 5, 5), (3, 13, 13)]) == [(13, 5)]
    assert links_of(group, 2) == [(16 + k, 16 + k) for k in range(4)]


def test_labelled_kinds_join_what_all_pairs_join(spark):
    rng = np.random.default_rng(11)
    fps = {7, 0x0F0F << 20, (0x0F0F << 20) ^ 3, (0x0F0F << 20) ^ (3 << 40)}
    for _ in range(200):
        fps.add(0x8123456789ABCDEF ^ sum(1 << int(b) for b in rng.choice(range(0, 64, 3), rng.integers(0, 6), replace=False)))
    fps = sorted(fps)
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    label = {f: f for f in signed}

    def top(x):
        while label[x] != x:
            x = label[x]
        return x

    for r in simhash.links(spark.createDataFrame([(f, 0) for f in signed], "fp long, k int")).collect():
        label[top(r.a)] = top(r.b)
    groups = lambda names: {frozenset(f for f, m in zip(signed, names) if m == n) for n in names}
    assert groups([top(f) for f in signed]) == groups(plain_components(range(len(fps)), fps))
