"""Line dedup, vectors, SpotSigs, toxicity and the pipeline: brute force, held-out accuracy and odd rows."""

import hashlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from verbatim.llm import linededup, queries, spotsigs, toxicity, vectors


def plain(v):
    return repr(round(v, 6) + 0.0) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_oracles(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "labels", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df = queries.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    cur = con.execute(queries.ORACLES[name])
    at = [[x[0] for x in cur.description].index(c) for c in cols]
    assert sorted(tuple(plain(r[c]) for c in cols) for r in df.collect()) == sorted(tuple(plain(r[k]) for k in at) for r in cur.fetchall())


def lines(*words):
    return "\n".join(f"l{w} " + " ".join(f"w{w}{k}" for k in range(9)) for w in words)


def test_line_runs(spark):
    shared, alone = lines(1, 2, 3, 4), lines(5)
    rows = [
        (1, f"start one\n{shared}\n\nend one"), (2, f"start two\n{shared}\nend two"), (3, f"x\n{alone}\ny"), (4, f"p\n{alone}\nq"),
        (5, lines(2, 3, 4) + "\nrest"), (6, None), (7, ""), (None, shared), (8, shared), (8, shared), (9, "z\n" * 20_000),
    ]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("gone", F.lit("x"))
    out = linededup.deduplicate(df).collect()
    got = {r.doc_id: r.text for r in out if r.doc_id != 9}
    # the row without an id comes first in order; ten words a line, forty for a run
    assert got == {None: shared, 1: "start one\n\nend one", 2: "start two\nend two", 3: rows[2][1], 4: rows[3][1], 5: rows[4][1], 6: None, 7: "", 8: ""}
    assert sum(r.doc_id == 8 for r in out) == 2 and len(out) == len(rows)
    assert [r.text.count("z") for r in out if r.doc_id == 9] == [1]  # every later window overlaps an earlier one
    assert linededup.deduplicate(df.select("doc_id", "text").limit(0)).count() == 0


def test_vectors(spark):
    rng = np.random.default_rng(1)
    base = rng.normal(size=(30, 16))
    rows = [(k, [float(x) for x in base[k % 30] + rng.normal(size=16) * 0.12 * (k % 5)], k % 3) for k in range(400)]
    rows += [(400, None, 1), (401, [0.0] * 16, 1), (402, [float("nan")] * 16, 1), (403, [1.0] * 16, None), (404, [None] * 16, 1), (405, [], 1), (406, [1.0, 2.0], 1), (407, [2.0, 4.0], 1), (408, rows[0][1], 0), (409, rows[0][1], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").selectExpr("*", *[f"'x' AS {c}" for c in ("_n", "_e", "_t", "_v", "_d", "_pc", "_rep")])
    ok = {r[0]: (np.array(r[1], dtype=np.float32).astype(float), r[2]) for r in rows if r[1] and r[2] is not None and None not in r[1] and np.isfinite(r[1]).all() and np.any(r[1])}
    links = {k: set() for k in (r[0] for r in rows)}
    for a, (x, la) in ok.items():
        for b, (y, lb) in ok.items():
            if a != b and la == lb and len(x) == len(y) and x @ y / np.sqrt((x @ x) * (y @ y)) >= 0.93:
                links[a].add(b)
    label = {k: k for k in links}
    for _ in range(50):
        label = {k: min([label[k], *[label[j] for j in v]]) for k, v in links.items()}
    for tile in (7, 64, 1024):
        got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in vectors.components(df, tile=tile).collect()}
        assert got == {k: (len(links[k]), label[k], label[k] == k) for k in links}
    assert vectors.components(df.limit(0)).count() == 0


def test_spotsigs(spark):
    rows = [(1, "the cat sat on the mat and the dog ran to a tree"), (2, "the cat sat on the mat and the dog ran to a tree"), (3, None), (4, ""), (5, "word"), (6, "der Hund und die Katze " * 5000), (None, "the moon is far away from here")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("_own", F.lit(1))
    got = {r.doc_id: r for r in spotsigs.compare_edited(df).collect()}
    order = [6, 5, 4, 3, 2, 1, None]
    text = {k: t or "" for k, t in rows}
    for k, n in zip(order, order[1:] + order[:1]):
        half = len(text[k]) // 2
        edited = text[k][: len(text[k]) - half] + text[n][:half]
        assert got[k].edited_sha256 == hashlib.sha256(edited.encode()).hexdigest() and got[k].n_chars == len(text[k])
        assert 0 <= got[k].near_edited <= 1 and 0 <= got[k].near_next <= 1
    assert got[1].fingerprint == got[2].fingerprint and got[2].near_next == 1 and got[4].near_next == 1
    assert spotsigs.compare_edited(df.limit(0)).count() == 0
    lone = spotsigs.compare_edited(df.where("doc_id = 1")).first()
    assert lone.near_next == 1


def plain_op9(docs):
    """(n_chars, edited_sha256, near_edited, near_next) of rows (doc_id, text) by plain code over the sets of `with_signatures` rewritten in Python."""
    import re

    anchors = set(spotsigs.ANCHORS)

    def sigs(text):
        every = ["^", *re.sub(r"[^\w]|_", " ", text.lower()).split(), "$", "$", "$"]
        bare = [x for x in every if x not in anchors and x != "^"]
        out, i, before = set(), 0, None
        for x in every:
            if x in anchors or x == "^":
                before = x
                continue
            if before is not None:  # the nearest common word, and three content words from here
                out.add((before, *bare[i : i + 3]))
            before, i = None, i + 1
        return frozenset(out)

    like = lambda a, b: len(a & b) / len(a | b)
    rows = sorted(docs, reverse=True)
    out = {}
    for k, (i, text) in enumerate(rows):
        nxt = rows[(k + 1) % len(rows)][1]
        half = len(text) // 2
        edited = text[: len(text) - half] + nxt[:half]
        out[i] = (len(text), hashlib.sha256(edited.encode()).hexdigest(), round(like(sigs(text), sigs(edited)), 9), round(like(sigs(text), sigs(nxt)), 9))
    return out, {i: sigs(t) for i, t in docs}


def test_spotsigs_whole_table(spark, sf):
    """The query against plain code, and its components against all pairs."""
    docs = [(r.doc_id, r.text or "") for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    want, sets = plain_op9(docs)
    rows = spotsigs.op9_spotsigs(spark, sf).collect()
    got = {r.doc_id: (r.n_chars, r.edited_sha256, round(r.near_edited, 9), round(r.near_next, 9)) for r in rows}
    assert len(rows) == len(docs) and got == want
    prints = {r.doc_id: r.fingerprint for r in rows}
    assert all((prints[a] == prints[b]) == (sets[a] == sets[b]) for a in sets for b in sets)
    groups = spotsigs.spotsigs_groups(spark, sf).collect()
    assert {r.doc_id: r.component_id for r in groups} == plain_groups(sets, 0.8) and len(groups) == len(docs)
    assert {r.doc_id: r.class_id for r in groups} == {a: min(b for b in sets if sets[b] == sets[a]) for a in sets}


def plain_groups(sets, least):
    label = {k: k for k in sets}
    near = {a: [b for b in sets if len(sets[a] & sets[b]) >= least * len(sets[a] | sets[b]) - 1e-12] for a in sets}
    while True:
        new = {k: min(label[j] for j in v) for k, v in near.items()}
        if new == label:
            return label
        label = new


def test_spotsigs_groups_of_any_size(spark):
    """A large group of near copies, a chain, a passage that many texts share and texts with little else: long lists go through rounds and through all pairs, with equal results."""
    rng = np.random.default_rng(7)
    base = [f"the w{k}x in y{k}" for k in range(40)]
    rows = []
    for c in range(60):  # near copies
        rows.append(" ".join(p if rng.random() > 0.06 else f"the e{c}q{k} in z{c}" for k, p in enumerate(base)))
    for c in range(25):  # a chain
        rows.append(" ".join(f"the c{k} of d{k}" if k >= c else f"the f{k} of g{k}" for k in range(30)))
    shared = " ".join(f"for s{k} and t{k}" for k in range(6))
    for c in range(40):  # a shared passage
        rows.append(shared + " " + " ".join(f"the own{c}n{k} is o{k}" for k in range(c % 5)))
    rows += ["", "word", "the", "the", rows[0]]
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    sets = {k: s for k, s in plain_op9(list(enumerate(rows)))[1].items()}
    ids = {r.doc_id: r._f for r in spotsigs.with_signatures(df, "text", "_s").select("doc_id", spotsigs.fingerprint(F.col("_s")).alias("_f")).collect()}
    want = plain_groups(sets, 0.8)
    got = {r._f: (r.class_id, r.component_id) for r in spotsigs.near_groups(df, 0.8, 2, 1, 4, 1).collect()}
    assert {k: got[f][1] for k, f in ids.items()} == want
    assert all(got[f][0] == min(j for j, g in ids.items() if g == f) for f in ids.values())


def test_spotsigs_many_rows_of_an_id(spark):
    """Null ids, ids that repeat and equal rows, dealt in split blocks: as one sorted list would have them."""
    rng = np.random.default_rng(3)
    text = lambda: " ".join(rng.choice(["the", "cat", "of", "dog", "runs", "by", "house", "tree"], 12))
    rows = [(None, text()) for _ in range(40)] + [(7, text()) for _ in range(30)] + [(k, text()) for k in range(600, 640)] + [(None, "the same cat of the house")] * 25 + [(7, "the same dog of the tree")] * 20
    df = spark.createDataFrame(rows, "doc_id long, text string")
    key = lambda r: tuple(repr(x) for x in (r.doc_id, r.n_chars, r.edited_sha256, r.fingerprint, r.near_edited, r.near_next))
    whole = sorted(map(key, spotsigs.compare_edited(df).collect()))
    assert len(whole) == len(rows)
    for heavy, many in ((8, 5), (16, 1000)):
        assert sorted(map(key, spotsigs.compare_edited(df, heavy, many).collect())) == whole


def test_spotsigs_links(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    members, links = spotsigs.near_duplicates(docs, 0.5)
    got = {(r.a, r.b) for r in links.collect()}
    reps = {r.class_id for r in members.collect()}
    sets = {r.doc_id: set(r.s) for r in spotsigs.with_signatures(docs, "text", "s").collect() if r.doc_id in reps}
    ids = sorted(sets)
    assert got == {(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if len(sets[a] & sets[b]) >= 0.5 * len(sets[a] | sets[b])}


def test_restoring():
    counts = np.zeros((toxicity.N,) * 3)
    for word in ("idiot", "hello", "stupid", "worthless", "good", "book", "trash"):
        c = [0, 0, *toxicity.codes(word), 0]
        for a, b, d in zip(c, c[1:], c[2:]):
            counts[a, b, d] += 50
    words = toxicity.restorer(toxicity.LanguageModel(counts))
    for text, word in (("an 1d10t", "idiot"), ("i d i o t", "idiot"), ("i.d.i.o.t", "idiot"), ("stuuuupid", "stupid"), ("w0rthle$$", "worthless"), ("tr@sh!", "trash"), ("goood", "good")):
        assert word in words(text), text
    assert words("hello good book") == {"hello", "good", "book"}
    assert words("") == set() and words("12 !! -- 3.5") == set()
    words("a1" * 50_000)
    # whole tokens, however long, and whole spaced stretches
    assert "idiot" in words("x" + "z" * 300 + " 1d10t")
    far = "-".join(["good"] * 40) + "-1d10t"
    assert "idiot" in words(far)
    assert max(map(len, toxicity.suspects(" ".join("abcdefgh" * 20)))) == 319


def test_toxicity_held_out(spark):
    sf = "/root/testdata/sf0.01"
    out = toxicity.op10_toxicity(spark, sf)
    d = out.join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").collect()
    hit = sum(r.predicted and r.toxic for r in d)
    assert hit >= 0.6 * sum(r.toxic for r in d) and sum(r.predicted and not r.toxic for r in d) <= 2
    assert out.where("score < 0 or score > 1 or score is null").count() == 0


def test_toxicity_odd_rows(spark):
    rows = [(k, t, "x") for k, t in enumerate([None, "", "idiot scum", "fine words", "i d i o t", "a" * 200_000, "@" * 5000])] + [(None, "no id", "x"), (2, "idiot scum", "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score string").drop("score")
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {r.score for r in toxicity.score(docs, none).collect()} == {0.0}
    labels = spark.createDataFrame([(0, 1, 0), (2, 1, 1), (3, None, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    assert toxicity.score(docs, labels).where("score between 0 and 1").count() == len(rows)
    assert toxicity.score(docs.limit(0), labels).count() == 0


def test_extra_columns_that_clash(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(40)
    names = ["_h", "_k", "_b", "gone", "_id", "n_removed", "_toxicity", "score", "_copies", "_x", "_r", "__index_p", "with.dot", "shard", "fp", "component_id"]
    wide = spark.createDataFrame([(*r, *[f"{n}{r.doc_id}" for n in names]) for r in docs.collect()], docs.columns + names)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, wide, sf)
        assert out.columns == wide.columns
        for r in out.collect():
            assert all(r[n] == f"{n}{r.doc_id}" for n in names)
    assert corpus_pipeline.to_ids(spark, wide, sf).count() == 40


def test_pipeline_against_the_parts(spark, sf):
    """Each stage's decision recomputed plainly from its own input."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    names = docs.columns
    clean = corpus_pipeline.clean(spark, docs, sf)
    assert clean.columns == names
    kept = {r.doc_id for r in clean.collect()}
    score = {r.doc_id: r.score for r in toxicity.op10_toxicity(spark, sf).collect()}
    assert kept == {k for k, s in score.items() if s < toxicity.THRESHOLD}
    clean = spark.createDataFrame(clean.collect(), docs.schema)
    cut = corpus_pipeline.without_repeated_lines(spark, clean, sf)
    assert cut.columns == names and cut.count() == len(kept)
    assert all(r.n_chars == len(r.text) and (r.text == texts[r.doc_id] or r.n_chars < len(texts[r.doc_id])) for r in cut.collect())
    cut = spark.createDataFrame(cut.collect(), docs.schema)
    from verbatim.llm import bpe, mixing, simhash

    one = corpus_pipeline.without_copies(spark, cut, sf)
    got = {r.doc_id for r in one.collect()}
    assert one.columns == names
    left = {r.doc_id: r.text for r in cut.collect()}
    shingles = {k: {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} for k, w in ((k, t.lower().split()) for k, t in left.items())}
    like = lambda a, b: len(shingles[a] & shingles[b]) / len(shingles[a] | shingles[b])
    for k in left:
        # what goes is 0.8 or more like a smaller text, itself kept or gone for a smaller one; what stays is like none that stays
        nearest = max((like(k, j) for j in (got if k in got else left) if j < k), default=0)
        assert nearest < 0.8 if k in got else nearest >= 0.8
    one = spark.createDataFrame(one.collect(), docs.schema)
    mixed = corpus_pipeline.to_weights(spark, one, sf)
    assert mixed.columns == names
    want = {r.doc_id: r._copies for r in mixing.mix(one, mixing.quality_weights(spark.read.parquet(f"{sf}/labels.parquet"))).collect()}
    count = {r.doc_id: r["count"] for r in mixed.groupBy("doc_id").count().collect()}
    assert count == {k: v for k, v in want.items() if v}
    ids = corpus_pipeline.to_ids(spark, spark.createDataFrame(mixed.collect(), docs.schema), sf)
    assert all(r.decoded_sha256 == hashlib.sha256(b).hexdigest() for r, b in ((r, bytes(r.bytes)) for r in bpe.decode(ids).collect()))
    assert corpus_pipeline.run(spark, sf).count() == sum(want.values())
