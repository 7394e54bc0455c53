"""What the plans must look like, and streams against plain code."""

import os

import pytest
from pyspark.sql import functions as F

from verbatim.operators import decode, lm, paraphrase, segments
from verbatim.plans import store
from verbatim.queries import QUERIES, paper
from verbatim.sources import tables
from verbatim.streaming import monitor


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_filters_and_columns_reach_the_scan(spark, sf):
    p = plan(QUERIES["scan_documents"](spark, sf))
    assert "EqualTo(lang,fr)" in p and "GreaterThan(n_chars,1000)" in p and "text" not in p.split("ReadSchema")[1]


def test_top_k_does_not_sort_the_table(spark, sf):
    p = plan(QUERIES["sample_docs"](spark, sf))
    assert "TakeOrderedAndProject" in p and "Exchange rangepartitioning" not in p


def test_measures_stay_in_the_jvm(spark, sf):
    assert "Python" not in plan(QUERIES["overlap_scan"](spark, sf)) and "Python" not in plan(QUERIES["contaminated_docs"](spark, sf))


def test_formats_round_trip(spark, sf, tmp_path):
    d = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").limit(20)
    want = sorted(map(tuple, d.collect()))
    for fmt in ("parquet", "orc", "json"):
        tables.write_report(d, str(tmp_path / fmt), fmt)
        assert sorted(map(tuple, tables.read_corpus(spark, str(tmp_path / fmt), fmt, d.schema).collect())) == want
    spark.dataSource.register(tables.GenerationEndpoint)
    assert spark.read.format("generations").option("rows", "5").load().count() == 5


SCHEMA = "conv_id long, turn long, role string, text string"


def plain_copies(rows, index, n):
    said: dict = {}
    for conv, turn, _, text in rows:
        said.setdefault(conv, {}).setdefault(turn, text)
    out = {}
    for conv, turns in said.items():
        w = [x for t in sorted(turns) for x in (turns[t] or "").split()]
        out[conv] = (len(turns), sum(" ".join(w[k : k + n]) in index for k in range(len(w) - n + 1)))
    return out


def test_state_crosses_chunks_in_any_order(spark, tmp_path):
    """Chunks in every order over many files, one a batch; gaps that fill later, short and empty chunks, a turn that comes twice."""
    rows = [(1, 0, "a", "one two three"), (1, 1, "a", "four five six"), (1, 2, "a", "seven"), (1, 3, "a", None), (1, 4, "a", "eight nine"), (2, 0, "a", "three four"), (2, 7, "a", "five six seven")]
    index = {"two three four", "four five six", "six seven eight", "seven eight nine", "three four five", "six seven five"}
    for k, order in enumerate(([0, 1, 2, 3, 4, 5, 6], [6, 4, 2, 0, 5, 3, 1, 0], [1, 3, 5, 0, 2, 4, 6, 6])):
        at = tmp_path / f"in{k}"
        for j, i in enumerate(order):
            spark.createDataFrame([rows[i]], SCHEMA).coalesce(1).write.parquet(str(at / f"f{j}"))
        for j in range(len(order)):  # files in the order of arrival
            for f in sorted((at / f"f{j}").glob("*.parquet")):
                f.rename(at / f"p{j}.parquet")
                os.utime(at / f"p{j}.parquet", (1_700_000_000 + j, 1_700_000_000 + j))
        read = lambda at=at: monitor.read_stream(spark, str(at), SCHEMA, glob="p*.parquet")
        out = monitor.drain(monitor.carry_over(read(), index, n=3, ttl_ms=None), "update")
        got = {r.conv_id: (r.chunks, r.copied) for r in out.groupBy("conv_id").agg(F.max("chunks").alias("chunks"), F.max_by("copied", "chunks").alias("copied")).collect()}
        assert got == plain_copies(rows, index, 3)
        if k != 1:
            continue
        have = spark.createDataFrame([(g,) for g in index], "gram string")
        assert {r.conv_id: (r.chunks, r.copied) for r in monitor.drain_joined(monitor.carried_grams(read(), 3), have).collect()} == got


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    for j, minute in enumerate((0, 60, 59, 1)):
        spark.sql(f"SELECT timestamp_seconds(1700000000 + {minute} * 60) AS ts, 1D AS value").coalesce(1).write.parquet(str(tmp_path / f"f{j}"))
        for f in (tmp_path / f"f{j}").glob("*.parquet"):
            f.rename(tmp_path / f"p{j}.parquet")
            os.utime(tmp_path / f"p{j}.parquet", (1_700_000_000 + j, 1_700_000_000 + j))
    s = monitor.read_stream(spark, str(tmp_path), "ts timestamp, value double", glob="p*.parquet")
    q = monitor.tumbling(s, "ts", "5 minutes", "10 minutes").writeStream.format("noop").outputMode("update").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert monitor.dropped_late(q.recentProgress) == 1


def test_no_plan_deals_order_0_by_context(spark, sf):
    """No window without partitions anywhere, and contexts are dealt by (ord, ctx) beyond order 0 only."""
    from verbatim.operators import decode, lm, policy
    from verbatim.queries import paper

    c = paper.counts(spark, sf)
    seqs = spark.createDataFrame([("s", None, ["the"], ["a"])], "seq_id string, directive string, given array<string>, text array<string>")
    bands = QUERIES["nll_shift_bands"](spark, sf)
    plans = [plan(lm.nucleus_table(c)), plan(policy.design(seqs, c)), plan(decode.successor_table(c, lm.MIX, 4)), plan(lm.sequence_nll(seqs, c, "seq_id", "given", "text")), plan(bands)]
    for p in plans:
        assert "SinglePartition" not in "".join(line for line in p.splitlines() if "Window" in line) and "windowspecdefinition(cnt" not in p
    for p in plans[1:4]:
        assert "Window" not in p


def test_frontier_leaves_the_table_in_its_buckets(spark):
    from verbatim.operators import decode

    table = decode.bucketed(spark.range(1000).select(F.col("id").cast("string").alias("ctx"), F.col("id").alias("say")), "ctx")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        p = plan(spark.range(5000).select(F.col("id").cast("string").alias("ctx")).join(table, "ctx"))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert p.count("Exchange hashpartitioning") == 1 and "Bucketed: true" in p


def test_stages_are_made_anew_when_tables_change(spark, tmp_path):
    from verbatim.plans import store

    spark.range(3).write.parquet(str(tmp_path / "t.parquet"))
    read = lambda: store.shared(("n", str(tmp_path)), spark, lambda: spark.read.parquet(str(tmp_path / "t.parquet"))).count()
    assert read() == 3 and read() == 3
    spark.range(5).write.mode("overwrite").parquet(str(tmp_path / "t.parquet"))
    assert read() == 5


def test_streams_read_tables_in_folders(spark, sf, tmp_path):
    """Each streamed query over tables of several files, the latest conversations first: equal to the tables of one file each."""
    for name in ("conversations", "events", "benchmark"):
        t = spark.read.parquet(f"{sf}/{name}.parquet")
        for j in range(3) if name == "conversations" else range(1):
            part = t.where(F.pmod("conv_id", F.lit(3)) == 2 - j) if name == "conversations" else t
            part.coalesce(1).write.parquet(str(tmp_path / "raw" / name / str(j)))
            for f in (tmp_path / "raw" / name / str(j)).glob("*.parquet"):
                to = tmp_path / f"{name}.parquet" / f"part-{j}.parquet"
                to.parent.mkdir(exist_ok=True)
                f.rename(to)
                os.utime(to, (1_700_000_000 + j, 1_700_000_000 + j))
    for name in ("stream_copy_monitor", "stream_prompt_join", "stream_copied_outputs", "tumbling_stream", "dedup_stream"):
        want = sorted(map(tuple, QUERIES[name](spark, sf).collect()))
        assert (want or name == "stream_copied_outputs") and sorted(map(tuple, QUERIES[name](spark, str(tmp_path)).collect())) == want, name


def test_stages_lie_in_compressed_files(spark, tmp_path):
    """A shared stage takes a fraction of the bytes of a checkpoint, and `drop` deletes its files."""
    from verbatim.plans import store

    spark.range(2).write.parquet(str(tmp_path / "t.parquet"))
    big = spark.range(20_000).select(F.array(*[F.concat(F.lit("word"), (F.col("id") % (7 + k)).cast("string")) for k in range(8)]).alias("tk"), "id")
    out = store.shared(("bytes", str(tmp_path)), spark, lambda: big)
    at = {f.removeprefix("file://").rsplit("/", 1)[0] for f in out.inputFiles()}
    assert len(at) == 1 and sum(e.stat().st_size for e in os.scandir(next(iter(at)))) < 400_000
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, big.collect()))
    store.drop(out)
    assert not os.path.exists(next(iter(at)))


def test_doubling_makes_no_checkpoints(spark, monkeypatch):
    from verbatim.operators import decode

    monkeypatch.setattr(decode, "cut", None)
    best = spark.createDataFrame([("", "a"), ("a", "b"), ("b", "c"), ("c", "a"), ("a b", "c")], "ctx string, tok string")
    given = spark.createDataFrame([("x", ["z", "a"]), ("y", [])], "id string, given array<string>")
    got = {r.id: r.generated for r in decode.greedy(given, best, 5, 3, "doubling").collect()}
    assert got == {"x": ["b", "c", "a", "b", "c"], "y": ["a", "b", "c", "a", "b"]}


def test_contexts_are_counted_in_parts(spark, sf, monkeypatch):
    """Parts hold every context once, give the tables that one pass gives, and their own counts are gone when the next part is counted."""
    whole = lm.fit(paper.seen(spark, sf).select("tk"))
    row = lambda df, *c: sorted(tuple(r[k] for k in c) for r in df.collect())
    want = row(lm.model(whole), "ord", "ctx", "tok", "cnt", "total", "n_next")
    pruned = row(lm.without_echoes(lm.best_next(whole)), "ord", "ctx", "tok")
    made = []
    fit = lm.fit
    monkeypatch.setattr(lm, "fit", lambda docs, part: made.append(part) or fit(docs, part=part))
    monkeypatch.setattr(paper, "PART_BYTES", paper.input_bytes(spark, f"{sf}/documents.parquet") // 3 + 1)
    store.forget()
    try:
        assert row(paper.counts(spark, sf), "ord", "ctx", "tok", "cnt", "total", "n_next") == want
        assert row(paper.best(spark, sf), "ord", "ctx", "tok") == pruned
        assert made == [(0, 3), (1, 3), (2, 3)] * 2
    finally:
        store.forget()


def test_nearest_vectors_are_few_candidates(spark):
    """Of all pairs only those that may be among the nearest take the exact expression: ties, copies of an id and rows without a cosine are kept."""
    from verbatim.operators import rel

    made = [(k, [1.0, k / 100.0, 0.5]) for k in range(200)] + [(200, [1.0, 0.0, 0.5]), (201, None), (202, [1.0, float("nan"), 0.0]), (203, [1.0])]
    rows = spark.createDataFrame(made, "b long, embedding array<double>").coalesce(1)
    asked = [(0, made[0][1]), (100, made[100][1])]
    got = {(r.i, r.b) for r in rel.near_candidates(rows, asked, 3).collect()}
    assert {b for i, b in got if i == 0} >= {1, 2, 200, 201, 202, 203} and {b for i, b in got if i == 1} >= {99, 101, 201, 202, 203}
    assert (0, 0) not in got and (1, 100) not in got
    few = rel.near_candidates(rows, asked, 3, at_once=4096).collect()
    assert len(few) < 20


def test_orders_are_summed_from_the_longest_contexts(spark):
    """Each token is dealt once, not once an order: no row is multiplied before the shuffle; counts are those of plain code, null words and short texts included."""
    texts = [["a", "b", "a", "b", "a"], ["b"], [], ["a", "b", "c", "a", "b", "c", "d"], ["a", None, "b", "a", "b"]]
    docs = spark.createDataFrame([(t,) for t in texts], "tk array<string>")
    want: dict = {}
    for t in texts:
        for i, x in enumerate(t):
            for o in range(min(i, 3) + 1):
                if None not in t[i - o : i]:
                    key = (o, " ".join(t[i - o : i]), x)
                    want[key] = want.get(key, 0) + 1
    got = lm.fit(docs)
    assert {(r.ord, r.ctx, r.tok): r.cnt for r in got.collect()} == want
    assert "stack(" not in plan(got)
    got = lm.fit(docs, 1)
    assert {(r.ord, r.ctx, r.tok): r.cnt for r in got.collect()} == {k: v for k, v in want.items() if not k[0]}


def test_a_large_frontier_moves_its_last_tokens_only(spark, monkeypatch):
    """A step of a frontier that does not travel keeps no tokens of earlier steps; the result is that of walking alone, for an id that is null and empty prefixes too, and its files are those of the result."""
    from verbatim.operators import decode

    docs = spark.createDataFrame([(["a", "b", "a", "c", "b", "a", "d"],), (["c", "b", "b", "a", "a", "b"],)], "tk array<string>")
    best = store.cut(lm.best_next(lm.fit(docs)))
    given = spark.createDataFrame([("x", ["z", "a"]), ("y", []), (None, ["c", "b"]), ("w", ["b", "a", "c", "b"])], "id string, given array<string>")
    want = {r.id: r.generated for r in decode.greedy(given, best, 11, strategy="broadcast").collect()}
    kept = []
    monkeypatch.setattr(decode, "_travels", lambda df: False)
    monkeypatch.setattr(decode, "keep", lambda df: kept.append((df.columns, out := store.keep(df))) or out)
    assert {r.id: r.generated for r in decode.greedy(given, best, 11, strategy="frontier").collect()} == want
    assert [c for c, _ in kept] == [["id", "tail", "_t"]] * 11 + [["id", "generated"]]
    for _, out in kept[:-1]:
        assert not os.path.exists(out.inputFiles()[0].removeprefix("file://")) if out.inputFiles() else True


TABLES_READ = {"published_report": {"orders", "lineitem"}, "published_writing": {"lineitem"}, "published_checks": {"lineitem"}, "relative_reduction": {"orders", "lineitem"}, "report_pivot": {"orders", "lineitem"}, "tradeoff_pareto": {"orders", "lineitem"}}


@pytest.mark.parametrize("name", sorted(TABLES_READ))
def test_reports_are_made_of_given_tables(spark, sf, name):
    """Tables of results come from Spark's scans, not from rows in the code, and say something."""
    df = QUERIES[name](spark, sf)
    assert {os.path.basename(f).split(".")[0] for f in df.inputFiles()} == TABLES_READ[name]
    assert df.count() > 2


def test_few_texts_do_not_deal_the_counts(spark, sf, monkeypatch):
    """Where the tokens to score are few, only their counts meet them; scores are those of the join with all counts."""
    c = paper.counts(spark, sf)
    seqs = spark.createDataFrame([("s", ["the"], ["a", "the", "zzz"]), ("t", [], ["of"])], "seq_id string, given array<string>, text array<string>")
    few = lm.sequence_nll(seqs, c, "seq_id", "given", "text")
    assert "LeftSemi" in plan(few)
    got = sorted(map(tuple, few.collect()))
    monkeypatch.setattr(lm, "fits", lambda df: False)
    assert got == sorted(map(tuple, lm.sequence_nll(seqs, c, "seq_id", "given", "text").collect()))


def _no_counts(monkeypatch):
    """From here on whatever asks for the table of all counts fails."""
    store.forget()

    def counts(spark, d):
        raise AssertionError("the table of all counts is made")

    monkeypatch.setattr(paper, "counts", counts)


def test_pairs_count_only_the_words_they_change(spark, sf, monkeypatch):
    """Rewrites look up the successors of few words; they are those of the table of all counts, which is not made."""
    segs, c = spark.createDataFrame([("s", "the of and to zzz of a".split()), ("t", ["of"])], "seg_id string, reference array<string>"), paper.counts(spark, sf)
    want = sorted(map(tuple, paraphrase.substitute(segs, c).collect()))
    assert sorted(map(tuple, paraphrase.substitute(segs, lm.after(paper.seen(spark, sf).select("tk"), paraphrase.asked(segs))).collect())) == want
    _no_counts(monkeypatch)
    assert QUERIES["prefs_mix"](spark, sf).count() > 0


def test_likelihoods_are_summed_over_parts(spark, sf, monkeypatch):
    """Segments meet one part of the counts after another; the sums are those of the join with all counts."""
    segs = segments.head_segment(paper.docs(spark, sf))
    want = {r.seg_id: (r.n_tokens, r.nll) for r in lm.sequence_nll(segs, paper.counts(spark, sf), "seg_id", "prefix", "reference").collect()}
    _no_counts(monkeypatch)
    monkeypatch.setattr(paper, "PART_BYTES", paper.input_bytes(spark, f"{sf}/documents.parquet") // 3 + 1)
    got = {r.seg_id: (r.n_tokens, r.nll) for r in QUERIES["sequence_nll"](spark, sf).collect()}
    assert got.keys() == want.keys() and all(n == want[k][0] and abs(x - want[k][1]) < 1e-5 for k, (n, x) in got.items())


def test_both_weightings_are_told_at_once(spark, sf, monkeypatch):
    """Likelihoods before and after share one pass over the parts, down to rows whose contexts are unknown or missing."""
    rows = [("a", ["the"], ["of", "zzz", "the", "and"]), ("b", [], ["of"]), ("c", ["zzz"], ["yyy", "the"])]
    segs, c = spark.createDataFrame(rows, "id string, given array<string>, text array<string>"), paper.counts(spark, sf)
    want = [{r.id: (r.n_tokens, r.nll) for r in lm.sequence_nll(segs, c, "id", "given", "text", mix).collect()} for mix in (lm.MIX, paper.AFTER)]
    _no_counts(monkeypatch)
    monkeypatch.setattr(paper, "PART_BYTES", paper.input_bytes(spark, f"{sf}/documents.parquet") // 3 + 1)
    for r in paper.likelihoods(spark, sf, segs, "id", "given", "text", [lm.MIX, paper.AFTER]).collect():
        for w, x in zip(want, (r.nll0, r.nll1)):
            assert w[r.id][0] == r.n_tokens and abs(w[r.id][1] - x) < 1e-9
    assert QUERIES["nll_reweighted"](spark, sf).count() > 0


def test_sampled_decoding_deals_tokens_not_nuclei(spark, sf, monkeypatch):
    """Each context draws where it meets the frontier; contexts that a shorter one repeats are left out, and draws stay the same. Made in parts, without the table of all counts."""
    nuclei = lm.nucleus_table(lm.fit(paper.seen(spark, sf).where("doc_id % 4 = 0").select("tk"))).cache()
    few = lm.without_repeats(nuclei)
    assert few.count() < nuclei.count()
    given = [["the"], [], ["zzz"], ["of", "the"], ["zzz", "and"], None]
    df = spark.createDataFrame([(str(k), g) for k, g in enumerate(given)], "id string, given array<string>")
    want = {r.id: r.generated for r in decode.nucleus(df.where("given is not null"), nuclei, 6, strategy="broadcast").collect()}
    for most in (store.BROADCAST_BYTES, 0):
        monkeypatch.setattr(decode, "BROADCAST_BYTES", most)
        got = {r.id: r.generated for r in decode.nucleus(df, few, 6, strategy="frontier").collect()}
        assert {k: got[k] for k in want} == want and got["5"] and len(got) == 6
    _no_counts(monkeypatch)
    assert QUERIES["decode_nucleus"](spark, sf).count() > 0


def test_packed_tables_give_what_rows_give(spark, sf, monkeypatch):
    """Words in numbers, split by array code: the same contexts, tokens and draws as by rows, for odd white space, letters and prefixes; made without counting rows, and as rows where words or frontier are too large."""
    from verbatim.functions.text import first_tokens, tokens
    from verbatim.operators import decode, packed

    texts = ["a b\tA  c b\x0b\x0ca d ", "C b b\u00a0x a a\x1cq b", "", None, " ", "\u0130 \u039f\u03a3 stra\u00dfe \u0130 a", "\nlone", "a b a c", "the of the"]
    odd = spark.createDataFrame([(t,) for t in texts], "text string")
    given = spark.createDataFrame([("x", ["z", "a"]), ("y", []), (None, ["c", "b"]), ("w", ["b", "a", "c", "b"]), ("v", ["of", "the"]), ("u", ["zzz", "the"])], "id string, given array<string>")
    row = lambda df, *c: sorted(tuple(r[k] for k in c) for r in df.collect())
    made = lambda df: {r.id: r.generated for r in df.collect()}
    counts = lm.fit(odd.select(tokens("text").alias("tk"))).cache()
    best, nuclei = lm.without_echoes(lm.best_next(counts)).cache(), lm.nucleus_table(counts)
    greedy, drawn = packed.make(odd, packed.Best()), packed.make(odd, packed.Nucleus(0.7, 0.9))
    assert row(greedy.rows(), "ord", "ctx", "tok") == row(best, "ord", "ctx", "tok")
    want, draws = made(decode.greedy(given, best, 4, strategy="broadcast")), made(decode.nucleus(given, nuclei, 4, strategy="broadcast"))
    assert made(decode.greedy(given, greedy, 4, strategy="frontier")) == want
    got, same = made(decode.nucleus(given, drawn, 4, strategy="frontier")), [k for k in want if k]  # rows and Python spell the key of a null id differently
    assert [got[k] for k in same] == [draws[k] for k in same] and len(got[None]) == 4
    with monkeypatch.context() as m:
        m.setattr(packed, "STATE_BYTES", 0)
        assert greedy.walk(given, 4) is None
        assert made(decode.nucleus(given, drawn.nuclei(), 4, strategy="broadcast")) == draws
        m.setattr(packed, "WORD_BYTES", 0)
        assert packed.make(odd, packed.Best()) is None
    for r in odd.where("text is not null").select(tokens("text").alias("t"), first_tokens("text", 2).alias("f")).collect():
        assert r.f == r.t[: len(r.f)] and len(r.f) >= min(2, len(r.t))
    monkeypatch.setattr(lm, "fit", None)
    store.forget()
    try:
        assert isinstance(paper.greedy_table(spark, sf), packed.Packed) and isinstance(paper.nucleus_table(spark, sf), packed.Packed)
    finally:
        store.forget()
