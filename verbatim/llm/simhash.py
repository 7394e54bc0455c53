"""SimHash near-duplicates by meet-in-the-middle ball hashing.

Two fingerprints within RADIUS bits share a variant: a value within half of that from both.
Emitting the whole ball of a 64-bit word (2,081 variants at radius 4) is exact but heavy, so
the word is halved first: of two fingerprints within 4 bits, one half differs in 2 bits or
fewer, and the balls of radius 1 over both halves (66 variants) meet there. Variants are
shuffled and sorted, and each run of equal variants is compared as it streams by, in bounded
memory.

A run that grows beyond MAX_RUN is not compared pair by pair: its members go to the ball of
the whole word, where everything that shares a variant lies within 4 bits, so that each run
is a star around its first member and costs its length. Nothing is dropped either way.

Only distinct fingerprints are emitted; copies follow their fingerprint. The links of a run
are those that span its parts, which is all that components need. Where several kinds of
fingerprints are linked, those with an equal half meet first, and a run then only links what
they have not joined: a large group of near copies would else be spanned anew by each task.

Defined results: null and empty texts have fingerprint zero and link like any other; equal
rows share all results; rows without an id link, but never name a component unless no other
row of theirs has one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans import store
from . import common as C

WORDS, SEED, RADIUS, MAX_RUN = 4, 42, 4, 4096
#: Of the near-copy stage: independent fingerprints a text, likeness, words a shingle; MinHash bands and their rows (of 0.8 likeness, 1 pair in 100,000 shares no band).
KINDS, LIKENESS, SHINGLE, BANDS, ROWS = 4, 0.8, 5, 16, 3
#: What tells texts apart: the smallest id that has one, and its hashes.
TEXT_ID = ["doc_id", "h1", "h2"]
#: Links that a task holds before it contracts them.
HELD = 1 << 20

_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.int64)
_LANES = (np.arange(8) * 256).astype(np.int64)
#: Masks of the whole word's ball of radius 2.
_ONE = [1 << b for b in range(64)]
_BALL = np.array([0, *_ONE, *[x | y for i, x in enumerate(_ONE) for y in _ONE[:i]]], dtype=np.uint64)


def fingerprint(text: str | None, words: int = WORDS) -> int:
    """The unsigned 64-bit fingerprint of a whole text."""
    w = (text or "").encode().lower().split()  # bytes: A-Z and ASCII white space only
    if not w:
        return 0
    digest = xxhash.xxh64_intdigest
    runs = zip(*[w[k:] for k in range(words)]) if len(w) >= words else [w]
    h = np.fromiter((digest(b" ".join(r), SEED) for r in runs), dtype=np.uint64, count=max(1, len(w) - words + 1))
    count = np.zeros(2048, dtype=np.int64)
    for at in range(0, len(h), 1 << 14):
        part = h[at : at + (1 << 14)].astype("<u8", copy=False).view(np.uint8).reshape(-1, 8)
        count += np.bincount((part + _LANES).ravel(), minlength=2048)
    ones = (count.reshape(8, 256)[:, :, None] * _BITS).sum(axis=1).ravel()
    return int.from_bytes(np.packbits(2 * ones > len(h), bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc_id, fp long): signed, kept by a checkpoint because several steps read it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.array([fingerprint(t.as_py(), words) for t in b.column("text")], dtype=np.uint64).astype(np.int64)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(fp)], ["doc_id", "fp"])
        C.give_back()

    kind = docs.schema["doc_id"].dataType.simpleString()
    return C.cut(docs.select("doc_id", C.text_or_empty("text").alias("text")).mapInArrow(run, f"doc_id {kind}, fp long"))


def _parts_of(fps: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Places (member, first member) of the parts that links within `radius` make of a run: each member meets those that no part has yet."""
    left, out = np.arange(len(fps)), []
    while len(left):
        root, left = left[0], left[1:]
        open_ = [root]
        while open_ and len(left):
            near = np.bitwise_count(fps[left] ^ fps[open_.pop()]) <= radius
            hit, left = left[near], left[~near]
            open_ += hit.tolist()
            out += [(h, root) for h in hit]
    return out


def _contract(links: np.ndarray) -> np.ndarray:
    """(node, smallest node of its part) for the parts that a task's links make: fewer rows, the same components."""
    nodes, at = np.unique(links, return_inverse=True)
    i, j = at.reshape(links.shape).T
    root = np.arange(len(nodes))
    while True:
        new = root.copy()
        np.minimum.at(new, i, root[j])
        np.minimum.at(new, j, root[i])
        new = np.minimum(new, new[new])
        if (new == root).all():
            return np.stack([nodes, nodes[root]], axis=1)[root != np.arange(len(nodes))]
        root = new


def _contracted(frames: Iterator[np.ndarray]) -> Iterator[pd.DataFrame]:
    """Links (a, b) of a whole task contracted, at most 2 * HELD of them in memory; marks (a, a) once each."""
    links, marks, rows = [], [], 0

    def out() -> pd.DataFrame:
        both = np.concatenate([_contract(np.concatenate(links)), np.unique(np.concatenate(marks), axis=0)])
        return pd.DataFrame({"a": both[:, 0].astype(np.int64), "b": both[:, 1].astype(np.int64)})

    for f in frames:
        same = f[:, 0] == f[:, 1]
        links.append(f[~same])
        marks.append(f[same])
        rows += len(f)
        if rows > HELD:
            links, marks = [_contract(np.concatenate(links))], [np.unique(np.concatenate(marks), axis=0)]
            rows = len(links[0]) + len(marks[0])
            if rows > HELD // 2:
                yield out()
                links, marks, rows = [], [], 0
    if links:
        yield out()
    del links, marks
    C.give_back()


def _runs(batches: Iterator[pd.DataFrame], radius: int, most: int) -> Iterator[np.ndarray]:
    """Links (a, b) of the runs of equal keys; (a, a) marks a member of a run longer than `most`. Where rows have a label `own`, links are between labels, and equal ones need none."""
    keys, fps, owns, hot = np.empty(0, dtype=np.int64), np.empty(0, dtype=np.uint64), np.empty(0, dtype=np.uint64), None

    def settle(keys: np.ndarray, fps: np.ndarray, owns: np.ndarray) -> np.ndarray:
        starts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
        lengths = np.diff(np.r_[starts, len(keys)])
        two = starts[lengths == 2]
        two = two[np.bitwise_count(fps[two] ^ fps[two + 1]) <= radius]
        two = two[owns[two] != owns[two + 1]]
        out = [np.stack([owns[two + 1], owns[two]], axis=1)]
        for s, n in zip(starts[lengths > 2], lengths[lengths > 2]):
            run, own = fps[s : s + n], owns[s : s + n]
            if n > most:
                out.append(np.stack([run, run], axis=1))
            elif (own != own[0]).any() and (found := _parts_of(run, radius)):
                met = own[np.array(found)]
                out.append(met[met[:, 0] != met[:, 1]])
        return np.unique(np.concatenate(out), axis=0)

    for b in batches:
        k, f = b["key"].to_numpy(), b["fp"].to_numpy().astype(np.uint64)
        o = b["own"].to_numpy().astype(np.uint64) if "own" in b.columns else f
        if hot is not None and len(k):
            same = np.searchsorted(k, hot, side="right") if k[0] == hot else 0
            if same:
                yield np.stack([f[:same], f[:same]], axis=1)
            k, f, o = k[same:], f[same:], o[same:]
            hot = hot if not len(k) else None
        keys, fps, owns = np.r_[keys, k], np.r_[fps, f], np.r_[owns, o]
        if not len(keys):
            continue
        last = np.searchsorted(keys, keys[-1], side="left")
        if last:
            yield settle(keys[:last], fps[:last], owns[:last])
        keys, fps, owns = keys[last:], fps[last:], owns[last:]
        if len(keys) > most:  # the open run is long already
            yield np.stack([fps, fps], axis=1)
            hot, keys, fps, owns = keys[0], keys[:0], fps[:0], owns[:0]
    if len(keys):
        yield settle(keys, fps, owns)


def _stars(batches: Iterator[pd.DataFrame]) -> Iterator[np.ndarray]:
    """(member, first of its run) for sorted keys whose runs are near throughout."""
    key = first = None
    for b in batches:
        if not len(b):
            continue
        k, f = b["key"].to_numpy(), b["fp"].to_numpy().astype(np.uint64)
        start = np.r_[key is None or k[0] != key, k[1:] != k[:-1]]
        at = np.maximum.accumulate(np.where(start, np.arange(len(k)), -1))
        head = np.where(at >= 0, f[np.maximum(at, 0)], first if first is not None else np.uint64(0))
        key, first = k[-1], head[-1]
        yield np.unique(np.stack([f, head], axis=1)[f != head], axis=0)


def links(fps: DataFrame, radius: int = RADIUS, most: int = MAX_RUN) -> DataFrame:
    """Edges (a, b) between the distinct fingerprints fps(fp, and k int where there are several kinds) that have the components of all pairs of a kind within `radius` bits."""
    assert radius == 4, "one half may then differ in 2 bits, and the whole ball has radius 2"
    n = C.partitions(fps.sparkSession)
    low = (1 << 32) - 1
    masks = lambda each: F.array(*[F.struct(F.lit(p).alias("p"), F.lit(m).cast("long").alias("m")) for p in (0, 1) for m in each])
    half = F.when(F.col("_v.p") == 0, F.col("fp").bitwiseAND(F.lit(low))).otherwise(F.shiftrightunsigned("fp", 32).bitwiseOR(F.lit(1 << 32)))

    def met(one: DataFrame, bits: list[int]) -> DataFrame:
        each = one.select("*", F.explode(masks(bits)).alias("_v"))
        keyed = each.select(half.bitwiseXOR(F.col("_v.m")).alias("key"), *one.columns).repartition(n, "key").sortWithinPartitions("key", "fp")
        return keyed.mapInPandas(lambda it: _contracted(_runs(it, radius, most)), "a long, b long")

    ball_of_one = [0, *[1 << b for b in range(32)]]
    if "k" in fps.columns:
        found = None
        for k in sorted(r["k"] for r in fps.select("k").distinct().collect()):
            one = fps.where(F.col("k") == k).select("fp")
            # what an equal half joins has one label; it links to a smaller one, which may have a label too
            first = store.keep(met(one, [0]).where("a <> b").groupBy("a").agg(F.min("b").alias("b")))
            own, up = first, first.select(F.col("a").alias("_a"), F.col("b").alias("_up"))
            for _ in range(2):
                own = own.join(up, F.col("b") == F.col("_a"), "left").select("a", F.coalesce("_up", "b").alias("b"))
            labelled = one.join(own, F.col("fp") == F.col("a"), "left").select("fp", F.coalesce("b", "fp").alias("own"))
            got = C.cut(met(labelled, ball_of_one).union(first).distinct())
            store.drop(first)
            C.sweep(fps.sparkSession)  # the variants of a kind are 66 times its rows and go before the next kind's come
            found = got if found is None else found.union(got)
        if found is None:
            return fps.select(F.col("fp").alias("a"), F.col("fp").alias("b"))
    else:
        found = C.cut(met(fps, ball_of_one).distinct())

    def ball(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            f = b["fp"].to_numpy().astype(np.uint64)
            for at in range(0, len(f), 64):
                part = f[at : at + 64]
                yield pd.DataFrame({"key": (part[:, None] ^ _BALL[None, :]).ravel().astype(np.int64), "fp": np.repeat(part, len(_BALL)).astype(np.int64)})

    hot = found.where("a = b").select(F.col("a").alias("fp")).repartition(n, "fp")
    wide = hot.mapInPandas(ball, "key long, fp long").repartition(n, "key").sortWithinPartitions("key", "fp")
    return found.where("a <> b").union(wide.mapInPandas(lambda it: _contracted(_stars(it)), "a long, b long").distinct())


def components(fps: DataFrame, radius: int = RADIUS, most: int = MAX_RUN) -> DataFrame:
    """fps(doc_id, fp) with component_id: the smallest doc_id that links reach."""
    reps = C.cut(fps.groupBy("fp").agg(F.min("doc_id").alias("_rep")))
    label = C.connected(links(reps.select("fp"), radius, most))
    named = reps.join(label, reps.fp == label.node, "left").select("fp", "_rep", F.coalesce("component", "fp").alias("_l"))
    least = named.join(label.select(F.col("node").alias("_l2")), F.col("_l") == F.col("_l2"), "left_semi").groupBy("_l").agg(F.min("_rep").alias("_c"))
    named = named.join(least.withColumnRenamed("_l", "_ll"), F.col("_l") == F.col("_ll"), "left").select("fp", F.coalesce("_c", "_rep").alias("component_id"))
    return fps.join(named, "fp").select("doc_id", "fp", "component_id")


def word_fingerprints(text: str, kinds: int) -> list[int]:
    """Signed SimHashes of a text's set of words, as many as asked for, from one hash a word."""
    words = set(text.encode().lower().split())
    if not words:
        return [0] * kinds
    h = np.fromiter((xxhash.xxh64_intdigest(w, SEED) for w in words), dtype=np.uint64, count=len(words))
    out = []
    for k in range(kinds):
        with np.errstate(over="ignore"):
            x = (h ^ np.uint64(k * 0x51ED270B)) * np.uint64(0x9E3779B97F4A7C15)
            x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
            x ^= x >> np.uint64(29)
        count = np.bincount((x.view(np.uint8).reshape(-1, 8) + _LANES).ravel(), minlength=2048)
        ones = (count.reshape(8, 256)[:, :, None] * _BITS).sum(axis=1).ravel()
        out.append(int.from_bytes(np.packbits(2 * ones > len(h), bitorder="little").tobytes(), "little", signed=True))
    return out


def shingle_set(text: str, words: int) -> np.ndarray:
    """A text's set of word shingles as 32-bit hashes, in order."""
    w = text.encode().lower().split()
    runs = zip(*[w[k:] for k in range(words)]) if len(w) >= words else [w]
    return np.unique(np.fromiter((xxhash.xxh32_intdigest(b" ".join(r), SEED) for r in runs), dtype=np.uint32, count=max(1, len(w) - words + 1)).view(np.int32))


def alike(a: np.ndarray, b: np.ndarray, least: float) -> bool:
    """Whether the Jaccard likeness of two whole sets is `least` or more."""
    if min(len(a), len(b)) < least * max(len(a), len(b)) - 1e-9:
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / max(1, len(a) + len(b) - both) >= least


def bands(h: np.ndarray, n: int, rows: int) -> list[int]:
    """n keys of a set, each from its smallest members in `rows` random orders: sets of likeness j share one with probability j ** rows."""
    h, out = h.astype(np.int64).view(np.uint64), np.zeros(n, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for k in range(n * rows):
            x = (h + np.uint64(k * 0x51ED270B + 1)) * np.uint64(0x9E3779B97F4A7C15)
            x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
            out[k // rows] = out[k // rows] * np.uint64(0x9E3779B97F4A7C15) + (x ^ (x >> np.uint64(29))).min()
    return out.view(np.int64).tolist()


def _sets(column: pa.ListArray) -> Iterator[np.ndarray]:
    flat, at = column.values.to_numpy(), column.offsets.to_numpy()
    return (flat[i:j] for i, j in zip(at, at[1:]))


def _later(batches: Iterator[pa.RecordBatch], least: float) -> Iterator[pa.RecordBatch]:
    """Of texts sorted by key and identity, those like an earlier one of their key; a text that is like none is held for those after it."""
    key, last, heads = None, None, []
    for b in batches:
        keys, ids, gone = b.column("key").to_pylist(), list(zip(*[b.column(c).to_pylist() for c in TEXT_ID])), []
        for i, s in enumerate(_sets(b.column("s"))):
            if keys[i] != key:
                key, last, heads = keys[i], None, []
            if ids[i] == last:  # a row that is there twice
                continue
            last = ids[i]
            if any(alike(s, x, least) for x in heads):
                gone.append(i)
            else:
                heads.append(s.copy())
        yield b.select(TEXT_ID).take(pa.array(gone, pa.int64()))
    C.give_back()


def with_hashes(docs: DataFrame) -> DataFrame:
    text = C.text_or_empty("text")
    return docs.withColumn("h1", F.xxhash64(text)).withColumn("h2", F.xxhash64(F.lit(5), text))


def near_copies(docs: DataFrame, kinds: int = KINDS, least: float = LIKENESS, words: int = SHINGLE) -> DataFrame:
    """(doc_id, h1, h2): texts of documents that are equal to, or near copies (likeness `least` of `words`-word shingles) of, one with a smaller id.

    The SimHash of shingles at 4 bits finds likeness above 0.95 or so. Two texts that are 0.8
    alike in five-word shingles are 0.95 alike in words, so SimHashes of word sets are within
    4 bits more often than not, and one of several independent ones nearly always is.
    Equal texts go first. The others' components only say what is compared: a text goes where
    its whole set of shingles is `least` like that of a smaller text, and of those that stay
    no two are. The component's smallest text is compared with all of it; the rest fall into
    blocks by MinHash bands, where each block's smallest text, and then every text that stays,
    is compared with those after it. Texts gone by then take no further part.
    """

    def prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            f = pa.array([word_fingerprints(t.as_py(), kinds) for t in b.column("text")], pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in TEXT_ID), f], [*TEXT_ID, "f"])
        C.give_back()

    n = C.partitions(docs.sparkSession)
    ids = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, h1 long, h2 long"
    itself = F.struct(*TEXT_ID)
    known = with_hashes(docs.where("doc_id is not null").select("doc_id", C.text_or_empty("text").alias("text")))
    f = C.cut(known.mapInArrow(prints, f"{ids}, f array<long>"))
    texts = C.cut(f.groupBy("h1", "h2").agg(F.min("doc_id").alias("rep"), F.first("f").alias("f")))
    equal = f.join(texts.select("h1", "h2", "rep"), ["h1", "h2"]).where("doc_id <> rep").select(*TEXT_ID)

    # a text is known by its first fingerprint, and each fingerprint by the smallest text that has it
    every = texts.select(F.get("f", F.lit(0)).alias("_f0"), F.posexplode("f").alias("k", "fp"))
    owner = C.cut(every.groupBy("fp").agg(F.min("_f0").alias("own")))
    shared = every.join(owner, "fp").where("_f0 <> own").select(F.col("_f0").alias("a"), F.col("own").alias("b"))
    found = links(every.select("fp", "k").distinct())
    found = found.join(owner.select(F.col("fp").alias("a"), F.col("own").alias("oa")), "a").join(owner.select(F.col("fp").alias("b"), F.col("own").alias("ob")), "b")
    label = C.connected(found.select(F.col("oa").alias("a"), F.col("ob").alias("b")).union(shared))
    mine = texts.select(F.col("rep").alias("doc_id"), "h1", "h2", F.get("f", F.lit(0)).alias("_f0"))
    mine = C.cut(mine.join(label, F.col("_f0") == F.col("node"), "left").select(*TEXT_ID, F.coalesce("component", "_f0").alias("_c")))
    first = C.cut(mine.groupBy("_c").agg(F.min(itself).alias("_first"), F.count(F.lit(1)).alias("_n")).where("_n > 1").drop("_n"))
    asked = C.cut(mine.join(C.maybe_broadcast(first), "_c").select(*TEXT_ID, "_first"))

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                s = pa.array([shingle_set(t.as_py(), words) for t in part.column("text")], pa.list_(pa.int32()))
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in TEXT_ID), s], [*TEXT_ID, "s"])
        C.give_back()

    told = known.join(C.maybe_broadcast(asked.select(*TEXT_ID)), TEXT_ID, "left_semi")
    told = C.cut(told.mapInArrow(sets, f"{ids}, s array<int>"))

    def compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            near = [alike(x, y, least) for x, y in zip(_sets(b.column("s")), _sets(b.column("_s")))]
            yield b.select(TEXT_ID).filter(pa.array(near, pa.bool_()))

    def like_first(pairs: DataFrame) -> DataFrame:
        both = pairs.where(itself != F.col("_first")).join(told, TEXT_ID).join(told.select(itself.alias("_first"), F.col("s").alias("_s")), "_first")
        return C.cut(both.select(*TEXT_ID, "s", "_s").mapInArrow(compared, ids).distinct())

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            k = pa.array([bands(s, BANDS, ROWS) for s in _sets(b.column("s"))], pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in [*TEXT_ID, "_c"]), k], [*TEXT_ID, "_c", "k"])

    near = like_first(asked)
    rest = C.drop_ids(asked.where(itself != F.col("_first")), near, TEXT_ID).select(*TEXT_ID, F.xxhash64("_first").alias("_c"))
    keyed = told.join(C.maybe_broadcast(rest), TEXT_ID).mapInArrow(keys, f"{ids}, _c long, k array<long>")
    keyed = C.cut(keyed.select(*TEXT_ID, "_c", F.posexplode("k").alias("_p", "_b")).select(F.xxhash64("_c", "_p", "_b").alias("key"), *TEXT_ID).distinct())
    heads = lambda k: k.groupBy("key").agg(F.min(itself).alias("_first"), F.max(itself).alias("_last")).where("_first <> _last").select("key", "_first")
    second = like_first(keyed.join(heads(keyed), "key").select(*TEXT_ID, "_first").distinct())
    keyed = C.cut(C.drop_ids(keyed, second, TEXT_ID))
    blocks = keyed.join(heads(keyed), "key", "left_semi").join(told, TEXT_ID).select("key", *TEXT_ID, "s").repartition(n, "key").sortWithinPartitions("key", *TEXT_ID)
    third = blocks.mapInArrow(lambda it: _later(it, least), ids)
    return equal.union(near).union(second).union(third).distinct()


@C.carrying("doc_id", "text")
def deduplicate(docs: DataFrame) -> DataFrame:
    """Near copies of a text with a smaller id go. Rows that share an id go each by its own text; of those with equal texts too one stays. Rows without an id stay."""
    text = ["doc_id", "h1"]
    left = C.drop_ids(with_hashes(docs), C.cut(near_copies(docs)), text)
    twice = C.cut(left.where("doc_id is not null").groupBy(*text).count().where("count > 1").select(*text))
    if twice.limit(1).count() == 0:
        return left.drop("h1", "h2")
    again = left.join(C.maybe_broadcast(twice), text, "left_semi")
    again = again.withColumn("_r", F.row_number().over(Window.partitionBy(*text).orderBy("h2"))).where("_r = 1").drop("_r")
    return C.drop_ids(left, twice, text).unionByName(again).drop("h1", "h2")


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = components(fingerprints(C.table(spark, sf_dir, "documents")))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
