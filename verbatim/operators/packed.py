"""The n-gram model's decoding tables in whole numbers, made and walked by array code in Arrow workers.

Words are numbered in their own order, so that the smaller number is the smaller word. Texts are
dealt once as four numbers a token, by the last two words of the context; what a lower order sums
is dealt once more, by the last word. A table lies in files of a few rows, each of which holds the
sorted contexts of one bucket, so that a step of decoding reads arrays instead of rows. Vocabularies
and frontiers beyond bounds in bytes take the tables of strings (`lm`, `decode`) instead.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.store import drop, keep, new_path, partitions, sweep

#: Most bytes of a vocabulary that each worker gets, and of the frontier's numbers on the driver; tokens that are numbered at a time.
WORD_BYTES, STATE_BYTES, AT_ONCE = 256 << 20, 128 << 20, 1_000_000
TABLE = "kind int, bucket int, lo binary, t3 binary, n binary, toks binary, vals binary"


def _split(texts: pa.Array) -> pa.ListArray:
    """The words of lower-case texts: what `functions.text.tokens` gives, by array code (both split at ASCII white space alone)."""
    texts = pc.ascii_trim_whitespace(texts.drop_null())
    return pc.ascii_split_whitespace(texts.filter(pc.not_equal(texts, "")))


def vocabulary(docs: DataFrame) -> tuple[pa.Array, np.ndarray] | None:
    """The words of docs(text) in order, and how often each occurs; None if they are too many bytes, or if there are none."""

    def said(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = _split(b.column(0)).flatten().value_counts()
            yield pa.RecordBatch.from_arrays([got.field(0).cast(pa.string()), got.field(1)], ["tok", "cnt"])

    words = keep(docs.select(F.lower("text")).mapInArrow(said, "tok string, cnt long").groupBy("tok").agg(F.sum("cnt").alias("cnt")))
    size = words.agg(F.sum(F.octet_length("tok").cast("long") + 8).alias("b")).first()["b"] or 0
    got = None
    if 0 < size <= WORD_BYTES:
        t = words.toArrow()
        order = pc.array_sort_indices(tok := t["tok"].combine_chunks().cast(pa.string()))
        got = tok.take(order), t["cnt"].combine_chunks().take(order).to_numpy()
        del t, tok, order
        pa.default_memory_pool().release_unused()
    drop(words)
    return got


def _bucket(key: np.ndarray, n: int) -> np.ndarray:
    return ((key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)) % np.uint64(n)).astype(np.int32)


def _slices(of: np.ndarray, n: int) -> Iterator[tuple[int, np.ndarray]]:
    """The rows of each bucket that has any."""
    order = np.argsort(of, kind="stable")
    ends = np.searchsorted(of[order], np.arange(n + 1))
    for k in np.flatnonzero(np.diff(ends)):
        yield int(k), order[ends[k] : ends[k + 1]]


def _numbers(toks: pa.Array, words: pa.Array) -> np.ndarray:
    """The place of each token among all words, -1 where it is none. The words are looked up among the tokens, so that only these are hashed."""
    coded = toks.dictionary_encode()
    found = np.asarray(pc.fill_null(pc.index_in(words, value_set=coded.dictionary), -1))
    there = np.flatnonzero(found >= 0)
    number = np.full(len(coded.dictionary), -1, np.int32)
    number[found[there]] = there
    return number[np.asarray(coded.indices)]


def _places(col: pa.Array, words: pa.Array) -> tuple[np.ndarray, ...]:
    """t3, t2, t1, t0 of every token that has one before it; -1 where the text does not reach back so far."""
    size = np.asarray(pc.fill_null(pc.list_value_length(col), 0)).astype(np.int64)
    t0 = _numbers(col.flatten(), words)
    pos = np.arange(len(t0)) - np.repeat(np.cumsum(size) - size, size)
    back = [np.where(pos >= k, np.r_[np.full(k, -1, np.int32), t0[:-k]][: len(t0)], np.int32(-1)) for k in (3, 2, 1)]
    return tuple(x[pos > 0] for x in (*back, t0))


def _firsts(*keys: np.ndarray) -> np.ndarray:
    """Where a run of equal keys begins."""
    new = np.ones(len(keys[0]), bool)
    if len(new):
        new[1:] = np.logical_or.reduce([k[1:] != k[:-1] for k in keys])
    return np.flatnonzero(new)


def _summed(key: np.ndarray, tok: np.ndarray, cnt: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(key, tok, cnt) with equal ones summed, sorted by both."""
    order = np.lexsort((tok, key))
    key, tok = key[order], tok[order]
    at = _firsts(key, tok)
    cnt = np.diff(np.r_[at, len(key)]) if cnt is None else np.add.reduceat(cnt[order], at) if len(at) else cnt
    return key[at], tok[at], cnt.astype(np.int64)


class Best:
    """What greedy decoding looks up of a context: its likeliest successor, the smaller word on a tie."""

    sized = False  # one successor each

    def told(self, key: np.ndarray, tok: np.ndarray, cnt: np.ndarray) -> tuple[np.ndarray, ...]:
        """(contexts, sizes, toks, values) of sorted counts."""
        at = _firsts(key)
        size = np.diff(np.r_[at, len(key)])
        most = np.repeat(np.maximum.reduceat(cnt, at), size) if len(at) else cnt
        hit = np.flatnonzero(cnt == most)
        one = hit[_firsts(key[hit])]
        return key[one], np.ones(len(one), np.int32), tok[one], np.zeros(0)

    def same(self, size: np.ndarray, tok: np.ndarray, shorter_size: np.ndarray, shorter_tok: np.ndarray) -> np.ndarray:
        """Whether backing off gives the same; tok: the first of each context."""
        return tok == shorter_tok


class Nucleus:
    """What sampled decoding looks up: the nucleus of each context and the running shares within it."""

    sized = True

    def __init__(self, temperature: float, top_p: float):
        self.temperature, self.top_p = temperature, top_p

    def told(self, key: np.ndarray, tok: np.ndarray, cnt: np.ndarray) -> tuple[np.ndarray, ...]:
        order = np.lexsort((tok, -cnt, key))
        key, tok, cnt = key[order], tok[order], cnt[order]
        at = _firsts(key)
        size = np.diff(np.r_[at, len(key)])
        weight = cnt.astype(float) ** (1.0 / self.temperature)
        cums, keep_ = np.ones(len(key)), np.ones(len(key), bool)
        for n in np.unique(size[size > 1]):  # contexts of one size are summed side by side, each from its own start
            rows = at[size == n][:, None] + np.arange(n)
            p = weight[rows] / weight[rows].sum(1, keepdims=True)
            run = np.cumsum(p, 1)
            before = np.c_[np.zeros(len(rows)), run[:, :-1]]
            inside = np.round(before, 9) < self.top_p
            keep_[rows] = inside
            cums[rows] = (before + p) / (p * inside).sum(1, keepdims=True)
        if not len(at):
            return key, np.zeros(0, np.int32), tok, cums
        return key[at], np.add.reduceat(keep_.astype(np.int32), at).astype(np.int32), tok[keep_], cums[keep_]

    def same(self, size, tok, shorter_size, shorter_tok) -> np.ndarray:
        return (size == 1) & (shorter_size == 1) & (tok == shorter_tok)


def _few(stay: np.ndarray, key: np.ndarray, size: np.ndarray, toks: np.ndarray, vals: np.ndarray) -> tuple[np.ndarray, ...]:
    each = np.repeat(stay, size)
    return key[stay], size[stay], toks[each], vals[each] if len(vals) else vals


def _starts(size: np.ndarray) -> np.ndarray:
    return np.cumsum(size, dtype=np.int64) - size


def _row(kind: int, bucket: int, lo, t3, n, toks, vals) -> dict:
    return {"kind": kind, "bucket": bucket, "lo": lo.astype(np.int64).tobytes(), "t3": t3.astype(np.int32).tobytes(), "n": n.astype(np.int32).tobytes(), "toks": toks.astype(np.int32).tobytes(), "vals": vals.tobytes()}


_ARROW = pa.schema([("kind", pa.int32()), ("bucket", pa.int32()), *[(c, pa.binary()) for c in ("lo", "t3", "n", "toks", "vals")]])
_NONE = np.zeros(0, np.int32)


def _batch(row: dict) -> pa.RecordBatch:
    return pa.RecordBatch.from_pylist([row], _ARROW)


def _arrays(row: dict) -> tuple[np.ndarray, ...]:
    return tuple(np.frombuffer(row[c], k) for c, k in (("lo", np.int64), ("t3", np.int32), ("n", np.int32), ("toks", np.int32)))


def _counted(say, buckets: int):
    """Counts of the tokens of a bucket: order 3 is told at once, orders 2 and 1 go on to the buckets of the last word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, two, one = defaultdict(list), [], []
        for b in batches:
            for k, rows in zip(b.column(0).to_pylist(), b.column(1)):
                held[k].append(np.frombuffer(rows.as_buffer(), np.int32).reshape(4, -1))
        for k in list(held):
            t3, t2, t1, t0 = np.concatenate(held.pop(k), axis=1)
            pairs, of = np.unique((t2.astype(np.int64) + 1) << 32 | t1, return_inverse=True)
            key, tok, cnt = _summed(of.astype(np.int64) << 32 | (t3.astype(np.int64) + 1), t0, None)
            pair, ptok, pcnt = _summed(key >> 32, tok, cnt)
            _, t, c = one_of = _summed(pairs[pair] & 0xFFFFFFFF, ptok, pcnt)
            one.append((one_of[0] << 32 | t, c))
            full = pairs[pair] >> 32 > 0
            short = say.told(pair[full], ptok[full], pcnt[full])
            two.append((pairs[short[0]], *short[1:]))
            far = key & 0xFFFFFFFF > 0
            three = say.told(key[far], tok[far], cnt[far])
            at = np.searchsorted(short[0], three[0] >> 32)  # each longer context's shorter one is there
            lead = lambda x: x[2][_starts(x[1])] if len(x[1]) else x[2]
            stay = ~say.same(three[1], lead(three), short[1][at], lead(short)[at])
            ctx, n, toks, vals = _few(stay, *three)
            if len(ctx):
                yield _batch(_row(3, k, pairs[ctx >> 32], (ctx & 0xFFFFFFFF) - 1, n if say.sized else _NONE, toks, vals))
        if one:
            key, cnt = (np.concatenate(x) for x in zip(*one))
            for k, rows in _slices(_bucket(key >> 32, buckets), buckets):
                yield _batch(_row(0, k, key[rows], _NONE, _NONE, _NONE, cnt[rows]))
            lo, n, toks, vals = (np.concatenate(x) for x in zip(*two))
            start = _starts(n)
            for k, rows in _slices(_bucket(lo & 0xFFFFFFFF, buckets), buckets):
                size = n[rows]
                each = np.repeat(start[rows] - _starts(size), size) + np.arange(size.sum())
                yield _batch(_row(2, k, lo[rows], _NONE, size, toks[each], vals[each] if len(vals) else vals))

    return run


def _lower(say, zero: int | None):
    """Order 1 of a bucket of last words, and order 2 without what order 1 says too; zero: what the empty context says, if order 1 goes without that."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = defaultdict(lambda: ([], []))
        for b in batches:
            for r in b.to_pylist():
                lo, _, n, toks = _arrays(r)
                if r["kind"]:
                    held[r["bucket"]][1].append((lo, n, toks, np.frombuffer(r["vals"], np.float64)))
                else:
                    held[r["bucket"]][0].append((lo, np.frombuffer(r["vals"], np.int64)))
        for k in list(held):
            ones, twos = held.pop(k)
            key, cnt = (np.concatenate(x) for x in zip(*ones))
            one = say.told(*_summed(key >> 32, (key & 0xFFFFFFFF).astype(np.int32), cnt))
            first = one[2][_starts(one[1])]
            if twos:
                lo, n, toks, vals = (np.concatenate(x) for x in zip(*twos))
                at = np.searchsorted(one[0], lo & 0xFFFFFFFF)
                stay = ~say.same(n, toks[_starts(n)], one[1][at], first[at])
                start, order = _starts(n), np.argsort(lo, kind="stable")
                order = order[stay[order]]
                size = n[order]
                each = np.repeat(start[order] - _starts(size), size) + np.arange(size.sum())
                if len(order):
                    yield _batch(_row(2, k, lo[order], _NONE, size if say.sized else _NONE, toks[each], vals[each] if len(vals) else vals))
            ctx, n, toks, vals = one if zero is None else _few(first != zero, *one)
            if len(ctx):
                yield _batch(_row(1, k, ctx, _NONE, n if say.sized else _NONE, toks, vals))

    return run


class Packed:
    """A model's decoding table in buckets of numbers, with its words."""

    def __init__(self, docs: DataFrame, say, known: tuple[pa.Array, np.ndarray]):
        spark = docs.sparkSession
        self.spark, self.say, (self.words, self.often) = spark, say, known
        self.sent = spark.sparkContext.broadcast(self.words)
        self.buckets = 4 * partitions(spark)
        #: the likeliest word, the smaller on a tie
        self.zero = int(np.argmax(self.often))
        sent, n, paths = self.sent, self.buckets, [new_path(spark, "packed") for _ in range(2)]

        def dealt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held, size = [], 0

            def out() -> pa.RecordBatch:
                t3, t2, t1, t0 = _places(pa.concat_arrays(held), sent.value)
                got = [(k, np.stack([x[rows] for x in (t3, t2, t1, t0)]).tobytes()) for k, rows in _slices(_bucket((t2.astype(np.int64) + 1) << 32 | t1, n), n)]
                return pa.RecordBatch.from_arrays([pa.array([k for k, _ in got], pa.int32()), pa.array([x for _, x in got], pa.binary())], ["bucket", "rows"])

            for b in batches:
                held.append(_split(b.column(0)))
                size += len(held[-1].flatten())
                if size >= AT_ONCE:
                    yield out()
                    held, size = [], 0
                    pa.default_memory_pool().release_unused()
            if held:
                yield out()
            held.clear()
            pa.default_memory_pool().release_unused()

        tokens = docs.select(F.lower("text")).mapInArrow(dealt, "bucket int, rows binary").repartition(partitions(spark), "bucket")
        tokens.mapInArrow(_counted(say, n), TABLE).write.partitionBy("kind").option("compression", "zstd").parquet(paths[0])
        sweep(spark)
        read = lambda path, kinds: spark.read.schema(TABLE).parquet(path).where(F.col("kind").isin(kinds))
        lower = read(paths[0], [0, 2]).select("kind", "bucket", "lo", "t3", "n", "toks", "vals").repartition(partitions(spark), "bucket")
        lower.mapInArrow(_lower(say, self.zero if isinstance(say, Best) else None), TABLE).write.partitionBy("kind").option("compression", "zstd").parquet(paths[1])
        sweep(spark)
        fs = spark._jvm.org.apache.hadoop.fs.Path(paths[0]).getFileSystem(spark._jsc.hadoopConfiguration())
        for kind in (0, 2):
            fs.delete(spark._jvm.org.apache.hadoop.fs.Path(f"{paths[0]}/kind={kind}"), True)
        self.table = read(paths[0], [3]).unionByName(read(paths[1], [1, 2]))
        self.contexts = 1 + (self.table.agg(F.sum(F.octet_length("lo") / 8)).first()[0] or 0)

    def rows(self) -> DataFrame:
        """(ord, ctx, tok) of what greedy decoding looks up, as words."""
        sent = self.sent

        def told(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            words = sent.value
            for b in batches:
                for r in b.to_pylist():
                    lo, t3, _, toks = _arrays(r)
                    word = [words.take(pa.array(x)) for x in (t3, (lo >> 32) - 1, lo & 0xFFFFFFFF)[3 - r["kind"] :] if len(x)]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(lo), r["kind"], np.int32)), pc.binary_join_element_wise(*word, " "), words.take(pa.array(toks))], ["ord", "ctx", "tok"])

        zero = self.spark.createDataFrame([(0, "", self.words[self.zero].as_py())], "ord int, ctx string, tok string")
        return self.table.mapInArrow(told, "ord int, ctx string, tok string").unionByName(zero)

    def nuclei(self) -> DataFrame:
        """(ctx, toks, cums) of what sampled decoding looks up, as words."""
        sent = self.sent

        def told(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            words = sent.value
            for b in batches:
                for r in b.to_pylist():
                    lo, t3, n, toks = _arrays(r)
                    word = [words.take(pa.array(x)) for x in (t3, (lo >> 32) - 1, lo & 0xFFFFFFFF)[3 - r["kind"] :] if len(x)]
                    at = pa.array(np.r_[0, np.cumsum(n)].astype(np.int32))
                    lists = [pa.ListArray.from_arrays(at, x) for x in (words.take(pa.array(toks)), pa.array(np.frombuffer(r["vals"], np.float64)))]
                    yield pa.RecordBatch.from_arrays([pc.binary_join_element_wise(*word, " "), *lists], ["ctx", "toks", "cums"])

        schema, (toks, cums) = "ctx string, toks array<string>, cums array<double>", self._of_all()
        zero = self.spark.createDataFrame([("", self.words.take(pa.array(toks)).to_pylist(), cums.tolist())], schema)
        return self.table.mapInArrow(told, schema).unionByName(zero)

    def _met(self, tails: np.ndarray, u: np.ndarray | None) -> list[tuple[int, np.ndarray, np.ndarray]]:
        """(order, which, word) of the tails' contexts that the table has; u: a number of [0, 1) for each to draw by."""
        t3, t2, t1 = (tails[:, k].astype(np.int64) for k in range(3))
        lo, n = (t2 + 1) << 32 | (t1 & 0xFFFFFFFF), self.buckets
        ask = {}
        for kind, which, key, by in ((3, (t3 >= 0) & (t2 >= 0) & (t1 >= 0), lo, lo), (2, (t2 >= 0) & (t1 >= 0), lo, t1), (1, t1 >= 0, t1, t1)):
            at = np.flatnonzero(which)
            ask[kind] = {k: (at[rows].astype(np.int32), key[at[rows]], t3[at[rows]], None if u is None else u[at[rows]]) for k, rows in _slices(_bucket(by[at], n), n)}
        sent = self.spark.sparkContext.broadcast(ask)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            ask = sent.value
            for b in batches:
                for i in range(b.num_rows):
                    kind = b.column(0)[i].as_py()
                    if (got := ask[kind].get(b.column(1)[i].as_py())) is None:
                        continue
                    at, key, far, u = got
                    lo, t3, size, toks, vals = (np.frombuffer(b.column(c)[i].as_buffer(), k) for c, k in zip(range(2, 7), (np.int64, np.int32, np.int32, np.int32, np.float64)))
                    if kind == 3:
                        first = _firsts(lo)
                        pair = np.searchsorted(lo[first], key)
                        there = (pair < len(first)) & (lo[first][np.minimum(pair, len(first) - 1)] == key)
                        run_of = np.zeros(len(lo), np.int64)
                        run_of[first[1:]] = 1
                        lo, key = np.cumsum(run_of) << 32 | t3, np.where(there, pair << 32 | far, -1)
                    found = np.minimum(np.searchsorted(lo, key), len(lo) - 1)
                    hit = np.flatnonzero(lo[found] == key)
                    if not len(hit):
                        continue
                    found = found[hit]
                    if u is None:
                        said = toks[found]
                    else:
                        start = _starts(size)
                        said = toks[start[found]].copy()
                        for j in np.flatnonzero(size[found] > 1):
                            s, m = start[found[j]], size[found[j]]
                            said[j] = toks[s + min(int(np.searchsorted(vals[s : s + m], u[hit[j]])), m - 1)]
                    yield pa.RecordBatch.from_pydict({"kind": pa.array([kind], pa.int32()), "at": pa.array([at[hit].tobytes()], pa.binary()), "tok": pa.array([said.astype(np.int32).tobytes()], pa.binary())})

        got = self.table.select("kind", "bucket", "lo", "t3", "n", "toks", "vals").mapInArrow(run, "kind int, at binary, tok binary").toArrow()
        sent.destroy()
        return sorted(((r["kind"], np.frombuffer(r["at"], np.int32), np.frombuffer(r["tok"], np.int32)) for r in got.to_pylist()), key=lambda x: x[0])

    def _of_all(self) -> tuple[np.ndarray, np.ndarray]:
        """The nucleus of the empty context."""
        _, _, toks, cums = self.say.told(np.zeros(len(self.often), np.int64), np.arange(len(self.often)), self.often)
        return toks, cums

    def walk(self, df: DataFrame, steps: int, seed: str | None = None) -> DataFrame | None:
        """(id, generated) from df(id string, given array<string>): as many rounds over the table as tokens, each for the different contexts of all rows. None if the rows are too many bytes for the driver."""
        last = F.slice("given", F.greatest(F.size("given") - 2, F.lit(1)), F.lit(3))
        rows = keep(df.select(F.monotonically_increasing_id().alias("n"), "id", F.when(F.size("given") > 0, last).otherwise(F.array().cast("array<string>")).alias("tail")))
        if rows.count() * (8 + 4 * (3 + steps)) > STATE_BYTES:
            drop(rows)
            return None
        t = rows.toArrow().combine_chunks().sort_by("n")
        at, tail = t["n"].to_numpy(), t["tail"].combine_chunks()
        size = np.asarray(pc.list_value_length(tail)).astype(np.int64)
        state = np.full((len(at), 3), -1, np.int32)
        which = np.repeat(np.arange(len(at)), size)
        where = 3 - np.repeat(size, size) + np.arange(size.sum()) - np.repeat(_starts(size), size)
        state[which, where] = _numbers(tail.flatten(), self.words)
        out = np.empty((len(at), steps), np.int32)
        ids = t["id"].to_pylist() if seed is not None else []
        zero = self._of_all() if seed is not None else None
        for step in range(steps):
            if seed is None:
                lo, inverse = np.unique((state[:, 1].astype(np.int64) + 1) << 32 | (state[:, 2].astype(np.int64) + 1), return_inverse=True)
                key, first, back = np.unique(inverse.astype(np.int64) << 32 | (state[:, 0].astype(np.int64) + 1), return_index=True, return_inverse=True)
                said = np.full(len(key), self.zero, np.int32)
                for _, which, toks in self._met(state[first], None):
                    said[which] = toks
                said = said[back]
            else:
                u = np.array([int(hashlib.md5(f"{seed}:{step if i is None else f'{i}:{step}'}".encode()).hexdigest()[:8], 16) for i in ids]) / float(1 << 32)
                said = zero[0][np.minimum(np.searchsorted(zero[1], u), len(zero[0]) - 1)].astype(np.int32)
                for _, which, toks in self._met(state, u):
                    said[which] = toks
            out[:, step] = said
            state = np.c_[state[:, 1:], said]
        sent, done = self.sent, self.spark.sparkContext.broadcast((at, out))

        def told(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            words, (at, out) = sent.value, done.value
            for b in batches:
                mine = out[np.searchsorted(at, np.asarray(b.column(0)))]
                toks = pa.ListArray.from_arrays(pa.array(np.arange(len(mine) + 1, dtype=np.int32) * steps), words.take(pa.array(mine.ravel())))
                yield pa.RecordBatch.from_arrays([b.column(1), toks], ["id", "generated"])

        return rows.select("n", "id").mapInArrow(told, "id string, generated array<string>")


def make(docs: DataFrame, say) -> Packed | None:
    """The decoding table of docs(text), split at white space; None if the vocabulary is too large to travel."""
    known = vocabulary(docs)
    return Packed(docs, say, known) if known else None
