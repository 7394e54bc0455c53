"""Toxicity: noisy-channel restoration of disguised words, then a score of the restored text.

1. A character language model (trigrams of letters inside words) is counted over all texts.
2. Tokens that may be disguised (letters mixed with look-alike signs, letters repeated, single
   letters spaced out) are read as lattices: each sign may be one of several letters or stay,
   each repeat may shrink to one or two letters or stay, each gap may close or stay. Viterbi
   finds the reading that is likeliest under the language model and the channel's costs. A
   token with one reading only needs no search.
3. Words of restored labelled texts get smoothed log-odds for toxicity from the counts of
   rows that hold them or a word that begins alike. A text is scored from its strongest words alone, by
   logistic regression, so neither its length nor its language matters much.

Labels are read only for the fit: at most MAX_LABELLED rows of each kind, those whose ids have
the smallest hashes. Labels, language, source and id are no input of a score.

Defined results: null is the empty text; empty texts score as texts without a strong word do;
rows that repeat an id are scored apart; without labels of both kinds every score is the share
of toxic labels (0 without labels); an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common as C

THRESHOLD = 0.7
#: Labelled rows of each kind for the fit at most; strongest words that count; toxic rows that a word needs.
MAX_LABELLED, TOP, LEAST_ROWS = 2_000, 4, 3

# Letters that a sign is used for.
SIGNS = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "€": "e", "(": "c", "2": "z", "6": "g"}
LETTERS = "abcdefghijklmnopqrstuvwxyzßàáâãäåæçèéêëìíîïñòóôõöøùúûüœ"
EDGE, OTHER = 0, len(LETTERS) + 1
N = OTHER + 1

#: Costs (negative log-probabilities) of the channel: reading a sign as a letter, keeping a sign, shrinking a repeat, keeping it, closing a gap, keeping it.
AS_LETTER, AS_SIGN, SHRINK, STAY, CLOSE, KEEP = 1.0, 7.0, 0.7, 7.0, 0.7, 1.5

_WORD = re.compile(r"[^\W\d_]+")
_code = np.zeros(0x250, dtype=np.uint8)
for _k, _c in enumerate(LETTERS):
    _code[ord(_c)] = _k + 1
for _o in range(0x250):
    if not _code[_o] and chr(_o).isalpha() and chr(_o).lower() == chr(_o):
        _code[_o] = OTHER


def codes(text: str) -> np.ndarray:
    """A number for each character of a lower-case text: its letter's, OTHER for other letters, EDGE for the rest."""
    u = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype="<u4")
    return np.where(u < 0x250, _code[np.minimum(u, 0x24F)], np.uint8(EDGE))


_is_sign = np.zeros(0x250, dtype=bool)
_is_word = np.array([chr(o).isalnum() or o == 95 for o in range(0x250)])
for _c in SIGNS:
    if ord(_c) < 0x250:
        _is_sign[ord(_c)] = True
_is_space = np.array([chr(o).isspace() for o in range(0x250)])
_FAR_SPACES = np.array([o for o in range(0x250, 0x10000) if chr(o).isspace()], dtype="<u4")
_is_gap = np.zeros(0x250, dtype=bool)
_is_gap[[ord(c) for c in " .-_*"]] = True


def suspects(low: str) -> set[str]:
    """Tokens of a lower-case text with more than one reading: a sign next to a letter (not a long tail of signs), a letter three times, or three or more single letters with one gap character between."""
    u = np.frombuffer(low.encode("utf-32-le", "surrogatepass"), dtype="<u4")
    if len(u) < 3:
        return set()
    u = np.r_[u, np.full(4, 32, dtype="<u4")]
    k = np.minimum(u, 0x24F)
    letter, sign, word, gap = _code[k] > 0, _is_sign[k], _is_word[k], _is_gap[k]
    n = len(low)
    mixed = (sign[:n] & letter[1 : n + 1]) | (letter[:n] & sign[1 : n + 1] & ~(sign[2 : n + 2] & sign[3 : n + 3]))
    again = letter[:n] & (u[:n] == u[1 : n + 1]) & (u[:n] == u[2 : n + 2])
    out = set()
    space = np.flatnonzero(_is_space[k[:n]] | ((u[:n] >= 0x250) & np.isin(u[:n], _FAR_SPACES)))
    # whole tokens, each once however many of its characters are suspect
    for t in np.unique(np.searchsorted(space, np.flatnonzero(mixed | again))).tolist():
        left, right = (space[t - 1] + 1 if t else 0), (space[t] if t < len(space) else n)
        out.add(low[left:right].rstrip("!|+(.,;:?"))
    alone = (letter | sign)[:n] & ~np.r_[False, word[: n - 1]] & ~word[1 : n + 1]
    step = np.r_[alone, np.zeros(4, dtype=bool)]
    # from one single letter to the next over one gap character: a stretch goes as far as that goes on
    on = alone & gap[1 : n + 1] & step[2 : n + 2]
    off = [np.flatnonzero(~on[p::2]) for p in (0, 1)]
    done = -1
    for at in np.flatnonzero(on & gap[3 : n + 3] & step[4 : n + 4]).tolist():
        if at <= done:
            continue
        stops = off[at % 2]
        end = 2 * int(stops[np.searchsorted(stops, at // 2)]) + at % 2
        out.add(low[at : end + 1])
        done = end
    return out


def trigram_counts(docs: DataFrame) -> np.ndarray:
    """Counts [a, b, c] of letters c after a, b over all docs(text); N cubed numbers at most reach the driver."""

    def count(total: np.ndarray, parts: list[np.ndarray]) -> None:
        # two edges before and one after each word; runs of edges count like one
        x = np.concatenate(parts).astype(np.int64)
        x = np.r_[EDGE, EDGE, x[(x > 0) | (np.r_[1, x[:-1]] > 0)], EDGE]
        y = np.where((x[:-1] == EDGE), EDGE, np.r_[EDGE, x[:-2]])
        total += np.bincount((y[:-1] * N + x[:-2]) * N + x[1:-1], minlength=N**3)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, parts, size = np.zeros(N**3, dtype=np.int64), [], 0
        for b in batches:
            for x in b.column("text"):
                t = x.as_py()
                parts += [codes(t.lower()), np.zeros(1, dtype=np.uint8)]
                size += len(t)
                if size > 1 << 18:  # a bin count costs N cubed: many texts share one
                    count(total, parts)
                    parts, size = [], 0
        if parts:
            count(total, parts)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], ["k", "n"])

    got = docs.select(C.text_or_empty("text").alias("text")).mapInArrow(run, "k int, n long").groupBy("k").agg(F.sum("n").alias("n")).toPandas()
    out = np.zeros(N**3)
    out[got["k"].to_numpy()] = got["n"].to_numpy()
    return out.reshape(N, N, N)


class LanguageModel:
    """Costs of a letter after two others, interpolated with shorter contexts."""

    def __init__(self, counts: np.ndarray):
        one = counts.sum(axis=(0, 1)) + 1.0
        p1 = one / one.sum()
        two = counts.sum(axis=0)
        p2 = (two + 5 * p1) / (two.sum(axis=1, keepdims=True) + 5)
        p3 = (counts + 5 * p2) / (counts.sum(axis=2, keepdims=True) + 5)
        self.cost = (-np.log(p3)).tolist()


def _lattice(token: str) -> list[list[tuple[str, float]]]:
    """For each place, the strings it may stand for and what each costs."""
    runs = [(m.group(0)[0], len(m.group(0))) for m in re.finditer(r"(.)\1*", token, re.S)]
    spaced = bool(re.fullmatch(r"(?:[^\W_]|[^\w\s])(?:[ .\-_*](?:[^\W_]|[^\w\s]))+[ .\-_*]?", token))
    out: list[list[tuple[str, float]]] = []
    for c, n in runs:
        if c.isspace() or (spaced and c in ".-_*"):
            out.append([("", CLOSE), (" ", KEEP)] if spaced and n == 1 else [(" ", 0.0)])
        elif c in SIGNS:
            ways = [(x * min(n, 2) if n < 3 else x, AS_LETTER * min(n, 2)) for x in SIGNS[c]]
            out.append([*ways, (" ", AS_SIGN)])
        elif c.isalpha():
            out.append([(c * n, 0.0)] if n == 1 else [(c * n, 0.0), (c, 3.0)] if n == 2 else [(c, SHRINK), (c * 2, 2 * SHRINK), (c * n, STAY)])
        else:
            out.append([(" ", 0.0)])
    return out


def _spell(cost, x: int, y: int, s: str) -> tuple[float, int, int]:
    """(cost, last two letters) of saying `s` after the letters x, y. A long repeat is settled after its second letter."""
    if len(s) > 3 and s == s[0] * len(s):
        total, x, y = _spell(cost, x, y, s[:2])
        each, x, y = _spell(cost, x, y, s[0])
        return total + each * (len(s) - 2), x, y
    total = 0.0
    for ch in s:
        k = int(_code[ord(ch)]) if ord(ch) < 0x250 else (OTHER if ch.isalpha() else EDGE)
        if k == EDGE and y == EDGE:
            continue
        total += cost[x][y][k]
        x, y = (EDGE, EDGE) if k == EDGE else (y, k)
    return total, x, y


def restore(token: str, lm: LanguageModel) -> str:
    """The likeliest reading of a whole token: Viterbi over its lattice, with the last two letters as states. Readings are kept as links to what came before, so long tokens take time in proportion; of equal costs the first found stays."""
    states: dict[tuple[int, int], tuple[float, tuple | None]] = {(EDGE, EDGE): (0.0, None)}
    for ways in [*_lattice(token), [(" ", 0.0)]]:
        new: dict[tuple[int, int], tuple[float, tuple | None]] = {}
        for (a, b), (cost, said) in states.items():
            for s, extra in ways:
                more, x, y = _spell(lm.cost, a, b, s)
                total = cost + extra + more
                if (x, y) not in new or total < new[(x, y)][0]:
                    new[(x, y)] = (total, (said, s))
        states = new
    link, parts = min(states.items(), key=lambda kv: (kv[1][0], kv[0]))[1][1], []
    while link is not None:
        link, s = link
        parts.append(s)
    return "".join(reversed(parts)).strip()


def restorer(lm: LanguageModel):
    """text -> set of words of the restored text."""
    read = lambda t: tuple(_WORD.findall(restore(t, lm)))
    cached = lru_cache(maxsize=20_000)(read)

    def words(text: str) -> set[str]:
        low = text.lower()
        found = set(_WORD.findall(low))
        for t in suspects(low):
            found.update(cached(t) if len(t) <= 256 else read(t))  # long tokens seldom come again
        return found

    return words


def _grams(word: str) -> set[str]:
    """The word, and its beginnings of four to eight characters (the edge included)."""
    w = f"^{word}$"
    return {w, *(w[:k] for k in range(5, min(9, len(w)) + 1))}


class Model:
    """Log-odds of words and beginnings, and weights of a text's strongest words."""

    def __init__(self, texts: list[tuple[str, int]], share: float):
        """texts: (words joined by spaces, label)."""
        self.share, self.weights, self.odds = share, None, {}
        y = np.array([t[1] for t in texts], dtype=float)
        if not len(y) or y.min() == y.max():
            return
        # words and features get numbers, so that a row is a small array
        features: dict[str, int] = {}
        of_word: dict[str, np.ndarray] = {}
        rows = []
        for words, _ in texts:
            mine = [of_word[w] if w in of_word else of_word.setdefault(w, np.array([features.setdefault(g, len(features)) for g in _grams(w)], dtype=np.int32)) for w in words.split()]
            rows.append(np.unique(np.concatenate(mine)) if mine else np.zeros(0, dtype=np.int32))
        toxic, clean = np.zeros(len(features)), np.zeros(len(features))
        for r, label in zip(rows, y):
            (toxic if label else clean)[r] += 1
        n1, n0 = y.sum(), len(y) - y.sum()

        def odds(a: np.ndarray, b: np.ndarray) -> np.ndarray:
            return np.where(a >= LEAST_ROWS, np.log((np.maximum(a, 0) + 0.1) / (n1 + 0.2)) - np.log((np.maximum(b, 0) + 0.5 * n0 / n1) / (n0 + n0 / n1)), 0.0)

        every = odds(toxic, clean)
        self.odds = {g: float(every[k]) for g, k in features.items() if every[k] > 0.7}
        # each labelled text is scored without what it says itself, else the fit would trust words too much
        rid = [(odds(toxic - 1, clean), odds(toxic, clean - 1))[label] for label in (0, 1)]
        x = [self._features([float(rid[int(1 - label)][of_word[w]].max()) for w in words.split()]) for words, label in texts]
        x = np.array(x)
        a = np.c_[x, np.ones(len(x))]
        w = np.zeros(a.shape[1])
        balance = np.where(y == 1, share * len(y) / n1, (1 - share) * len(y) / n0)
        for _ in range(50):  # Newton steps of a ridge-penalised fit, at the share that labels have
            p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
            g = a.T @ (balance * (p - y)) + 0.05 * np.r_[w[:-1], 0]
            h = (a * (balance * p * (1 - p))[:, None]).T @ a + 0.05 * np.eye(len(w))
            step = np.linalg.solve(h, g)
            w -= step
            if np.abs(step).max() < 1e-9:
                break
        self.weights = w

    @staticmethod
    def _features(odds: list[float]) -> list[float]:
        """The largest log-odds, and what the first has above 2 and 4: few words of clean texts come there."""
        best = sorted(odds, reverse=True)[:TOP]
        best += [0.0] * (TOP - len(best))
        return [*best, max(0.0, best[0] - 2), max(0.0, best[0] - 4)]

    @staticmethod
    def _word(word: str, odds: dict[str, float]) -> float:
        return max((odds.get(g, 0.0) for g in _grams(word)), default=0.0)

    def scorer(self, words_of):
        word = lru_cache(maxsize=50_000)(lambda w: Model._word(w, self.odds))

        def score(text: str) -> float:
            if self.weights is None:
                return self.share
            x = self._features(list(map(word, words_of(text))))
            return float(1 / (1 + np.exp(-np.clip(np.dot(self.weights[:-1], x) + self.weights[-1], -30, 30))))

        return score


@C.carrying("doc_id", "text")
def keep_clean(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of `docs` that score below the threshold."""
    return score(docs, labels, out="_toxicity").where(F.col("_toxicity") < THRESHOLD).drop("_toxicity")


def held_out(doc_id="doc_id"):
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")) % 3 == 1


def fit(docs: DataFrame, labels: DataFrame, most: int = MAX_LABELLED) -> tuple[LanguageModel, Model]:
    """The language model of docs(text), and the model of the labels (doc_id, toxic) that may be learnt."""
    lm = LanguageModel(trigram_counts(docs))
    known = C.cut(labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic")).join(docs.select("doc_id"), "doc_id", "left_semi"))
    n = {r["toxic"]: r["n"] for r in known.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    total = sum(n.values())
    picked = [known.where(F.col("toxic") == t).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most) for t in (0, 1)]
    picked = F.broadcast(picked[0].unionByName(picked[1]))

    def restored(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        words = restorer(lm)
        for b in batches:
            yield pd.DataFrame({"toxic": b["toxic"], "words": [" ".join(sorted(words(t))) for t in b["text"]]})

    rows = docs.select("doc_id", C.text_or_empty("text").alias("text")).join(picked, "doc_id").select("toxic", "text").mapInPandas(restored, "toxic int, words string").collect()
    texts = sorted((r["words"], r["toxic"]) for r in rows)
    return lm, Model(texts, n.get(1, 0) / total if total else 0.0)


@C.carrying("doc_id", "text")
def score(docs: DataFrame, labels: DataFrame, most: int = MAX_LABELLED, out: str = "score") -> DataFrame:
    """`docs` with its score, double, as the column `out`."""
    lm, model = fit(docs, labels, most)
    sent = docs.sparkSession.sparkContext.broadcast((lm, model))

    @F.arrow_udf("double")
    def scored(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        lm, model = sent.value
        one = model.scorer(restorer(lm))
        for b in batches:
            yield pa.array([one(t.as_py()) for t in b], pa.float64())
        del one
        C.give_back()

    return docs.withColumn(out, scored(C.text_or_empty("text")))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = score(C.table(spark, sf_dir, "documents").select("doc_id", "text"), C.table(spark, sf_dir, "labels"))
    return out.select("doc_id", held_out().alias("held_out"), "score", F.when(F.col("score") >= THRESHOLD, 1).otherwise(0).cast("int").alias("predicted"))
