"""Line dedup: repeated runs of lines found in a suffix array over line ids.

The corpus is one sequence of lines for each document. Lines that occur once end every
repeat, so only the others take part. Their suffixes are sorted by prefix doubling: the rank
by one line is the place of its id, the rank by 2k lines the place of the pair of ranks by k
lines at a line and k lines on. Each round numbers the distinct pairs by a distributed sort,
keeps ranks only of pairs that occur again, and ends when no pair does.

Suffixes whose first lines agree over a window are one interval of the suffix array (its
longest common prefix reaches the window), told by the ranks of the two power-of-two blocks
that cover the window. For each line the windows asked for are the shortest one of at least
`min_words` words that starts there and the shortest that ends there. Of an interval's
occurrences the first in document order stays and the lines of the others go: the union of
those windows is exactly the maximal repeated runs of at least `min_words` words.

Defined results: lines are compared without white space at their ends; blank lines count for
nothing and stay; null text is the empty text; a document never loses its row, only lines;
documents that share an id are told apart by a text hash, and rows that share both lose the
same lines; a repeat that overlaps itself (one line many times over) leaves only the lines
before its second start; an empty table gives
an empty result; other columns are carried along.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common as C

MIN_WORDS = 40


def lines_of(text: Column) -> Column:
    """The lines that are not blank: array of (at: number among all lines, line)."""
    every = F.transform(F.split(text, "\n", -1), lambda x, i: F.struct(i.alias("at"), F.btrim(x, F.lit(" \t\r\x0b\x0c")).alias("line")))
    return F.filter(every, lambda x: x["line"] != "")


def repeated_lines(docs: DataFrame) -> DataFrame:
    """(doc_id, _h, i, w, r0): each line that occurs again, its words, and its rank by one line."""
    text = C.text_or_empty("text")
    d = docs.select("doc_id", F.xxhash64("text").alias("_h"), F.posexplode(lines_of(text)).alias("i", "_x"))
    d = d.select("doc_id", "_h", "i", F.xxhash64("_x.line").alias("_a"), F.xxhash64(F.lit(3), "_x.line").alias("_b"), F.regexp_count("_x.line", F.lit(C.WORD)).cast("int").alias("w"))
    d = C.cut(d.distinct())
    twice = d.groupBy("_a", "_b").agg(F.count(F.lit(1)).alias("_n")).where("_n > 1").select("_a", "_b")
    ranks = C.cut(C.global_index(twice, [F.col("_a"), F.col("_b")], "r0"))
    return C.cut(d.join(C.maybe_broadcast(ranks), ["_a", "_b"]).select("doc_id", "_h", "i", "w", "r0"))


def suffix_ranks(lines: DataFrame, most: int) -> tuple[DataFrame, int]:
    """`lines` with r1, r2, ...: ranks of its suffixes by 2, 4, ... lines, at most `most` lines; and how many."""
    order = Window.partitionBy("doc_id", "_h").orderBy("i")
    k, level = 1, 0
    while 2 * k <= most:
        r, new = f"r{level}", f"r{level + 1}"
        # k rows on is k lines on where no line between is missing
        on = F.when(F.lead("i", k).over(order) == F.col("i") + k, F.lead(r, k).over(order))
        pairs = C.cut(lines.withColumn("_on", on))
        again = pairs.where(f"{r} is not null and _on is not null").groupBy(r, "_on").agg(F.count(F.lit(1)).alias("_n")).where("_n > 1").select(F.col(r).alias("_p"), F.col("_on").alias("_q"))
        ranks = C.cut(C.global_index(again, [F.col("_p"), F.col("_q")], new))
        if ranks.limit(1).count() == 0:
            break
        lines = C.cut(pairs.join(C.maybe_broadcast(ranks), (F.col(r) == F.col("_p")) & (F.col("_on") == F.col("_q")), "left").drop("_p", "_q", "_on"))
        k, level = 2 * k, level + 1
    return lines, level + 1


def _windows(i: np.ndarray, doc: np.ndarray, w: np.ndarray, ranks: list[np.ndarray], least: int) -> tuple:
    """(start, length, rank of the first block, rank of the last block) of the shortest windows of `least` words."""
    n = len(i)
    new = np.r_[True, (doc[1:] != doc[:-1]) | (i[1:] != i[:-1] + 1)]
    first = np.flatnonzero(new)
    stretch = np.cumsum(new) - 1
    end = np.r_[first[1:], n][stretch]
    total = np.r_[0, np.cumsum(w)]
    at = np.arange(n)
    stop = np.searchsorted(total, total[:-1] + least, side="left")  # forward: lines at..stop-1
    fits = stop <= end
    s1, m1 = at[fits], (stop - at)[fits]
    start = np.searchsorted(total, total[1:] - least, side="right") - 1  # backward: lines start..at
    fits = start >= first[stretch]
    s2, m2 = start[fits], (at + 1 - start)[fits]
    both = np.unique(np.stack([np.r_[s1, s2], np.r_[m1, m2]], axis=1), axis=0)
    s, m = both[:, 0], both[:, 1]
    level = np.floor(np.log2(np.maximum(m, 1))).astype(int)
    known = level < len(ranks)
    s, m, level = s[known], m[known], level[known]
    table = np.stack(ranks)
    a, b = table[level, s], table[level, s + m - (1 << level)]
    again = (a >= 0) & (b >= 0)
    return s[again], m[again], a[again], b[again]


def removed_lines(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(doc_id, _h, gone array<int>): numbers, among lines that are not blank, of the lines that repeat an earlier run."""
    ranked, levels = suffix_ranks(repeated_lines(docs), min_words)
    kind = docs.schema["doc_id"].dataType.simpleString()
    names = [f"r{k}" for k in range(levels)]

    def windows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = None
        for b in batches:
            b = b if held is None else pd.concat([held, b], ignore_index=True)
            if not len(b):
                continue
            doc = (b["_h"].ne(b["_h"].shift()) | (b["doc_id"].ne(b["doc_id"].shift()) & ~(b["doc_id"].isna() & b["doc_id"].shift().isna()))).cumsum().to_numpy()
            last = int(np.searchsorted(doc, doc[-1]))
            held = b.iloc[last:]
            if last:
                yield found(b.iloc[:last], doc[:last])
        if held is not None and len(held):
            yield found(held, np.zeros(len(held)))

    def found(b: pd.DataFrame, doc: np.ndarray) -> pd.DataFrame:
        ranks = [b[n].fillna(-1).to_numpy().astype(np.int64) for n in names]
        s, m, x, y = _windows(b["i"].to_numpy(), doc, b["w"].to_numpy().astype(np.int64), ranks, min_words)
        return pd.DataFrame({"doc_id": b["doc_id"].array[s], "_h": b["_h"].to_numpy()[s], "i": b["i"].to_numpy()[s], "m": m, "x": x, "y": y})

    dealt = ranked.repartition(C.partitions(docs.sparkSession), "doc_id", "_h").sortWithinPartitions("doc_id", "_h", "i")
    asked = C.cut(dealt.mapInPandas(windows, f"doc_id {kind}, _h long, i int, m int, x long, y long"))
    place = F.struct("doc_id", "_h", "i")
    # one row an interval is a side of its own: it travels if it fits, else the join may split an interval with very many places
    first = C.cut(asked.groupBy("m", "x", "y").agg(F.min(place).alias("_first"), F.count(F.lit(1)).alias("_n")).where("_n > 1").drop("_n"))
    later = asked.join(C.maybe_broadcast(first), ["m", "x", "y"]).where(~place.eqNullSafe(F.col("_first")))
    gone = later.select("doc_id", "_h", F.explode(F.sequence(F.col("i"), F.col("i") + F.col("m") - 1)).alias("i")).distinct()
    return gone.groupBy("doc_id", "_h").agg(F.sort_array(F.collect_list("i")).alias("gone"))


@C.carrying("doc_id", "text")
def deduplicate(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """`docs` without the lines of later copies, with n_lines and n_removed."""
    gone = C.cut(removed_lines(docs, min_words).select(F.col("doc_id").alias("_id"), F.col("_h").alias("_hh"), "gone"))
    j = docs.withColumn("_h", F.xxhash64("text")).join(C.maybe_broadcast(gone), F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_h") == F.col("_hh")), "left")

    @F.pandas_udf("string")
    def without(text: pd.Series, gone: pd.Series) -> pd.Series:
        return pd.Series([None if t is None else _without(t, g) for t, g in zip(text, gone)], dtype=object)

    # only texts that lose lines are sent to Python
    lost = F.col("gone").isNotNull()
    j = j.withColumn("_new", without(F.when(lost, F.col("text")), "gone"))
    j = j.withColumn("n_removed", F.when(lost, F.size("gone")).otherwise(0)).withColumn("text", F.when(lost, F.col("_new")).otherwise(F.col("text")))
    return j.drop("_id", "_hh", "_h", "_new", "gone")


def _without(text: str, gone) -> str:
    out, gone, n = [], set(gone), 0
    for line in text.split("\n"):
        full = line.strip(" \t\r\x0b\x0c") != ""
        if not (full and n in gone):
            out.append(line)
        n += full
    return "\n".join(out)


def op5_linededup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with the number of lines that went, and length and SHA-256 of the text that is left."""
    docs = C.table(spark, sf_dir, "documents").select("doc_id", "text")
    out = deduplicate(docs)
    return out.select("doc_id", F.col("n_removed").cast("long").alias("n_removed"), F.length("text").cast("long").alias("kept_chars"), F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))


def oracle(min_words: int = MIN_WORDS) -> str:
    """A plain reading of the same rule: every window spelled out as text, without ranks."""
    trim = r"trim(x, ' ' || chr(9) || chr(13) || chr(11) || chr(12))"
    return rf"""
WITH a AS (SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents),
e AS (SELECT doc_id, unnest(ls) AS x, generate_subscripts(ls, 1) AS ln FROM a),
l AS (SELECT doc_id, ln, row_number() OVER (PARTITION BY doc_id ORDER BY ln) AS i, {trim} AS line, len(regexp_extract_all({trim}, '[^\x20\x09-\x0D]+')) AS w FROM e WHERE {trim} <> ''),
c AS (SELECT *, sum(w) OVER (PARTITION BY doc_id ORDER BY i) AS c FROM l),
f AS (SELECT a.doc_id, a.i AS s, min(b.i) AS t FROM c a JOIN c b ON a.doc_id = b.doc_id AND b.i >= a.i AND b.c - a.c + a.w >= {min_words} GROUP BY ALL),
g AS (SELECT a.doc_id, max(b.i) AS s, a.i AS t FROM c a JOIN c b ON a.doc_id = b.doc_id AND b.i <= a.i AND a.c - b.c + b.w >= {min_words} GROUP BY ALL),
u AS (SELECT * FROM f UNION SELECT doc_id, s, t FROM g),
k AS (SELECT u.doc_id, u.s, u.t, string_agg(c.line, chr(10) ORDER BY c.i) AS body FROM u JOIN c ON c.doc_id = u.doc_id AND c.i BETWEEN u.s AND u.t GROUP BY ALL),
p AS (SELECT *, min((doc_id, s)) OVER (PARTITION BY body) AS first_place FROM k),
r AS (SELECT DISTINCT c.doc_id, c.ln FROM p JOIN c ON c.doc_id = p.doc_id AND c.i BETWEEN p.s AND p.t WHERE (p.doc_id, p.s) <> p.first_place),
o AS (SELECT e.doc_id, string_agg(x, chr(10) ORDER BY e.ln) FILTER (r.ln IS NULL) AS kept, count(r.ln) AS n FROM e LEFT JOIN r ON r.doc_id = e.doc_id AND r.ln = e.ln GROUP BY e.doc_id)
SELECT doc_id, n::BIGINT AS n_removed, length(coalesce(kept, ''))::BIGINT AS kept_chars, sha256(coalesce(kept, '')) AS kept_sha256 FROM o
"""
