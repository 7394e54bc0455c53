"""Byte-level BPE encoding and decoding of whole texts, long ones in overlapping chunks.

A text longer than CHUNK characters is cut into chunk rows, each with OVERLAP characters of
the next chunk, that are dealt over the cluster. Each chunk pre-tokenises its overlaps: the
first pre-token boundary there that has white space after it and none before is where two
neighbours resynchronise, because no pre-token runs from a character that is not white space
into one that is, whatever stands before. Pieces between such boundaries are encoded alone,
stitched by number; decoding concatenates the bytes of the ids. A text with a chunk that
finds no such boundary is encoded whole, so results never depend on the chunk size.

Defined results: null is the empty text, which has no ids and no bytes; ids that repeat, tie
or are null are kept apart by row; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import pandas as pd
import public_tokenizers
import pyarrow as pa
import regex
import tiktoken
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

CHUNK, OVERLAP = 1 << 15, 1 << 10
VOCABULARY = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")

_known: dict = {}


def encoding(lines: bytes, pattern: str) -> tuple[tiktoken.Encoding, list[str]]:
    """The encoding of a rank file's content, and each id as decimal text; built once in a worker."""
    key = hash((lines, pattern))
    if key not in _known:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines.splitlines())}
        _known[key] = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}), list(map(str, range(max(ranks.values()) + 1)))
    return _known[key]


def resync(zone: str, pattern: str) -> int | None:
    """Where pre-tokens of the zone, started at its first character, are in step with any other start."""
    for m in regex.finditer(pattern, zone):
        if m.end() < len(zone) and zone[m.end()] in " \t\r\n" and not zone[m.end() - 1].isspace():
            return m.end()
    return None


def _digest(ids: list[int], enc: tiktoken.Encoding, names: list[str]) -> tuple[int, str, str]:
    return len(ids), hashlib.sha256(",".join([names[i] for i in ids]).encode()).hexdigest(), hashlib.sha256(enc.decode_bytes(ids)).hexdigest()


def _piece(text: str, first: bool, last: bool, chunk: int, pattern: str) -> str | None:
    """A chunk's own piece: from its resynchronised start to that of the next chunk."""
    start = 0 if first else resync(text[:chunk], pattern)
    end = len(text) if last else resync(text[chunk:], pattern)
    return None if start is None or end is None else text[start : len(text) if last else chunk + end]


def encode(docs: DataFrame, keep: list[str], vocabulary: str = VOCABULARY, pattern: str = public_tokenizers.PATTERN, chunk: int = CHUNK, overlap: int = OVERLAP, with_ids: bool = True) -> DataFrame:
    """`keep` columns, n_tokens, ids_sha256, decoded_sha256 and, if wanted, ids (array<int>) of each row's text."""
    with open(vocabulary, "rb") as f:
        lines = docs.sparkSession.sparkContext.broadcast(f.read())
    assert overlap <= chunk
    text = C.text_or_empty("text")
    kept = docs.select(*[F.col(c).alias(f"_k{i}") for i, c in enumerate(keep)], text.alias("_text"), F.length(text).alias("_len"))
    own = ", ".join(f"_k{i} {docs.schema[c].dataType.simpleString()}" for i, c in enumerate(keep))
    out = f"{own}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    names = [f"_k{i}" for i in range(len(keep))]

    def finish(keys: dict, tokens: list[list[int]], enc, texts) -> pd.DataFrame:
        said = [_digest(t, enc, texts) for t in tokens]
        cols = dict(keys) | {n: [x[k] for x in said] for k, n in enumerate(("n_tokens", "ids_sha256", "decoded_sha256"))}
        return pd.DataFrame(cols | ({"ids": tokens} if with_ids else {}))

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, texts = encoding(lines.value, pattern)
        for b in batches:
            for at in range(0, b.num_rows, 64):  # ids of few texts at once are in memory
                part = b.slice(at, 64)
                tokens = [enc.encode_ordinary(t.as_py()) for t in part.column("_text")]
                said = [_digest(t, enc, texts) for t in tokens]
                made = [pa.array([x[0] for x in said], pa.int64()), pa.array([x[1] for x in said], pa.string()), pa.array([x[2] for x in said], pa.string())]
                made += [pa.array(tokens, pa.list_(pa.int32()))] * with_ids
                yield pa.RecordBatch.from_arrays([*(part.column(n) for n in names), *made], [*names, "n_tokens", "ids_sha256", "decoded_sha256", *["ids"] * with_ids])
        C.give_back()

    def pieces(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        enc, _ = encoding(lines.value, pattern)
        for b in batches:
            for row, k, n, t in zip(b["_row"], b["_c"], b["_n"], b["_part"]):
                p = _piece(t, k == 0, k == n - 1, chunk, pattern)
                yield pd.DataFrame({"_row": [row], "_c": [k], "_ok": [p is not None], "_ids": [[] if p is None else enc.encode_ordinary(p)]})

    def stitch(group: pd.DataFrame) -> pd.DataFrame:
        enc, texts = encoding(lines.value, pattern)
        group = group.sort_values("_c")
        return finish({n: group[n].iloc[:1].array for n in names}, [[i for ids in group["_ids"] for i in ids]], enc, texts)

    short = kept.where(F.col("_len") <= chunk).select(*names, "_text").mapInArrow(whole, out)
    # rows get their number before chunks are dealt, and both are cut off: a retry can't renumber them
    long = kept.where(F.col("_len") > chunk).withColumn("_row", F.monotonically_increasing_id())
    long = long.withColumn("_n", F.ceil(F.col("_len") / chunk).cast("int")).select(*names, "_row", "_n", "_text", F.explode(F.sequence(F.lit(0), F.col("_n") - 1)).alias("_c"))
    parts = long.select(*names, "_row", "_n", "_c", F.substr("_text", F.col("_c") * chunk + 1, F.lit(chunk + overlap)).alias("_part"))
    parts = C.cut(parts.repartition(C.partitions(docs.sparkSession)))
    done = C.cut(parts.select("_row", "_c", "_n", "_part").mapInPandas(pieces, "_row long, _c int, _ok boolean, _ids array<int>"))
    lost = done.where("not _ok").select("_row").distinct()
    firsts = parts.where("_c = 0").select("_row", *names)
    good = done.join(lost, "_row", "left_anti").join(firsts, "_row").groupBy("_row").applyInPandas(stitch, out)

    def mend(group: pd.DataFrame) -> pd.DataFrame:
        enc, texts = encoding(lines.value, pattern)
        t = "".join(p[:chunk] for p in group.sort_values("_c")["_part"])
        return finish({n: group[n].iloc[:1].array for n in names}, [enc.encode_ordinary(t)], enc, texts)

    again = parts.join(lost, "_row", "left_semi").groupBy("_row").applyInPandas(mend, out)
    every = short.unionByName(good).unionByName(again)
    return every.select(*[F.col(f"_k{i}").alias(c) for i, c in enumerate(keep)], "n_tokens", "ids_sha256", "decoded_sha256", *(["ids"] if with_ids else []))


def decode(ids: DataFrame, vocabulary: str = VOCABULARY, pattern: str = public_tokenizers.PATTERN) -> DataFrame:
    """`ids` (any columns and ids array<int>) with `bytes` binary: the bytes of each id, one after the other."""
    with open(vocabulary, "rb") as f:
        lines = ids.sparkSession.sparkContext.broadcast(f.read())

    @F.pandas_udf("binary")
    def joined(col: pd.Series) -> pd.Series:
        enc, _ = encoding(lines.value, pattern)
        return col.map(lambda x: b"" if x is None else enc.decode_bytes(list(x)))

    return ids.withColumn("bytes", joined("ids"))


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(C.table(spark, sf_dir, "documents"), ["doc_id"], with_ids=False)
