"""Copying watched as outputs arrive: windows, joins and state over streams.

Streams are read from files with a declared schema. Event times are cast to `timestamp`, since
a watermark can't be set on a time without zone. Chunks of a conversation may arrive in any
order, over any number of batches: state keeps stretches of turns that follow each other, each
with its first and last n - 1 tokens, and joins them once what lies between has come.
"""

from __future__ import annotations

import json
from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.text import grams, tokens
from ..plans.store import new_path, small


def read_stream(spark: SparkSession, path: str, schema, time: str | None = None, files: int = 1, glob: str | None = None) -> DataFrame:
    """A stream of the Parquet files in a folder whose names fit `glob`."""
    r = spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    df = (r.option("pathGlobFilter", glob) if glob else r).parquet(path)
    return df.withColumn(time, F.col(time).cast("timestamp")) if time else df


def read_table(spark: SparkSession, path: str, name: str, schema, time: str | None = None, files: int = 1) -> DataFrame:
    """A stream of a table's files, be it one file or a folder of them: the source lists folders only, and its glob is for the names of files."""
    at = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/{name}.parquet")
    if at.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(at).isDirectory():
        return read_stream(spark, f"{path}/{name}.parquet", schema, time, files)
    return read_stream(spark, path, schema, time, files, f"{name}.parquet")


def tumbling(df: DataFrame, time: str, width: str, late: str | None, *by: str) -> DataFrame:
    d = df.withWatermark(time, late) if late else df
    return d.groupBy(F.window(time, width), *by).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sliding(df: DataFrame, time: str, width: str, step: str, late: str | None, *by: str) -> DataFrame:
    d = df.withWatermark(time, late) if late else df
    return d.groupBy(F.window(time, width, step), *by).agg(F.count(F.lit(1)).alias("n"))


def sessions(df: DataFrame, time: str, gap: str, late: str | None, user: str) -> DataFrame:
    d = df.withWatermark(time, late) if late else df
    return d.groupBy(F.session_window(time, gap), user).agg(F.count(F.lit(1)).alias("n"))


def once(df: DataFrame, keys: list[str], time: str, late: str) -> DataFrame:
    """Rows that come again within the watermark go; state older than it goes too."""
    return df.withWatermark(time, late).dropDuplicatesWithinWatermark(keys)


def copied_outputs(outputs: DataFrame, corpus: DataFrame, n: int = 11) -> DataFrame:
    """Outputs of a stream with an n-gram of the (static) corpus: (output_id, ts, gram)."""
    have = corpus.select(F.explode(grams("tk", n)).alias("gram")).distinct()
    d = outputs.withColumn("tk", tokens("text")).select("output_id", "ts", F.explode(grams("tk", n)).alias("gram"))
    return d.join(have, "gram", "left_semi")


def overlap_online(prompts: DataFrame, outputs: DataFrame, within: str = "5 minutes", late: str | None = "10 minutes") -> DataFrame:
    """Stream-stream join: each output with the prompt of its conversation at most `within` before it. Without `late` no row is too late, whatever the order of the files, and state keeps all rows: for streams that are drained."""
    p = prompts.withColumnsRenamed({"ts": "p_ts", "conv_id": "p_conv"})
    p, o = (p.withWatermark("p_ts", late), outputs.withWatermark("ts", late)) if late else (p, outputs)
    return o.join(p, F.expr(f"conv_id = p_conv AND ts >= p_ts AND ts <= p_ts + INTERVAL {within}"))


class Stretch:
    """Turns that follow each other: the first and last n - 1 tokens of what they say, and how many turns."""

    def __init__(self, first: int, last: int, head: list[str], tail: list[str], size: int):
        self.first, self.last, self.head, self.tail, self.size = first, last, head, tail, size

    @classmethod
    def of(cls, turn: int, words: list[str], n: int) -> Stretch:
        return cls(turn, turn, words[: n - 1], words[max(0, len(words) - n + 1) :], len(words))

    def join(self, other: Stretch, n: int) -> tuple[Stretch, list[str]]:
        """Both as one, and the n-grams that span their border."""
        seam = self.tail + other.head
        spanning = [" ".join(seam[k : k + n]) for k in range(len(seam) - n + 1)]
        head = (self.head + other.head)[: n - 1] if self.size < n - 1 else self.head
        both = self.tail + other.tail
        tail = both[max(0, len(both) - n + 1) :] if other.size < n - 1 else other.tail
        return Stretch(self.first, other.last, head, tail, self.size + other.size), spanning

    def pack(self) -> list:
        return [self.first, self.last, self.head, self.tail, self.size]


def _arrive(stretches: list[Stretch], chunks: list[tuple[int, str | None]], n: int) -> tuple[list[Stretch], int, Counter]:
    """State after more chunks (turn, text): stretches, how many turns are new, and the n-grams that came (and, negative, those that a chunk now keeps apart).

    Until a gap is filled, the stretches around it count as neighbours. A turn that comes again counts nothing.
    """
    change: Counter = Counter()

    def seams(parts: list[Stretch], sign: int) -> None:
        whole = None
        for s in parts:
            if whole is not None:
                whole, spanning = whole.join(s, n)
                for g in spanning:
                    change[g] += sign
            else:
                whole = s

    seams(stretches, -1)
    new = 0
    for turn, text in sorted(chunks, key=lambda c: (c[0], c[1] or "")):
        if any(s.first <= turn <= s.last for s in stretches):
            continue
        words = (text or "").lower().split()
        for k in range(len(words) - n + 1):
            change[" ".join(words[k : k + n])] += 1
        stretches = sorted([*stretches, Stretch.of(turn, words, n)], key=lambda s: s.first)
        new += 1
    joined: list[Stretch] = []
    for s in stretches:
        if joined and joined[-1].last + 1 == s.first:
            joined[-1], spanning = joined[-1].join(s, n)
            for g in spanning:
                change[g] += 1
        else:
            joined.append(s)
    seams(joined, 1)
    return joined, new, Counter({g: c for g, c in change.items() if c})


STATE = "stretches string, chunks long, copied long"


def _stateful(outputs: DataFrame, n: int, ttl_ms: int | None, schema: str, say) -> DataFrame:
    def step(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        packed, chunks, copied = state.get if state.exists else ("[]", 0, 0)
        rows = [(int(t), x) for b in batches for t, x in zip(b["turn"], b["text"]) if not pd.isna(t)]
        stretches, new, change = _arrive([Stretch(*s) for s in json.loads(packed)], rows, n)
        row, copied = say(key[0], chunks + new, copied, change)
        state.update((json.dumps([s.pack() for s in stretches]), chunks + new, copied))
        if ttl_ms is not None:
            state.setTimeoutDuration(ttl_ms)
        yield row

    timeout = GroupStateTimeout.NoTimeout if ttl_ms is None else GroupStateTimeout.ProcessingTimeTimeout
    return outputs.groupBy("conv_id").applyInPandasWithState(step, schema, STATE, "update", timeout)


def carry_over(outputs: DataFrame, index: dict[str, bool] | set, n: int = 11, ttl_ms: int | None = 3_600_000) -> DataFrame:
    """(conv_id, chunks, copied): n-grams of a small `index` in each conversation so far, those across chunk borders included.

    The row with the most chunks is the latest. State goes after ttl_ms without a chunk (None:
    never, for streams that are drained, which a processing-time timeout would keep awake).
    """
    sent = outputs.sparkSession.sparkContext.broadcast(frozenset(index))

    def say(conv, chunks, copied, change):
        copied += sum(c for g, c in change.items() if g in sent.value)
        return pd.DataFrame({"conv_id": [conv], "chunks": [chunks], "copied": [copied]}), copied

    return _stateful(outputs, n, ttl_ms, "conv_id long, chunks long, copied long", say)


def carried_grams(outputs: DataFrame, n: int = 11, ttl_ms: int | None = None) -> DataFrame:
    """(conv_id, chunks, grams, signs): for each conversation of a batch its chunks so far and the n-grams that the batch brought (or, negative, took back), to be joined with an index of any size."""

    def say(conv, chunks, copied, change):
        return pd.DataFrame({"conv_id": [conv], "chunks": [chunks], "grams": [list(change)], "signs": [list(change.values())]}), copied

    return _stateful(outputs, n, ttl_ms, "conv_id long, chunks long, grams array<string>, signs array<long>", say)


def drain(df: DataFrame, mode: str, each=None, schema=None) -> DataFrame:
    """Run a bounded stream to its end; what it puts out goes to files in the shared folder. `each` turns a batch into what is kept of it, of the given schema.

    Mode `complete` leaves the last batch's rows, the others those of all batches.
    """
    spark = df.sparkSession
    root = new_path(spark, "stream")
    schema = df.schema if schema is None else schema
    batches: list = []

    def keep(batch: DataFrame, number: int) -> None:
        out = batch if each is None else each(batch, f"{root}/held")
        batches.append(number)
        out.write.mode("overwrite").parquet(f"{root}/out/batch={number if mode != 'complete' else 0}")

    q = df.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(schema).parquet(f"{root}/out/batch=*") if batches else spark.createDataFrame([], schema)


def drain_joined(carried: DataFrame, have: DataFrame) -> DataFrame:
    """(conv_id, chunks, copied) of `carried_grams` run to its end: each batch's n-grams are joined with have(gram), broadcast where it fits, else shuffled."""
    spark = carried.sparkSession
    at = new_path(spark, "index")
    have.write.parquet(at)
    index = small(spark.read.parquet(at))

    def copies(batch: DataFrame, held: str) -> DataFrame:
        batch.write.mode("overwrite").parquet(held)  # state is asked once a batch
        rows = batch.sparkSession.read.parquet(held)
        each = rows.select("conv_id", F.explode(F.arrays_zip("grams", "signs")).alias("x")).select("conv_id", F.col("x.grams").alias("gram"), F.col("x.signs").alias("sign"))
        hits = each.join(index, "gram").groupBy("conv_id").agg(F.sum("sign").alias("copied"))
        return rows.select("conv_id", "chunks").join(hits, "conv_id", "left").select("conv_id", "chunks", F.coalesce("copied", F.lit(0)).cast("long").alias("copied"))

    out = drain(carried, "update", copies, "conv_id long, chunks long, copied long")
    return out.groupBy("conv_id").agg(F.max("chunks").alias("chunks"), F.sum("copied").alias("copied"))


def dropped_late(progress: list) -> int:
    """Rows that stateful operators of a query left out because they came after the watermark, from its recent progress."""
    return sum(op["numRowsDroppedByWatermark"] for p in progress for op in p["stateOperators"])
