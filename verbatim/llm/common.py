"""Helpers that the corpus operators share."""

from __future__ import annotations

import ctypes
import gc
from functools import wraps

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import store

#: Pattern of one word: a run of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"

#: Shared with the rest of the library: the folder of driver and executors, paths in it, reliable checkpoints, sizes before a broadcast, global row numbers.
shared_dir, new_path, cut, sweep, partitions, global_index = store.shared_dir, store.new_path, store.cut, store.sweep, store.partitions, store.numbered


def delete_path(spark: SparkSession, path: str) -> None:
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    jpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jpath, True)


def give_back() -> None:
    """Return a Python worker's free memory to the system at the end of a task that held many texts."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_or_empty(col: str | Column) -> Column:
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))


def maybe_broadcast(df: DataFrame) -> DataFrame:
    """Broadcast a narrow side that is cheap to read, if its bytes are counted to fit; else the same join shuffles."""
    return store.small(df)


def carrying(*needed: str):
    """For functions of documents that return their rows: columns that are not `needed` travel
    packed in one struct, so that no name of theirs can clash with one that the function uses.
    Columns that the function adds replace carried ones of that name.
    """

    def wrap(f):
        @wraps(f)
        def g(docs: DataFrame, *args, **kwargs) -> DataFrame:
            extra = [c for c in docs.columns if c not in needed]
            if not extra:
                return f(docs, *args, **kwargs)
            quoted = lambda c: F.col("`" + c.replace("`", "``") + "`")
            packed = docs.select(*[c for c in docs.columns if c in needed], F.struct(*map(quoted, extra)).alias("__rest"))
            out = f(packed, *args, **kwargs)
            new = [c for c in out.columns if c not in packed.columns]
            own = [F.col(c) if c in needed else F.col("__rest").getField(c).alias(c) for c in docs.columns if c not in new]
            return out.select(*own, *new)

        return g

    return wrap


def drop_ids(docs: DataFrame, gone: DataFrame, key: str | list[str] = "doc_id") -> DataFrame:
    """Rows whose key is not in `gone`; a short list is broadcast so that texts need no shuffle."""
    return docs.join(maybe_broadcast(gone.select(key).distinct()), key, "left_anti")


def connected(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): the smallest node that each node of `edges` reaches.

    Min-label propagation with pointer jumping; only nodes that have an edge take part. The
    rounds grow with the logarithm of a component's length; each is cut off by a checkpoint.
    A hub's messages are combined before the shuffle, and its rows meet a side of one row a
    node in joins of checkpoints, which may be split.
    """
    d = cut(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct())
    # a node keeps its smallest neighbour, and that one takes over the others: as connected, and far fewer edges where stars overlap
    for _ in range(3):
        least = cut(d.groupBy("u").agg(F.min("v").alias("_m")))
        over = d.join(least, "u").where("v <> _m").select(F.col("v").alias("u"), F.col("_m").alias("v"))
        d = cut(least.select("u", F.col("_m").alias("v")).union(over).distinct())
    e = d
    e = cut(e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct())
    lab = e.groupBy("u").agg(F.min("v").alias("l")).select(F.col("u").alias("node"), F.least("u", "l").alias("component"))
    lab = cut(lab)
    while True:
        heard = e.join(lab, e.u == lab.node).groupBy(F.col("v").alias("node")).agg(F.min("component").alias("_m"))
        step = lab.join(heard, "node").select("node", F.least("component", "_m").alias("_c"), F.col("component").alias("_old"))
        up = lab.select(F.col("node").alias("_n"), F.col("component").alias("_up"))
        new = cut(step.join(up, F.col("_c") == F.col("_n")).select("node", F.least("_c", "_up").alias("component"), "_old"))
        moved = new.where("component <> _old").limit(1).count()
        lab = new.select("node", "component")
        if not moved:
            return lab
