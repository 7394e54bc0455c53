"""Cutting lineage, stages that several queries share, sizes before a broadcast, and numbers without one task that sees every row."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

_kept: dict = {}

#: Most bytes of a side that is broadcast, and of a table that goes to Python workers as objects; beyond them joins shuffle.
BROADCAST_BYTES, PYTHON_BYTES = 64 << 20, 32 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Only a local session may do without one and gets a new folder."""
    sc = spark.sparkContext
    at = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not at:
        if not sc.master.startswith("local[") and sc.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        at = "file://" + tempfile.mkdtemp(prefix="verbatim-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(at)
    return at


def new_path(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{what}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: the lineage ends in files that outlive executors."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def keep(df: DataFrame) -> DataFrame:
    """`cut` for large stages: the lineage ends in compressed Parquet files of the shared folder, a fraction of a checkpoint's bytes; shuffle files that made them may go."""
    spark = df.sparkSession
    path = new_path(spark, "stage")
    df.write.option("compression", "zstd").parquet(path)
    sweep(spark)
    return spark.read.schema(df.schema).parquet(path)


def keep_parts(spark: SparkSession, n: int, make) -> DataFrame:
    """`keep` of n parts together, one after another: make(k) gives part k's rows and what to do when they are written; its shuffle files go before the next part's come."""
    path = new_path(spark, "stage")
    for k in range(n):
        df, done = make(k)
        df.write.mode("append").option("compression", "zstd").parquet(path)
        done()
        sweep(spark)
    return spark.read.schema(df.schema).parquet(path)


def input_bytes(spark: SparkSession, path: str) -> int:
    """Bytes of the files of a table."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(p).getLength()


def drop(kept: DataFrame) -> None:
    """Delete the files of what `keep` returned, once nothing reads it any more."""
    spark = kept.sparkSession
    for at in {f.rsplit("/", 1)[0] for f in kept.inputFiles()}:
        path = spark._jvm.org.apache.hadoop.fs.Path(at)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def sweep(spark: SparkSession) -> None:
    """Let the driver collect its garbage: shuffle files and checkpoints that nothing refers to any more go then, and else stay until it happens to."""
    gc.collect()
    spark._jvm.System.gc()


def stamp(spark: SparkSession, path: str) -> tuple:
    """Names, times and sizes of what lies in a folder: tells whether its tables changed."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = p.getFileSystem(spark._jsc.hadoopConfiguration())
    return tuple(sorted((f.getPath().getName(), f.getModificationTime(), f.getLen()) for f in fs.listStatus(p)))


def remember(key: tuple, spark: SparkSession, make):
    """`make()` once for a session, a key (name, folder, ...) and the state of the folder."""
    at = (spark.sparkContext.applicationId, stamp(spark, key[1]), *key)
    if at not in _kept:
        _kept[at] = make()
    return _kept[at]


def shared(key: tuple, spark: SparkSession, make) -> DataFrame:
    """`make()` cut off once; later queries read the files again."""
    return remember(key, spark, lambda: keep(make()))


def forget() -> None:
    """Drop what is remembered: the next query makes its stages anew. Files of `keep` stay in the shared folder, as a reader may still hold them."""
    _kept.clear()


def _varying(value: Column, kind: T.DataType) -> Column | None:
    """Bytes of a value beyond its place in the row; None where there are never any."""
    if isinstance(kind, (T.StringType, T.BinaryType)):
        return F.coalesce(F.octet_length(value), F.lit(0)).cast("long")
    if isinstance(kind, T.ArrayType):
        each = _varying(F.lit(None).cast(kind.elementType), kind.elementType)
        own = F.coalesce(F.size(value), F.lit(0)).cast("long") * (8 if each is None else 16)
        return own if each is None else own + F.coalesce(F.aggregate(value, F.lit(0).cast("long"), lambda a, x: a + F.coalesce(_varying(x, kind.elementType), F.lit(0))), F.lit(0))
    if isinstance(kind, T.StructType):
        parts = [p for p in (_varying(value.getField(f.name), f.dataType) for f in kind.fields) if p is not None]
        return sum(parts, F.lit(8 * len(kind.fields)).cast("long")) if parts else F.lit(8 * len(kind.fields)).cast("long")
    return None


def fits(df: DataFrame, most: int = BROADCAST_BYTES) -> bool:
    """Whether the rows of `df` take `most` bytes or less, counted with their strings and arrays; rows too many stop the count early."""
    fixed = 16 + 8 * len(df.columns)
    if df.limit(most // fixed + 1).count() > most // fixed:
        return False
    quoted = [(F.col("`" + f.name.replace("`", "``") + "`"), f.dataType) for f in df.schema.fields]
    parts = [p for p in (_varying(c, k) for c, k in quoted) if p is not None]
    if not parts:
        return True
    size = sum(parts, F.lit(fixed).cast("long"))
    return (df.agg(F.sum(size)).first()[0] or 0) <= most


def small(df: DataFrame, most: int = BROADCAST_BYTES) -> DataFrame:
    """`df`, marked for a broadcast if it fits. It is counted, so it should be cheap to read."""
    return F.broadcast(df) if fits(df, most) else df


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def numbered(df: DataFrame, keys: list[Column], name: str, sums: dict[str, Column] | None = None) -> DataFrame:
    """Number the rows 0, 1, ... in the order of `keys`, without one task that sees them all; each name of `sums` gets the sum of its value over the rows that come earlier.

    Range partitions are sorted in place and cut off by a checkpoint (so that their borders
    cannot move), then each partition's offset is the sum of the counts before it; the driver
    sees one row for each partition. Rows that tie on all keys share the numbers of their tie
    in any order.
    """
    spark, sums = df.sparkSession, sums or {}
    values = {f"__index_v{k}": v for k, v in enumerate(sums.values())}
    spread = F.monotonically_increasing_id()
    placed = df.withColumns(values) if values else df
    placed = placed.withColumn("__index_s", spread).repartitionByRange(partitions(spark), *keys, F.col("__index_s"))
    placed = placed.sortWithinPartitions(*keys, F.col("__index_s")).drop("__index_s")
    placed = placed.withColumn("__index_p", F.spark_partition_id()).withColumn("__index_i", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)))
    placed = cut(placed)
    each = placed.groupBy("__index_p").agg(F.count(F.lit(1)).alias("n"), *[F.sum(c).cast("double").alias(c) for c in values])
    total, amounts, offsets = 0, [0.0] * len(values), []
    for r in sorted(each.collect(), key=lambda r: r["__index_p"]):
        offsets.append((r["__index_p"], total, *amounts))
        total, amounts = total + r["n"], [a + (r[c] or 0.0) for a, c in zip(amounts, values)]
    starts = spark.createDataFrame(offsets or [(0, 0, *amounts)], "__index_p int, __index_o long" + "".join(f", {c}o double" for c in values))
    out = placed.join(F.broadcast(starts), "__index_p").withColumn(name, F.col("__index_o") + F.col("__index_i"))
    earlier = Window.partitionBy("__index_p").orderBy("__index_i").rowsBetween(Window.unboundedPreceding, -1)
    for before, c in zip(sums, values):
        out = out.withColumn(before, F.col(f"{c}o") + F.coalesce(F.sum(c).over(earlier).cast("double"), F.lit(0.0)))
    return out.drop("__index_p", "__index_i", "__index_o", *values, *[f"{c}o" for c in values])


def tiles(index: Column, n: int, bands: int) -> Column:
    """The band 1, 2, ... of row number `index` of n where the first n % bands bands have one row more."""
    q, r = divmod(n, bands)
    edge = r * (q + 1)
    return (F.when(index < edge, F.floor(index / (q + 1))).otherwise(r + F.floor((index - edge) / max(1, q))) + 1).cast("int")

