"""Readers and writers of corpora, recorded outputs and reports."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

OUTPUTS = T.StructType([T.StructField("output_id", T.StringType()), T.StructField("task", T.StringType()), T.StructField("model", T.StringType()), T.StructField("text", T.StringType()), T.StructField("logp", T.DoubleType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_corpus(spark: SparkSession, path: str, fmt: str = "parquet", schema=None) -> DataFrame:
    """parquet, orc, json lines, csv (with a header), text (a row a line) or whole (a row a file)."""
    r = spark.read if schema is None else spark.read.schema(schema)
    if fmt == "whole":
        return r.option("wholetext", True).text(path)
    if fmt == "csv":
        r = r.option("header", True).option("multiLine", True).option("escape", '"')
    return r.format(fmt).load(path)


def read_outputs(spark: SparkSession, path: str, fmt: str = "json") -> DataFrame:
    """Recorded generations of a real model; a fixed schema, so no inference pass."""
    return spark.read.schema(OUTPUTS).format(fmt).load(path)


def write_report(df: DataFrame, path: str, fmt: str = "parquet", by: tuple[str, ...] = ()) -> None:
    w = df.write.mode("overwrite").format(fmt)
    (w.partitionBy(*by) if by else w).save(path)


def write_bucketed(df: DataFrame, name: str, keys: list[str], buckets: int) -> None:
    """A table whose later joins on `keys` need no shuffle of it."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)


class _Part(InputPartition):
    def __init__(self, k: int):
        self.k = k


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.parts = int(options.get("rows", "8")), int(options.get("parts", "2"))

    def partitions(self):
        return [_Part(k) for k in range(self.parts)]

    def read(self, part):
        for i in range(part.k, self.rows, self.parts):
            yield (f"g{i}", "story", "stub", f"once upon a time there were {i} tales", -float(i))


class GenerationEndpoint(DataSource):
    """Rows from a generation service; this one makes them up, a real one overrides the reader."""

    @classmethod
    def name(cls):
        return "generations"

    def schema(self):
        return OUTPUTS

    def reader(self, schema):
        return _Reader(self.options)


def page_text(html: str = "html"):
    """Visible text of a page: scripts, styles, navigation and comments go, then tags, then the common entities."""
    x = F.col(html)
    for pattern in (r"(?is)<script[^>]*>.*?</script>", r"(?is)<style[^>]*>.*?</style>", r"(?is)<nav[^>]*>.*?</nav>", r"(?s)<!--.*?-->", r"(?s)<[^>]*>"):
        x = F.regexp_replace(x, pattern, " ")
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        x = F.replace(x, F.lit(name), F.lit(char))
    return F.trim(F.regexp_replace(x, r"\s+", " "))


def page_title(html: str = "html"):
    return F.regexp_extract(F.col(html), r"(?is)<title>(.*?)</title>", 1)
