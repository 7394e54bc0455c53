"""From raw documents to token ids: five stages, each over all rows that the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from verbatim.llm import bpe, linededup, mixing, simhash, toxicity
from verbatim.llm import common as C


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score as toxic go; labels serve the fit alone."""
    return toxicity.keep_clean(docs, C.table(spark, sf_dir, "labels"))


def without_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of repeated line runs go; no row does, and n_chars follows the text."""

    @C.carrying("doc_id", "text", "n_chars")
    def cut(d: DataFrame) -> DataFrame:
        out = linededup.deduplicate(d)
        return out.withColumn("n_chars", F.when(F.col("n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).drop("n_removed")

    return cut(docs)


def without_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays."""
    return simhash.deduplicate(docs)


def to_weights(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row as often as the mix takes it."""
    return mixing.mixed(docs, mixing.quality_weights(C.table(spark, sf_dir, "labels")))


def to_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text, and digests of them and of what they decode to."""
    return bpe.encode(docs, ["doc_id", "source"])


STAGES = [
    ("toxicity", clean),
    ("line_dedup", without_repeated_lines),
    ("simhash_near_dedup", without_copies),
    ("mixing", to_weights),
    ("bpe", to_ids),
]

#: Word scores, suffix ranks and byte pairs are beyond SQL; a test holds run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`; each is written as Parquet to the shared folder and read again, and goes when the next one is there."""
    docs, before = C.table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        path = C.new_path(spark, f"pipeline-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        if before:
            C.delete_path(spark, before)
        docs, before = spark.read.parquet(path), path
    return docs
