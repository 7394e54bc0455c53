"""The SQL surface: Python table functions and SQL functions whose bodies Catalyst sees."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class _Grams:
    """n-grams of a text for every n in lo..hi: (n, pos, gram)."""

    def eval(self, text: str, lo: int, hi: int):
        words = text.lower().split() if text else []
        for n in range(lo, hi + 1):
            for k in range(len(words) - n + 1):
                yield n, k, " ".join(words[k : k + n])


class _Segments:
    """Windows of n + m tokens at multiples of stride: (start, prefix, reference)."""

    def eval(self, text: str, n: int, m: int, stride: int):
        words = text.lower().split() if text else []
        for k in range(0, len(words) - n - m + 1, stride):
            yield k, words[k : k + n], words[k + n : k + n + m]


def register(spark: SparkSession) -> None:
    """ngrams(...) and segments(...) as table functions; tokens(text), seeded_hash(seed, key) and softplus(x) as SQL functions."""
    spark.udtf.register("ngrams", udtf(_Grams, returnType="n int, pos int, gram string"))
    spark.udtf.register("segments", udtf(_Segments, returnType="start int, prefix array<string>, reference array<string>"))
    spark.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION tokens(t STRING) RETURNS ARRAY<STRING> RETURN filter(split(lower(t), '\\s+'), x -> x <> '')")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION seeded_hash(s STRING, k STRING) RETURNS BIGINT RETURN CAST(conv(substr(md5(concat(s, ':', k)), 1, 8), 16, 10) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION softplus(x DOUBLE) RETURNS DOUBLE RETURN log1p(exp(-abs(x))) + greatest(x, 0D)")
