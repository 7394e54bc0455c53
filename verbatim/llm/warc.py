"""WARC archives in which equal payloads are stored once.

Headers (page id, payload digest, length) are shuffled by digest; the smallest page id of a
digest stays a response, the others become revisit records that refer to it. Archives are
written through Spark's own writer, so any file system that Spark knows will do: each file
holds a bounded number of records, and the blank lines that end a record are the line
separator. Reading walks the files by Content-Length and joins revisits to their responses.

Defined results: a null html is the empty payload; a null page id comes last among equals and
its record carries none; white space and control characters in a url are percent-encoded and
a null url has no target header; rows that repeat a page id with the same payload are one
response (or revisit) and revisits of the same page, each with a record id of its own; an
empty table gives archives without records. A file is one gzip stream, as Spark's text writer
makes it, not a member for each record.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
from collections.abc import Iterator
from urllib.parse import quote

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common as C

#: Most records in a file; payloads shorter than MIN_BYTES are never revisits.
RECORDS_PER_FILE, MIN_BYTES = 1_000, 0
DATE = "2024-01-01T00:00:00Z"

# Line end, version line, profile of the revisit record type, base32 alphabet.
CRLF = "\r\n"
VERSION = "WARC/1.1"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"


def base32_sha1(payload: Column) -> Column:
    """Bare upper-case base32: each five hex digits of the SHA-1 are four of its letters."""
    hexa = F.sha1(payload)
    letters = []
    for k in range(8):
        v = F.conv(F.substring(hexa, 5 * k + 1, 5), 16, 10).cast("int")
        letters += [F.substr(F.lit(BASE32), F.shiftright(v, s).bitwiseAND(31) + 1, F.lit(1)) for s in (15, 10, 5, 0)]
    return F.concat(*letters)


def heads(pages: DataFrame) -> DataFrame:
    """(page_id, url, _d, _n): digest and bytes of each payload, kept by a checkpoint because every decision reads them."""
    payload = C.text_or_empty("html").cast("binary")
    return C.cut(pages.select("page_id", "url", base32_sha1(payload).alias("_d"), F.octet_length(payload).cast("long").alias("_n")))


def decide(heads: DataFrame, min_bytes: int = MIN_BYTES) -> DataFrame:
    """heads with _first, the response's page id, and _dup, whether a row revisits it."""
    first = C.cut(heads.groupBy(F.col("_d").alias("_dd")).agg(F.min("page_id").alias("_first"), F.count(F.lit(1)).alias("_m")).where("_m > 1").drop("_m"))
    d = heads.join(C.maybe_broadcast(first), F.col("_d") == F.col("_dd"), "left")
    return d.withColumn("_dup", F.col("_dd").isNotNull() & (F.col("_n") >= min_bytes) & ~F.col("page_id").eqNullSafe(F.col("_first"))).drop("_dd")


def record_id(page_id: Column, digest: Column, number: Column) -> Column:
    """From page id, digest and the row's number among rows that share both."""
    h = F.md5(F.concat_ws("|", page_id.cast("string"), digest, F.when(number > 0, number.cast("string"))))
    return F.concat(F.lit("urn:uuid:"), F.concat_ws("-", F.substring(h, 1, 8), F.substring(h, 9, 4), F.substring(h, 13, 4), F.substring(h, 17, 4), F.substring(h, 21, 12)))


def _same(a: DataFrame, b: DataFrame, ident: str, digest: str) -> Column:
    return a["page_id"].eqNullSafe(b[ident]) & (a["_d"] == b[digest])


def records(pages: DataFrame, min_bytes: int = MIN_BYTES, date: str = DATE) -> DataFrame:
    """One string column `value` with a whole WARC record for each row of pages(page_id, url, html).

    Only the rows that revisit travel to the pages: their list is joined by page id, broadcast
    where it is short, so responses keep their place. Rows that share page id and payload, if
    there are any, are numbered from their headers alone, and one payload serves them all.
    """
    head_rows = heads(pages)
    told = decide(head_rows, min_bytes)
    dup = C.cut(told.where("_dup").select(F.col("page_id").alias("_pid"), F.col("_d").alias("_dd"), "_first").distinct())
    payload = C.text_or_empty("html")
    d = pages.select("page_id", "url", payload.alias("_html"), base32_sha1(payload.cast("binary")).alias("_d"), F.octet_length(payload).cast("long").alias("_n"))
    again = C.cut(head_rows.groupBy(F.col("page_id").alias("_aid"), F.col("_d").alias("_ad")).agg(F.count(F.lit(1)).alias("_k")).where("_k > 1").drop("_k"))
    own = d
    several = again.limit(1).count() > 0
    if several:
        few = C.maybe_broadcast(again)
        own = d.join(few, _same(d, few, "_aid", "_ad"), "left_anti")
        num = C.global_index(told.join(few, _same(told, few, "_aid", "_ad"), "left_semi"), [F.col("_d"), F.col("page_id"), F.col("url")], "_i")
        low = C.cut(num.groupBy(F.col("page_id").alias("_lid"), F.col("_d").alias("_ld")).agg(F.min("_i").alias("_low")))
        num = num.join(low, _same(num, low, "_lid", "_ld")).withColumn("_number", F.col("_i") - F.col("_low"))
        num = num.withColumn("_rev", F.col("_dup") | ((F.col("_n") >= min_bytes) & (F.col("_number") > 0)))
        one = d.join(few, _same(d, few, "_aid", "_ad"), "left_semi").groupBy(F.col("page_id").alias("_oid"), F.col("_d").alias("_od")).agg(F.first("_html").alias("_html"))
        full = num.where("not _rev")
        full = full.join(one, _same(full, one, "_oid", "_od"))
        parts = ["page_id", "url", "_html", "_d", "_n", "_rev", "_first", "_number"]
        num = full.select(*parts).unionByName(num.where("_rev").withColumn("_html", F.lit(None).cast("string")).select(*parts))
    own = own.join(C.maybe_broadcast(dup), own.page_id.eqNullSafe(dup._pid) & (own._d == dup._dd), "left")
    own = own.withColumn("_rev", F.col("_dd").isNotNull()).withColumn("_number", F.lit(0).cast("long"))
    d = own.select(*parts).unionByName(num) if several else own
    head = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit(CRLF))
    http = F.concat(F.lit("HTTP/1.1 200 OK" + CRLF + "Content-Type: text/html; charset=utf-8" + CRLF + "Content-Length: "), F.col("_n"), F.lit(CRLF + CRLF))
    block = F.when(F.col("_rev"), http).otherwise(F.concat(http, F.col("_html")))

    @F.pandas_udf("string")
    def target(u: pd.Series) -> pd.Series:
        return u.map(lambda x: None if x is None else quote(x, safe="!#$%&'()*+,/:;=?@[]~"))

    d = d.withColumn("_block", block).withColumn("_u", target("url"))
    return d.select(F.concat(
        F.lit(VERSION + CRLF), head("WARC-Type", F.when(F.col("_rev"), "revisit").otherwise("response")), head("WARC-Record-ID", F.concat(F.lit("<"), record_id(F.col("page_id"), F.col("_d"), F.col("_number")), F.lit(">"))), head("WARC-Date", F.lit(date)),
        F.when(F.col("_u").isNotNull(), head("WARC-Target-URI", F.col("_u"))).otherwise(""), head("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("_d"))),
        F.when(F.col("_rev"), F.concat(head("WARC-Profile", F.lit(PROFILE)), head("WARC-Refers-To", F.concat(F.lit("<"), record_id(F.col("_first"), F.col("_d"), F.lit(0)), F.lit(">"))))).otherwise(""),
        F.when(F.col("page_id").isNotNull(), head("X-Page-Id", F.col("page_id").cast("string"))).otherwise(""),
        head("Content-Type", F.lit("application/http;msgtype=response")), head("Content-Length", F.octet_length("_block").cast("string")), F.lit(CRLF), F.col("_block"),
    ).alias("value"))


def write_archives(pages: DataFrame, path: str, min_bytes: int = MIN_BYTES, records_per_file: int = RECORDS_PER_FILE) -> None:
    records(pages, min_bytes).write.option("lineSep", CRLF + CRLF).option("compression", "gzip").option("maxRecordsPerFile", records_per_file).text(path)


def parse(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, block) of each record of an uncompressed archive."""
    at = 0
    while True:
        at = data.find(b"WARC/", at)
        if at < 0:
            return
        end = data.index(b"\r\n\r\n", at)
        lines = data[at:end].decode("utf-8").split(CRLF)[1:]
        heads = {k.lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}
        size = int(heads["content-length"])
        yield heads, data[end + 4 : end + 4 + size]
        at = end + 4 + size


READ = "page_id long, record_type string, record_id string, refers_id string, target string, digest string, payload_bytes long, payload_digest string, payload string"


def read_archives(spark: SparkSession, path: str, with_payload: bool = True) -> DataFrame:
    """The records of all archives under `path`; a revisit has no payload of its own."""

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for content in batch["content"]:
                data = gzip.decompress(content) if content[:2] == b"\x1f\x8b" else bytes(content)
                out = []
                for h, block in parse(data):
                    payload = block[block.index(b"\r\n\r\n") + 4 :]
                    own = h["warc-type"] == "response"
                    out.append((int(h["x-page-id"]) if "x-page-id" in h else None, h["warc-type"], h["warc-record-id"].strip("<>"), h.get("warc-refers-to", "").strip("<>") or None, h.get("warc-target-uri"), h["warc-payload-digest"].removeprefix("sha1:"), len(payload) if own else None, base64.b32encode(hashlib.sha1(payload).digest()).decode() if own else None, payload.decode("utf-8") if own and with_payload else None))
                    if len(out) >= 200:
                        yield frame(out)
                        out = []
                if out:
                    yield frame(out)

    def frame(out: list) -> pd.DataFrame:
        names = [x.split()[0] for x in READ.split(", ")]
        return pd.DataFrame({n: pd.Series([r[k] for r in out], dtype="Int64" if n in ("page_id", "payload_bytes") else object) for k, n in enumerate(names)})

    return spark.read.format("binaryFile").load(path).select("content").mapInPandas(rows, READ)


def resolve(found: DataFrame) -> DataFrame:
    """Every record with the payload data of the response that it is or refers to, and refers_to, that response's page id."""
    held = [c for c in ("payload_bytes", "payload_digest", "payload") if c in found.columns]
    own = Window.partitionBy("record_id").orderBy(F.col("page_id").asc_nulls_last())
    first = found.where("record_type = 'response'").withColumn("_r", F.row_number().over(own)).where("_r = 1").select(F.col("record_id").alias("_rid"), F.col("page_id").alias("_to"), *[F.col(c).alias(f"_{c}") for c in held])
    back = found.where("record_type = 'revisit'").join(first, F.col("refers_id") == F.col("_rid"), "left")
    back = back.select("page_id", "record_type", "record_id", "target", *[F.col(f"_{c}").alias(c) for c in held], F.col("_to").alias("refers_to"))
    return found.where("record_type = 'response'").select("page_id", "record_type", "record_id", "target", *held, F.lit(None).cast("long").alias("refers_to")).unionByName(back)


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Write all pages, read the archives back, return what they say; the archives go when that is kept."""
    path = C.new_path(spark, "warc")
    write_archives(C.table(spark, sf_dir, "pages"), path)
    found = C.cut(read_archives(spark, path, with_payload=False).drop("payload"))
    C.delete_path(spark, path)
    return resolve(found).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def oracle() -> str:
    letters = " || ".join(f"substr('{BASE32}', ((v >> {s}) & 31) + 1, 1)" for s in (15, 10, 5, 0))
    return f"""
WITH h AS (SELECT page_id, strlen(coalesce(html, ''))::BIGINT AS payload_bytes, sha1(coalesce(html, '')) AS hexa FROM pages),
g AS (SELECT page_id, payload_bytes, hexa, k, ('0x' || substr(hexa, 5 * k + 1, 5))::BIGINT AS v FROM h, range(8) AS r(k)),
d AS (SELECT page_id, payload_bytes, hexa, string_agg({letters}, '' ORDER BY k) AS payload_digest FROM g GROUP BY ALL),
f AS (SELECT *, min(page_id) OVER (PARTITION BY hexa) AS first_id FROM d)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = first_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = first_id THEN NULL ELSE first_id END AS refers_to FROM f
"""
