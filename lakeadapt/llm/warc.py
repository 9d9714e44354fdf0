"""Content-addressed web archive.

Two tables make an archive: `payloads` holds the bytes of every different payload once, under its SHA-256 digest, and
`records` holds the exact header block of each WARC record with the digest of its payload. Whole records come back by
joining the two; what is read is hashed again and must give the digest it is stored under.

Defined cases: a null payload is an empty one; payloads below `min_bytes` are always a response; of equal larger ones
the smallest id is the response and the rest are revisits of it (rows that repeat this id are responses too; null
ids sort after all others). Extra columns of the input are ignored. An empty table gives an empty archive.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lakeadapt.llm.common import new_path, of_type

#: Fixed values of the WARC 1.1 format.
VERSION = "WARC/1.1"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
CRLF = "\r\n"


@dataclass(frozen=True)
class Archive:
    spark: SparkSession
    records_path: str
    payloads_path: str

    def records(self) -> DataFrame:
        return self.spark.read.parquet(self.records_path)

    def payloads(self) -> DataFrame:
        return self.spark.read.parquet(self.payloads_path)


def _headers(kind, digest, target, n_bytes, when: str):
    """The header block of a record, byte for byte, with the blank line that ends it."""
    def line(name: str, value) -> list:
        return [F.lit(f"{name}: "), value, F.lit(CRLF)]

    body_bytes = F.when(F.col(kind) == "response", F.col(n_bytes)).otherwise(F.lit(0)).cast("string")
    record_id = F.concat(F.lit("<urn:lakeadapt:"), F.coalesce(F.col("page_id").cast("string"), F.lit("none")), F.lit(">"))
    plain = [
        F.lit(VERSION + CRLF),
        *line("WARC-Type", F.col(kind)),
        *line("WARC-Record-ID", record_id),
        *line("WARC-Target-URI", F.regexp_replace(F.coalesce(F.col(target), F.lit("")), r"[\r\n]", "%0A")),
        *line("WARC-Date", F.lit(when)),
        *line("WARC-Payload-Digest", F.concat(F.lit("sha256:"), F.col(digest))),
        *line("Content-Length", body_bytes),
    ]
    back = [
        *line("WARC-Profile", F.lit(REVISIT_PROFILE)),
        *line("WARC-Refers-To", F.concat(F.lit("<urn:lakeadapt:"), F.col("refers_to").cast("string"), F.lit(">"))),
    ]
    text = F.when(F.col(kind) == "revisit", F.concat(*plain, *back, F.lit(CRLF))).otherwise(F.concat(*plain, F.lit(CRLF)))
    return F.encode(text, "UTF-8")


def write_archive(pages: DataFrame, min_bytes: int = 100, when: str = "2020-01-01T00:00:00Z", records_a_part: int = 4096) -> Archive:
    """pages(page_id, url, html) -> an archive in the shared folder. Records that share a payload are dealt into parts of about
    `records_a_part`, so that reading back meets a hot payload in many tasks."""
    spark = pages.sparkSession
    rows = of_type(pages, {"page_id": "long", "url": "string", "html": "string"})
    rows = rows.withColumn("payload", F.encode(F.coalesce("html", F.lit("")), "UTF-8")).select(
        "page_id", "url", "payload", F.sha2("payload", 256).alias("digest"), F.octet_length("payload").cast("long").alias("n_bytes")
    )
    archive = Archive(spark, new_path(spark, "warc-records"), new_path(spark, "warc-payloads"))
    # one payload per digest: combined before the shuffle, so a hot group sends one copy per task
    parts = F.ceil(F.count("*") / records_a_part).cast("int").alias("parts")
    rows.groupBy("digest").agg(F.any_value("payload").alias("payload"), F.any_value("n_bytes").alias("n_bytes"), parts).write.option(
        "compression", "zstd"
    ).parquet(archive.payloads_path)
    slim = rows.select("page_id", "url", "digest", "n_bytes")
    shared = slim.groupBy("digest").agg(F.when(F.any_value("n_bytes") >= min_bytes, F.min("page_id")).alias("first_id"), parts)
    records = (
        slim.join(shared, "digest")
        .withColumn("part", F.expr("cast(pmod(xxhash64(page_id, url), parts) AS int)"))
        .withColumn("record_type", F.when(F.col("first_id").isNull() | F.col("page_id").eqNullSafe(F.col("first_id")), "response").otherwise("revisit"))
        .withColumn("refers_to", F.when(F.col("record_type") == "revisit", F.col("first_id")))
        .withColumn("header", _headers("record_type", "digest", "url", "n_bytes", when))
        .select("page_id", "header", "digest", "part", "record_type", "refers_to")
    )
    records.write.option("compression", "zstd").parquet(archive.records_path)
    return archive


def _parsed(records: DataFrame) -> DataFrame:
    """What the stored header bytes say, not what the writer knew."""
    text = F.decode("header", "UTF-8")

    def field(name: str):
        return F.regexp_extract(text, rf"\r\n{name}: ([^\r]*)\r\n", 1)

    return records.select(
        "page_id",
        "header",
        "part",
        F.regexp_replace(field("WARC-Payload-Digest"), "^sha256:", "").alias("digest"),
        field("WARC-Type").alias("record_type"),
        F.expr(r"try_cast(nullif(regexp_extract(decode(header, 'UTF-8'), 'WARC-Refers-To: <urn:lakeadapt:([^>]*)>', 1), '') AS bigint)").alias("refers_to"),
    )


def reconstruct(archive: Archive) -> DataFrame:
    """page_id, header, digest, record (exact bytes of the WARC record: header, body, two line ends), payload (full, for revisits too)."""
    stored = archive.payloads().select("digest", "payload", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"))
    whole = _parsed(archive.records()).join(stored, ["digest", "part"])
    body = F.when(F.col("record_type") == "response", F.col("payload")).otherwise(F.lit(b""))
    end = F.encode(F.lit(CRLF + CRLF), "UTF-8")
    return whole.select("page_id", "header", "digest", "record_type", "refers_to", F.concat("header", body, end).alias("record"), "payload")


def read_measures(archive: Archive) -> DataFrame:
    """What each rebuilt record gives: the body that its Content-Length marks, for a revisit the payload it stands for, is hashed
    again and must give the digest that the header names."""
    size = F.regexp_extract(F.decode("header", "UTF-8"), r"\r\nContent-Length: (\d+)\r\n", 1).cast("int")
    body = F.substring("record", F.octet_length("header") + 1, size)
    read = reconstruct(archive).withColumn("payload", F.when(F.col("record_type") == "response", body).otherwise(F.col("payload")))
    found = F.sha2("payload", 256)
    wrong = F.raise_error(F.concat(F.lit("payload does not give the digest "), F.col("digest"))).cast("string")
    return read.select(
        "page_id",
        F.octet_length("payload").cast("long").alias("payload_bytes"),
        F.when(found == F.col("digest"), found).otherwise(wrong).alias("payload_digest"),
        "record_type",
        "refers_to",
    )


def op2_warc_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_measures(write_archive(spark.read.parquet(f"{sf_dir}/pages.parquet")))


ORACLE = """
WITH p AS (
  SELECT page_id, strlen(coalesce(html, '')) AS n, sha256(coalesce(html, '')) AS d FROM pages
), f AS (SELECT d, min(page_id) AS first_id FROM p WHERE n >= 100 GROUP BY d)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, p.d AS payload_digest,
       CASE WHEN first_id IS NULL OR page_id = first_id THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id <> first_id THEN first_id END AS refers_to
FROM p LEFT JOIN f ON p.d = f.d
"""
