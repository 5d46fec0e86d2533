"""Content-addressed archive of web records.

``payloads``  one row per distinct payload: its SHA-256, length and bytes, kept once.
``records``   one row per record: its exact header block, its payload's digest and length, its type and what it refers to.
A record is rebuilt byte by byte by joining its header with the payload of its digest (``record_bytes``), parsed again by
``parsed``, and written as a ``.warc`` file by ``export``. On reading, every payload is hashed again and must have the digest
and the length it is kept under. Equal payloads of at least ``least`` bytes have one response, the record with the
smallest id, and revisits to it; shorter ones are all responses (their bytes are still kept once).

A payload that a third of all records share is one row of ``payloads``; the smallest id per digest is aggregated before
the shuffle. Revisits have no body, so that the join that rebuilds records moves a payload to its one response and to none of
its revisits; adaptive execution can split a hot digest in it.

Nulls and edges: a null payload is empty; a null url gives a header without a target; rows with a null id stay
responses of their own; an id that repeats stays as often as it is there, rows that differ under record ids of their own;
other columns are ignored; an empty table gives an empty archive.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load, new_path

LEAST = 100
DATE = "2024-01-01T00:00:00Z"
LINE = "\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _records(pages: DataFrame) -> DataFrame:
    payload = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    rows = pages.select("page_id", "url", payload.alias("payload")).select("page_id", "url", F.sha2("payload", 256).alias("payload_digest"), F.octet_length("payload").cast("long").alias("payload_bytes"), "payload")
    return rows.withColumn("own", F.lower(F.hex(F.xxhash64("page_id", "url", "payload_digest"))))


def _record_id(page_id: Column, own: Column) -> Column:
    """Of a row; exact copies of a row are one record and share it."""
    return F.concat(F.lit("<urn:page:"), F.coalesce(page_id.cast("string"), F.lit("unknown")), F.lit(":"), own, F.lit(">"))


def header(date: str) -> Column:
    """The WARC/1.1 header block of a record, every line ended by CR LF, with the empty line that closes it."""
    revisit = F.col("record_type") == "revisit"
    lines = [
        F.lit("WARC/1.1"),
        F.concat(F.lit("WARC-Type: "), "record_type"),
        F.concat(F.lit("WARC-Record-ID: "), _record_id(F.col("page_id"), F.col("own"))),
        F.concat(F.lit("WARC-Target-URI: "), F.regexp_replace("url", "[\\r\\n]+", "%0A")),
        F.lit(f"WARC-Date: {date}"),
        F.when(revisit, F.concat(F.lit("WARC-Refers-To: "), _record_id(F.col("first.page_id"), F.col("first.own")))),
        F.when(revisit, F.lit(f"WARC-Profile: {PROFILE}")),
        F.concat(F.lit("WARC-Payload-Digest: sha256:"), "payload_digest"),
        F.lit("Content-Type: text/html; charset=utf-8"),
        F.concat(F.lit("Content-Length: "), F.when(revisit, F.lit(0).cast("long")).otherwise(F.col("payload_bytes")).cast("string")),
        F.lit(LINE),
    ]
    return F.concat_ws(LINE, *lines)


def write_archive(pages: DataFrame, path: str, least: int = LEAST, date: str = DATE) -> None:
    """Write ``pages`` (page_id, url, html) as an archive under ``path``."""
    spark = pages.sparkSession
    rows = _records(pages)
    # Equal digests stand for equal bytes, so any row's payload serves, and tasks combine a hot payload before the shuffle.
    known = F.when(F.col("page_id").isNotNull(), F.struct("page_id", "own"))
    rows.groupBy("payload_digest", "payload_bytes").agg(F.min(known).alias("first"), F.any_value("payload").alias("payload")).write.option("compression", "zstd").parquet(f"{path}/payloads")
    first = spark.read.parquet(f"{path}/payloads").select("payload_digest", "payload_bytes", "first")
    heads = rows.select("page_id", "own", "url", "payload_digest", "payload_bytes").join(first, ["payload_digest", "payload_bytes"])
    again = (F.col("payload_bytes") >= least) & (F.col("page_id") != F.col("first.page_id"))
    heads = heads.withColumn("record_type", F.when(again, "revisit").otherwise("response")).withColumn("refers_to", F.when(again, F.col("first.page_id")))
    heads.select("page_id", "payload_digest", "payload_bytes", "record_type", "refers_to", header(date).alias("header")).write.parquet(f"{path}/records")


def verified(spark: SparkSession, path: str) -> DataFrame:
    """Payloads with the digest and the length of the bytes read; others than those they are kept under raise an error."""
    read = spark.read.parquet(f"{path}/payloads").select("payload_digest", F.col("payload_bytes").alias("said"), "payload", F.sha2("payload", 256).alias("digest_read"), F.octet_length("payload").cast("long").alias("bytes_read"))
    whole = (F.col("digest_read") == F.col("payload_digest")) & (F.col("bytes_read") == F.col("said"))
    fail = F.raise_error(F.concat(F.lit("payload does not match "), "payload_digest"))
    return read.withColumn("bytes_read", F.when(whole, F.col("bytes_read")).otherwise(fail.cast("long"))).drop("said")


def read_archive(spark: SparkSession, path: str) -> DataFrame:
    """Records with their payloads, rebuilt by a join on the digest."""
    return spark.read.parquet(f"{path}/records").join(verified(spark, path), "payload_digest")


def record_bytes(spark: SparkSession, path: str) -> DataFrame:
    """(record, bytes_read, digest_read): every original record, header, body and the two closing line ends, and what its full
    payload was read as. A revisit has no body and meets the digest and the length of its payload only."""
    heads = spark.read.parquet(f"{path}/records").select("payload_digest", "record_type", "header")
    kept = verified(spark, path)
    end = F.lit(LINE + LINE).cast("binary")
    whole = heads.where("record_type = 'response'").join(kept, "payload_digest").select(F.concat(F.encode("header", "UTF-8"), "payload", end).alias("record"), "bytes_read", "digest_read")
    again = heads.where("record_type = 'revisit'").join(kept.drop("payload"), "payload_digest").select(F.concat(F.encode("header", "UTF-8"), end).alias("record"), "bytes_read", "digest_read")
    return whole.unionByName(again)


def parsed(records: DataFrame, record: str = "record") -> DataFrame:
    """``records`` with page_id, record_type, refers_to, target, said_digest and body in place of the bytes of column ``record``."""
    # Header blocks are text without an empty line; the bytes after them may be anything.
    text = F.decode(record, "ISO-8859-1")
    size = F.locate(LINE + LINE, text) + 3
    head = F.decode(F.substring(F.col(record), F.lit(1), size), "UTF-8")
    df = records.withColumn("size", size).withColumn("head", head)

    def field(name: str, value: str = "([^\\r\\n]*)") -> Column:
        return F.nullif(F.regexp_extract("head", f"(?m)^{name}: {value}", 1), F.lit(""))

    body = F.substring(F.col(record), F.col("size") + 1, field("Content-Length").cast("int"))
    number = "<urn:page:(-?[0-9]+):"
    return df.select(
        field("WARC-Record-ID", number).cast("long").alias("page_id"), field("WARC-Type").alias("record_type"), field("WARC-Refers-To", number).cast("long").alias("refers_to"),
        field("WARC-Target-URI").alias("target"), field("WARC-Payload-Digest", "sha256:([0-9a-f]+)").alias("said_digest"), body.alias("body"), *[c for c in records.columns if c != record],
    )


def export(records: DataFrame, path: str, compression: str = "gzip") -> None:
    """Records (``record_bytes``) as WARC files: the text sink's line separator is what closes a record."""
    size = F.octet_length("record") - 4
    records.select(F.decode(F.substring(F.col("record"), F.lit(1), size), "UTF-8").alias("value")).write.option("lineSep", LINE + LINE).option("compression", compression).text(path)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = new_path(spark, "archive")
    write_archive(load(spark, sf_dir, "pages"), path)
    r = parsed(record_bytes(spark, path))
    response = F.col("record_type") == "response"
    return r.select(
        "page_id", F.when(response, F.octet_length("body").cast("long")).otherwise(F.col("bytes_read")).alias("payload_bytes"),
        F.when(response, F.sha2("body", 256)).otherwise(F.col("digest_read")).alias("payload_digest"), "record_type", "refers_to",
    )


ORACLE = f"""
WITH p AS (
  SELECT page_id, sha256(coalesce(html, '')) AS payload_digest, strlen(coalesce(html, ''))::BIGINT AS payload_bytes FROM pages),
f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first_id FROM p)
SELECT page_id, payload_bytes, payload_digest,
  CASE WHEN payload_bytes >= {LEAST} AND page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN payload_bytes >= {LEAST} AND page_id <> first_id THEN first_id END AS refers_to
FROM f
"""
