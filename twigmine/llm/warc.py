"""Content-addressed web archive: payload bytes stored once by strong digest, exact record headers apart.

An archive is a folder with two tables: payloads(sha256, payload) and headers(record_id, header, sha256, ...).  A record is
header, payload (responses), and two line ends; joining the tables by digest gives back every record byte for byte.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import whole_numbers

#: Payloads at least this long are stored as one response and revisits.
REVISIT_FROM = 1000
DATE = "2024-01-01T00:00:00Z"
END = "\r\n"


def records_of(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", date: str = DATE) -> DataFrame:
    """One record per row: page_id, url, payload, sha1, sha256, payload_bytes, record_type, refers_to, header.

    The payload is the html in UTF-8 (null: empty).  Of the records with equal payloads of at least REVISIT_FROM bytes the one
    with the largest id is the response and the others revisit it; rows repeated with that id are all responses.
    Rows with a null id revisit like others and are responses only if all equal ones have no id.
    """
    p = pages.select(F.col(id_col).cast("long").alias("page_id"), F.coalesce(F.col(url_col).cast("string"), F.lit("")).alias("url"), F.encode(F.coalesce(F.col(html_col).cast("string"), F.lit("")), "UTF-8").alias("payload"))
    # Digests come before the join, so that headers need no payload in it.
    p = p.withColumns({"payload_bytes": F.octet_length("payload").cast("long"), "sha256": F.sha2("payload", 256), "sha1": F.sha1("payload")})
    groups = p.filter(f"payload_bytes >= {REVISIT_FROM}").groupBy("sha256").agg(F.max("page_id").alias("response_id"), F.count(F.lit(1)).alias("c")).filter("c > 1").drop("c")
    p = p.join(groups, "sha256", "left")
    revisit = F.col("response_id").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("response_id"))
    p = p.withColumn("record_type", F.when(revisit, "revisit").otherwise("response")).withColumn("refers_to", F.when(revisit, F.col("response_id")))
    uid = lambda c: F.concat(F.lit("<urn:uuid:"), F.regexp_replace(F.md5(F.coalesce(c.cast("string"), F.lit(""))), "^(.{8})(.{4})(.{4})(.{4})(.{12})$", "$1-$2-$3-$4-$5"), F.lit(">"))
    line = lambda name, value: F.concat(F.lit(name + ": "), value, F.lit(END))
    blank = F.lit("")
    header = F.concat(
        F.lit("WARC/1.1" + END), line("WARC-Type", F.col("record_type")), line("WARC-Record-ID", uid(F.col("page_id"))), line("WARC-Date", F.lit(date)),
        line("WARC-Target-URI", F.regexp_replace("url", r"[\r\n]", "")), line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("sha1"))),
        F.when(revisit, F.concat(line("WARC-Profile", F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")), line("WARC-Refers-To", uid(F.col("refers_to"))))).otherwise(blank),
        line("Content-Type", F.lit("text/html; charset=utf-8")), line("Content-Length", F.when(revisit, F.lit("0")).otherwise(F.col("payload_bytes").cast("string"))), F.lit(END),
    )
    return p.withColumn("header", header)


def archive(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", date: str = DATE) -> None:
    """Write the two tables for a table of pages.  Headers are made and joined without payloads; every different payload is moved once, by its digest.

    Null pages are empty payloads, repeated rows are repeated records, and an empty table makes an empty archive.
    """
    whole_numbers(pages, id_col)
    headers = records_of(pages, id_col, url_col, html_col, date).select("page_id", "header", "sha256", "refers_to", "record_type")
    headers.write.parquet(f"{path}/headers")
    payload = pages.select(F.encode(F.coalesce(F.col(html_col).cast("string"), F.lit("")), "UTF-8").alias("payload"))
    payload.select(F.sha2("payload", 256).alias("sha256"), "payload").groupBy("sha256").agg(F.first("payload").alias("payload")).write.parquet(f"{path}/payloads")


def write_archive(records: DataFrame, path: str) -> None:
    """Write the two tables for records that are made already; each payload is stored once.  Records with equal payloads must share their digest."""
    records.select("page_id", "header", "sha256", "refers_to", "record_type").write.parquet(f"{path}/headers")
    records.groupBy("sha256").agg(F.first("payload").alias("payload")).write.parquet(f"{path}/payloads")


def read_archive(spark: SparkSession, path: str) -> DataFrame:
    """Every record rebuilt: page_id, header, record_type, refers_to, payload (of a revisit too), sha256.

    Fails if the bytes stored under a digest do not have it, or if a record finds no payload.
    """
    headers = spark.read.parquet(f"{path}/headers")
    payloads = spark.read.parquet(f"{path}/payloads")
    # The digest is verified here, on what was read, not on what was written.
    bad = F.raise_error(F.concat(F.lit("payload does not have the digest "), F.col("sha256")))
    verified = payloads.withColumn("payload", F.when(F.sha2("payload", 256) == F.col("sha256"), F.col("payload")).otherwise(bad.cast("binary")))
    rebuilt = headers.join(verified, "sha256", "left")
    return rebuilt.withColumn("payload", F.when(F.col("payload").isNotNull(), F.col("payload")).otherwise(F.raise_error(F.concat(F.lit("no payload for "), F.col("sha256"))).cast("binary")))


def record_bytes(rebuilt: DataFrame) -> DataFrame:
    """The records as they stand in a WARC file: page_id, record; one row per row, revisits without payload, null ids kept."""
    body = F.when(F.col("record_type") == "response", F.col("payload")).otherwise(F.lit(b""))
    return rebuilt.select("page_id", F.concat(F.encode("header", "UTF-8"), body, F.lit((END * 2).encode())).alias("record"))


def header_field(name: str):
    """A field of the stored header, as a column (null where absent)."""
    found = F.regexp_extract("header", rf"(?:^|\r\n){name}: ([^\r\n]*)", 1)
    return F.when(found != "", found)


def write_warc_files(records: DataFrame, path: str) -> None:
    """WARC files through Spark's text sink, gzipped: one record after another."""
    rows = records.select(F.concat("header", F.when(F.col("record_type") == "response", F.decode("payload", "UTF-8")).otherwise("")))
    rows.write.option("lineSep", END * 2).option("compression", "gzip").text(path)


def read_warc_files(spark: SparkSession, path: str) -> DataFrame:
    """Records of gzipped or plain WARC files: type, uri, digest, header, payload.  Files are read whole, one at a time; empty ones have no records."""

    def parse(batches):
        import gzip

        for batch in batches:
            for data in batch.column("content").to_pylist():
                data = gzip.decompress(data) if data[:2] == b"\x1f\x8b" else data
                out, at = [], 0
                while at < len(data):
                    stop = data.index(b"\r\n\r\n", at) + 4
                    head = data[at:stop].decode()
                    fields = dict(re.findall(r"([^:\r\n]+): ([^\r\n]*)", head))
                    size = int(fields["Content-Length"])
                    out.append((fields.get("WARC-Type"), fields.get("WARC-Target-URI"), fields.get("WARC-Payload-Digest"), head, data[stop : stop + size]))
                    at = stop + size + 4
                columns = list(zip(*out, strict=True)) or [()] * 5
                yield pa.RecordBatch.from_arrays([pa.array(columns[k], pa.binary() if k == 4 else pa.string()) for k in range(5)], ["type", "uri", "digest", "header", "payload"])

    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("content")
    return files.mapInArrow(parse, "type string, uri string, digest string, header string, payload binary")
