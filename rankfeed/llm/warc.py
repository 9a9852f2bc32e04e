"""WARC archives: one request, response (or revisit) and metadata record per page, written, read back and joined to captures.

Writing goes through Spark's text sink (its commit protocol survives lost executors); a record ends in CR LF CR LF and the sink's
line end is the last byte of it. Reading parses whole files by ``Content-Length``. Records meet by ``WARC-Concurrent-To``.

Of equal payloads of ``least`` bytes or more, the row with the largest page id is the response, the others are revisits without payload.
Defined cases: a null payload is empty; null ids and urls stay null; repeated rows are captures of their own; an empty table gives none.
"""

from __future__ import annotations

import gzip
import hashlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .runtime import attach, scratch_path, written

EOL = "\r\n"
RECORD = "record_id string, type string, concurrent_to string, refers_to string, uri string, digest string, page_id long, payload_bytes long, payload binary"
SCHEME = "urn:md5:"


def record(kind: Column, identity: Column, uri: Column, more: Column, block: Column) -> Column:
    head = F.concat(F.lit(f"WARC/1.0{EOL}WARC-Type: "), kind, F.lit(f"{EOL}WARC-Record-ID: <{SCHEME}"), identity, F.lit(f">{EOL}WARC-Date: 2024-01-01T00:00:00Z{EOL}"))
    target = F.when(uri.isNotNull(), F.concat(F.lit("WARC-Target-URI: "), F.regexp_replace(uri, r"[\r\n]", ""), F.lit(EOL))).otherwise(F.lit(""))
    size = F.concat(F.lit("Content-Length: "), F.octet_length(block).cast("string"), F.lit(EOL + EOL))
    return F.concat(head, target, more, size, block, F.lit(EOL + "\r"))


def write(pages: DataFrame, path: str, least: int = 1000) -> None:
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce("html", F.lit("")).alias("html")).withColumn("uid", F.monotonically_increasing_id())
    rows = rows.withColumn("digest", F.sha1("html")).withColumn("n", F.octet_length("html"))
    small = written(rows.select("page_id", "uid", "digest", "n"), "payloads")
    groups = small.where(F.col("n") >= least).groupBy("digest").agg(F.max(F.struct("page_id", "uid")).alias("best"), F.count(F.lit(1)).alias("group_size")).where("group_size > 1")
    known = attach(rows, written(groups, "equal"), "digest", small.count())
    name = F.md5(F.concat_ws(":", F.coalesce(F.col("page_id").cast("string"), F.lit("-")), F.col("uid").cast("string")).cast("binary"))
    other = F.md5(F.concat_ws(":", F.coalesce(F.col("best.page_id").cast("string"), F.lit("-")), F.col("best.uid").cast("string")).cast("binary"))
    again = F.coalesce((F.col("n") >= least) & (F.col("best.uid") != F.col("uid")), F.lit(False))
    digest = F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("digest"), F.lit(EOL))
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{EOL}Content-Type: text/html; charset=utf-8{EOL}Content-Length: "), F.col("n").cast("string"), F.lit(EOL + EOL))
    refers = F.concat(F.lit(f"WARC-Refers-To: <{SCHEME}"), other, F.lit(f">{EOL}WARC-Profile: http://netpreserve.org/warc/1.0/revisit/identical-payload-digest{EOL}"))
    beside = F.concat(F.lit(f"WARC-Concurrent-To: <{SCHEME}"), name, F.lit(f">{EOL}"))
    main = F.when(again, record(F.lit("revisit"), name, F.col("url"), F.concat(digest, refers), http)).otherwise(record(F.lit("response"), name, F.col("url"), digest, F.concat(http, F.col("html"))))
    ask = record(F.lit("request"), F.concat(name, F.lit("-q")), F.col("url"), beside, F.lit(f"GET / HTTP/1.1{EOL}{EOL}"))
    about = record(F.lit("metadata"), F.concat(name, F.lit("-m")), F.col("url"), beside, F.concat(F.lit("page_id: "), F.coalesce(F.col("page_id").cast("string"), F.lit("")), F.lit(EOL)))
    known.select(F.explode(F.array(ask, main, about)).alias("value")).write.option("compression", "gzip").option("lineSep", "\n").text(path)


def parsed(data: bytes) -> Iterator[dict]:
    at = 0
    while at < len(data):
        end = data.index(b"\r\n\r\n", at)
        head = dict(x.split(": ", 1) for x in data[at:end].decode().split(EOL)[1:])
        size = int(head["Content-Length"])
        block = data[end + 4 : end + 4 + size]
        at = end + 4 + size + 4

        def bare(key: str, head: dict = head) -> str | None:
            return head[key][len(SCHEME) + 1 : -1] if key in head else None

        row = {"record_id": bare("WARC-Record-ID"), "type": head["WARC-Type"], "concurrent_to": bare("WARC-Concurrent-To"), "refers_to": bare("WARC-Refers-To"), "uri": head.get("WARC-Target-URI"), "digest": None, "page_id": None, "payload_bytes": None, "payload": None}
        if row["type"] in ("response", "revisit"):
            cut = block.index(b"\r\n\r\n")
            row["payload_bytes"] = int(dict(x.split(": ", 1) for x in block[:cut].decode().split(EOL)[1:])["Content-Length"])
            row["digest"] = head["WARC-Payload-Digest"].removeprefix("sha1:")
            if row["type"] == "response":
                row["payload"] = block[cut + 4 :]
                if len(row["payload"]) != row["payload_bytes"] or hashlib.sha1(row["payload"]).hexdigest() != row["digest"]:
                    raise ValueError(f"record {row['record_id']}: payload differs from its digest")
        elif row["type"] == "metadata":
            value = block.decode().strip().removeprefix("page_id:").strip()
            row["page_id"] = int(value) if value else None
        yield row


def records(spark: SparkSession, path: str, payload: bool = True) -> DataFrame:
    names = [c.split()[0] for c in RECORD.split(", ")]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for raw in b["content"]:
                rows, size = [], 0
                for r in parsed(gzip.decompress(raw)):
                    if not payload:
                        r["payload"] = None
                    rows.append(r)
                    size += len(r["payload"] or b"") + 200
                    if size > 16 << 20:
                        yield frame(rows)
                        rows, size = [], 0
                yield frame(rows)

    def frame(rows: list[dict]) -> pd.DataFrame:
        out = pd.DataFrame(rows, columns=names)
        return out.astype({"page_id": "Int64", "payload_bytes": "Int64"})

    return spark.read.format("binaryFile").option("pathGlobFilter", "*.gz").load(path).select("content").mapInPandas(run, RECORD)


def captures(found: DataFrame) -> DataFrame:
    """One nested row per capture: ``capture_id, request, main, metadata``."""
    whole = F.struct("record_id", "type", "refers_to", "uri", "digest", "page_id", "payload_bytes", "payload")
    of = {"request": "type = 'request'", "main": "type in ('response', 'revisit')", "metadata": "type = 'metadata'"}
    return found.groupBy(F.coalesce("concurrent_to", "record_id").alias("capture_id")).agg(*[F.first(F.when(F.expr(c), whole), ignorenulls=True).alias(k) for k, c in of.items()])


def report(pages: DataFrame) -> DataFrame:
    """Write, read back, assemble: ``page_id, payload_bytes, payload_digest, record_type, refers_to``."""
    spark = pages.sparkSession
    path = scratch_path(spark, "archives")
    write(pages, path)
    found = captures(records(spark, path, payload=False))
    flat = found.select("capture_id", F.col("metadata.page_id").alias("page_id"), "main.payload_bytes", F.col("main.digest").alias("payload_digest"), F.col("main.type").alias("record_type"), F.col("main.refers_to").alias("target"))
    flat = written(flat, "captures")
    wanted = flat.where("target is not null").groupBy("target").agg(F.count(F.lit(1)).alias("group_size"))
    targets = wanted.join(flat.select(F.col("capture_id").alias("target"), F.col("page_id").alias("refers_to")), "target")
    return attach(flat, written(targets, "targets"), "target", flat.count()).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE = """
with p as (select page_id, coalesce(html, '') as h from pages),
q as (select page_id, cast(octet_length(encode(h)) as bigint) as payload_bytes, sha1(h) as payload_digest, max(page_id) over (partition by h) as top from p)
select page_id, payload_bytes, payload_digest, case when payload_bytes >= 1000 and page_id < top then 'revisit' else 'response' end as record_type,
case when payload_bytes >= 1000 and page_id < top then top end as refers_to from q
"""
