"""WARC archives: written by Spark's text writer, read back record by record, assembled by transaction.

A capture is three records: a request, a response or revisit, and metadata; the first and last name
the middle one in WARC-Concurrent-To. The reader parses archives in streams and joins the three
into one nested row per capture. Archives are gzip files, which are read whole and in order.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.llm.common import load, shared_path, staged

LEAST_REVISIT = 1000
#: Fixed values of the format.
VERSION, END, PROFILE = "WARC/1.1", "\r\n\r\n", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2020-01-01T00:00:00Z"


def _record_id(kind: str) -> Column:
    h = F.md5(F.concat_ws("|", F.lit(kind), F.coalesce(F.col("page_id").cast("string"), F.lit("null")), F.col("digest")).cast("binary"))
    return _urn(h)


def _urn(h: Column) -> Column:
    return F.concat(F.lit("<urn:uuid:"), F.substring(h, 1, 8), F.lit("-"), F.substring(h, 9, 4), F.lit("-"), F.substring(h, 13, 4), F.lit("-"), F.substring(h, 17, 4), F.lit("-"), F.substring(h, 21, 12), F.lit(">"))


def _record(kind: str, record_id: Column, block: Column, content_type: str, *headers: Column) -> Column:
    length = F.octet_length(block).cast("string")
    lines = [F.lit(f"{VERSION}\r\nWARC-Type: {kind}\r\nWARC-Date: {DATE}\r\nWARC-Record-ID: "), record_id, *[F.concat(F.lit("\r\n"), h) for h in headers], F.lit(f"\r\nContent-Type: {content_type}\r\nContent-Length: "), length, F.lit(END), block]
    return F.concat(*lines)


def decide_types(pages: DataFrame, least: int = LEAST_REVISIT) -> DataFrame:
    """Adds digest, bytes and refers_to: of rows with equal payloads of at least `least` bytes all but
    that with the largest page_id refer to it."""
    body = F.coalesce(F.col("html"), F.lit(""))
    narrow = pages.select("page_id", F.sha1(body.cast("binary")).alias("digest"), F.octet_length(body).cast("long").alias("bytes"))
    shared = narrow.filter(F.col("bytes") >= least).groupBy("digest").agg(F.max("page_id").alias("first_id"), F.count(F.lit(1)).alias("n")).filter("n > 1 and first_id is not null").select("digest", "first_id")
    shared = staged(shared, "payloads")
    full = pages.withColumn("html", body).withColumn("digest", F.sha1(F.col("html").cast("binary"))).withColumn("bytes", F.octet_length("html").cast("long"))
    joined = full.join(shared, "digest", "left")
    return joined.withColumn("refers_to", F.when(~F.col("page_id").eqNullSafe(F.col("first_id")) & F.col("first_id").isNotNull(), F.col("first_id"))).drop("first_id")


def write_archives(pages: DataFrame, path: str, least: int = LEAST_REVISIT) -> None:
    """pages: page_id, url, html. Each row gives a request, a response or revisit, and metadata.

    A response carries the whole payload; a revisit carries the HTTP header alone and names the
    response's record and the payload's digest.
    """
    rows = decide_types(pages.select(F.col("page_id").cast("bigint").alias("page_id"), F.regexp_replace(F.coalesce(F.col("url"), F.lit("")), r"[\r\n]", "").alias("url"), "html"), least)
    own = F.when(F.col("refers_to").isNull(), _record_id("response")).otherwise(_record_id("revisit"))
    target = F.concat(F.lit("WARC-Target-URI: "), F.col("url"))
    payload = F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("digest"))
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.col("bytes").cast("string"), F.lit(END))
    path_part = F.regexp_extract("url", r"^[a-z]+://[^/]*([^#]*)", 1)
    host = F.regexp_extract("url", r"^[a-z]+://([^/#?]*)", 1)
    get = F.concat(F.lit("GET "), F.when(path_part == "", F.lit("/")).otherwise(path_part), F.lit(" HTTP/1.1\r\nHost: "), host, F.lit(END))
    other = F.md5(F.concat_ws("|", F.lit("response"), F.col("refers_to").cast("string"), F.col("digest")).cast("binary"))
    middle = F.when(F.col("refers_to").isNull(), _record("response", own, F.concat(http, F.col("html")), "application/http; msgtype=response", target, payload)).otherwise(
        _record("revisit", own, http, "application/http; msgtype=response", target, payload, F.lit(f"WARC-Profile: {PROFILE}"), F.concat(F.lit("WARC-Refers-To: "), _urn(other)))
    )
    link = F.concat(F.lit("WARC-Concurrent-To: "), own)
    request = _record("request", _record_id("request"), get, "application/http; msgtype=request", target, link)
    fields = F.concat(F.lit("page-id: "), F.coalesce(F.col("page_id").cast("string"), F.lit("")), F.when(F.col("refers_to").isNotNull(), F.concat(F.lit("\r\nrefers-to-page: "), F.col("refers_to").cast("string"))).otherwise(F.lit("")), F.lit("\r\n"))
    metadata = _record("metadata", _record_id("metadata"), fields, "application/warc-fields", target, link)
    rows.select(F.explode(F.array(request, middle, metadata)).alias("value")).write.option("lineSep", END).option("compression", "gzip").text(path)


class _Parser:
    """Records of an archive whose text comes in parts that were split at blank lines.

    Parts are joined as they were; a block is cut by its length, so blank lines in it or line ends
    before the record's own end do no harm.
    """

    def __init__(self) -> None:
        self.head: dict[str, str] | None = None
        self.chunks: list[bytes] = []
        self.want = self.held = 0

    def feed(self, part: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
        data = part + END.encode()
        while data:
            if self.head is None:
                head, end, data = data.lstrip(b"\r\n").partition(END.encode())
                if not head:
                    return
                self.head = {}
                for line in head.decode("utf-8").split("\r\n"):
                    name, colon, value = line.partition(": ")
                    if colon:
                        self.head[name.lower()] = value
                self.want, self.chunks, self.held = int(self.head["content-length"]), [], 0
            self.chunks.append(data)
            self.held += len(data)
            if self.held < self.want:
                return
            whole = b"".join(self.chunks)
            yield self.head, whole[: self.want]
            self.head, data = None, whole[self.want :]


RECORD = "record_id string, kind string, concurrent_to string, refers_to_id string, uri string, payload_bytes bigint, payload_digest string, page_id bigint, refers_to bigint"


def _parsed(with_payload: bool):
    names = [c.split()[0] for c in RECORD.split(", ")] + ["payload"] * with_payload
    kinds = [pa.int64() if c.endswith("bigint") else pa.string() for c in RECORD.split(", ")] + [pa.binary()] * with_payload

    def row(head: dict[str, str], block: bytes) -> list:
        kind, payload, size, digest, page, refers = head["warc-type"], None, None, None, None, None
        if kind == "response":
            payload = block.partition(END.encode())[2]
            size, digest = len(payload), hashlib.sha1(payload).hexdigest()
            if f"sha1:{digest}" != head["warc-payload-digest"]:
                raise ValueError(f"the payload of {head['warc-record-id']} isn't what its digest says")
        elif kind == "revisit":
            http = dict(x.split(": ", 1) for x in block.decode("utf-8").split("\r\n") if ": " in x)
            size, digest = int(http["Content-Length"]), head["warc-payload-digest"].removeprefix("sha1:")
        elif kind == "metadata":
            fields = dict(x.split(": ", 1) for x in block.decode("utf-8").split("\r\n") if ": " in x)
            page, refers = (int(fields[n]) if fields.get(n) else None for n in ("page-id", "refers-to-page"))
        return [head["warc-record-id"], kind, head.get("warc-concurrent-to"), head.get("warc-refers-to"), head.get("warc-target-uri"), size, digest, page, refers, payload][: len(names)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parser, rows, held = _Parser(), [], 0

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

        for batch in batches:
            for part in batch.column(0).to_pylist():
                for head, block in parser.feed(part):
                    rows.append(row(head, block))
                    held += len(block) if with_payload else 64
            if rows and (len(rows) >= 2048 or held >= 8 << 20):
                yield out()
                rows, held = [], 0
        if parser.head is not None:
            raise ValueError("an archive ends within a record")
        if rows:
            yield out()

    return run


def read_records(spark: SparkSession, path: str, with_payload: bool = False) -> DataFrame:
    """A row per record; payload digests are of what was read. A gzip file is read by one task, in order."""
    text = spark.read.schema("value string").option("lineSep", END).text(path)
    return text.select(F.col("value").cast("binary")).mapInArrow(_parsed(with_payload), RECORD + ", payload binary" * with_payload)


def assemble(records: DataFrame) -> DataFrame:
    """One nested row per capture: the middle record joined with the request and metadata that are concurrent to it.

    Captures that repeat a page and its payload share their ids and still give a row each.
    """
    middle = records.filter(F.col("kind").isin("response", "revisit"))
    side = records.filter(F.col("kind").isin("request", "metadata")).groupBy(F.col("concurrent_to").alias("_of")).agg(
        F.max(F.when(F.col("kind") == "request", F.struct("record_id", "uri"))).alias("request"),
        F.max(F.when(F.col("kind") == "metadata", F.struct("record_id", "page_id", "refers_to"))).alias("metadata"),
    )
    payload = ["payload"] if "payload" in records.columns else []
    response = F.struct("record_id", "kind", "refers_to_id", "uri", "payload_bytes", "payload_digest", *payload).alias("response")
    return middle.select("record_id", response).join(side, F.col("record_id") == F.col("_of"), "left").select("request", "response", "metadata")


def round_trip(pages: DataFrame, path: str | None = None, least: int = LEAST_REVISIT) -> DataFrame:
    """Writes pages as archives and reads them back: page_id, payload_bytes, payload_digest, record_type, refers_to.

    Null html is an empty payload and null urls are empty; rows without a page_id come back with
    null and never stand for others; rows that repeat the largest page_id of a payload are all
    responses; an empty table gives an empty result; further columns of pages are ignored.
    """
    spark = pages.sparkSession
    path = path or shared_path(spark, "warc")
    write_archives(pages, path, least)
    captures = assemble(read_records(spark, path))
    return captures.select(
        F.col("metadata.page_id").alias("page_id"), F.col("response.payload_bytes").alias("payload_bytes"), F.col("response.payload_digest").alias("payload_digest"), F.col("response.kind").alias("record_type"), F.col("metadata.refers_to").alias("refers_to")
    )


def op2_warc_transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(load(spark, sf_dir, "pages"))


OP2_SQL = """
WITH d AS (
  SELECT page_id, sha1(coalesce(html, '')) AS payload_digest, CAST(strlen(coalesce(html, '')) AS BIGINT) AS payload_bytes FROM pages
), g AS (
  SELECT payload_digest, max(page_id) AS first_id FROM d WHERE payload_bytes >= 1000 GROUP BY 1 HAVING count(*) > 1
)
SELECT d.page_id, d.payload_bytes, d.payload_digest,
       CASE WHEN g.first_id IS NOT NULL AND d.page_id IS DISTINCT FROM g.first_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN g.first_id IS NOT NULL AND d.page_id IS DISTINCT FROM g.first_id THEN g.first_id END AS refers_to
FROM d LEFT JOIN g USING (payload_digest)
"""
