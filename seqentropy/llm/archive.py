"""Content-addressed web archives.

Every page becomes one WARC record.  Payloads are kept by their digest (SHA-256 and length): a store holds the bytes of
each payload once, and a table of headers holds one row for each record, without payloads.  Of the records with equal
payloads of ``MIN_BYTES`` or more, that of the largest page id is the response; the others are revisit records, which have
their own exact headers and the digest.  Response records are headers joined to the store.  Records are whole text values
to Spark's text writer with a line separator of two CRLF, so archives are written by executors, compressed, to any file
system that Spark writes.

Reading parses the files as streams, by Content-Length, and recomputes both digests of every stored payload (a mismatch
is an error).  Headers and payloads are then tables again, and a join on the digest gives every record its full payload.

Headers are counted, not numbered: rows with equal page id, url and payload are one group with a number of copies, so the
input may be read in any order.

Defined cases: a null html is an empty payload; a null url is an empty target; tabs, line feeds and carriage returns in
urls are percent encoded in the header; null page ids are kept (and rank below all others); rows with equal ids and
payloads: one of them (of several urls, the largest) is the response and the others revisit it; an empty table gives an
empty archive; other columns are not stored.
"""

from __future__ import annotations

import gzip
import hashlib
import io
import sys
from collections.abc import Iterator

import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, read, scratch_path

MIN_BYTES, RECORDS_A_FILE = 1000, 1000
CRLF = "\r\n"
END = CRLF + CRLF
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
READ_SCHEMA = "record_id string, page_id long, record_type string, target string, header string, digest string, strong string, shared long, refers_to long, payload binary"


def plan_records(pages: DataFrame, min_bytes: int = MIN_BYTES) -> DataFrame:
    """The table of headers: page_id, url, digests, length, record type, what a revisit refers to, the copy's number and how many records stand for the payload; with the body where that is under ``min_bytes``."""
    payload = F.coalesce("html", F.lit(""))
    keys = ["strong", "bytes"]
    rows = pages.select("page_id", "url", F.sha1(payload.cast("binary")).alias("digest"), F.sha2(payload.cast("binary"), 256).alias("strong"), F.octet_length(payload).cast("long").alias("bytes"), F.when(F.octet_length(payload) < min_bytes, payload).alias("body"))
    alike = rows.groupBy(*keys, "digest", "page_id", "url", "body").agg(F.count("*").alias("copies"))
    first = alike.where(F.col("bytes") >= min_bytes).groupBy(*keys).agg(F.max(F.struct("page_id", "url")).alias("first"), F.sum("copies").alias("shared")).where("shared > 1")
    each = alike.join(first, keys, "left").withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    top = F.col("first.page_id").eqNullSafe(F.col("page_id")) & F.col("first.url").eqNullSafe(F.col("url")) & (F.col("copy") == 1)
    response = F.col("first").isNull() | top
    return each.select("page_id", "url", "digest", *keys, F.when(response, "response").otherwise("revisit").alias("record_type"), F.when(~response, F.col("first.page_id")).alias("refers_to"), "copy", F.coalesce("shared", F.lit(1).cast("long")).alias("shared"), "body")


def payload_store(pages: DataFrame, min_bytes: int = MIN_BYTES) -> DataFrame:
    """strong, bytes, stored: every distinct payload of at least ``min_bytes`` once."""
    payload = F.col("html")
    keyed = pages.where(F.octet_length(payload) >= min_bytes).select(F.sha2(payload.cast("binary"), 256).alias("strong"), F.octet_length(payload).cast("long").alias("bytes"), payload.alias("stored"))
    return keyed.groupBy("strong", "bytes").agg(F.first("stored").alias("stored"))


def _line(name: str, value) -> F.Column:
    return F.concat(F.lit(f"{CRLF}{name}: "), value)


def record_text(date: str) -> F.Column:
    """A record without the two line ends that close it."""
    url = F.coalesce("url", F.lit(""))
    for code in (9, 10, 13):
        url = F.replace(url, F.lit(chr(code)), F.lit(f"%{code:02X}"))
    hexed = F.md5(F.concat_ws(":", "strong", F.coalesce(F.col("page_id").cast("string"), F.lit("-")), F.coalesce("url", F.lit("-")), "copy").cast("binary"))
    uuid = F.concat_ws("-", *(F.substring(hexed, a, n) for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))))
    response = F.col("record_type") == "response"
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}Content-Length: "), F.col("bytes").cast("string"), F.lit(END))
    length = F.octet_length(http) + F.when(response, F.col("bytes")).otherwise(0)
    return F.concat(
        F.lit("WARC/1.1"), _line("WARC-Type", F.col("record_type")), _line("WARC-Record-ID", F.concat(F.lit("<urn:uuid:"), uuid, F.lit(">"))), _line("WARC-Date", F.lit(date)), _line("WARC-Target-URI", url),
        _line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), "digest")), _line("WARC-X-Payload-Strong-Digest", F.concat(F.lit("sha256:"), "strong")),
        F.when(response & (F.col("shared") > 1), _line("WARC-X-Shared", F.col("shared").cast("string"))).otherwise(""), F.coalesce(_line("WARC-X-Page", F.col("page_id").cast("string")), F.lit("")),
        F.when(response, F.lit("")).otherwise(F.concat(_line("WARC-Profile", F.lit(PROFILE)), F.coalesce(_line("WARC-X-Refers-To-Page", F.col("refers_to").cast("string")), F.lit("")))),
        _line("Content-Type", F.lit("application/http;msgtype=response")), _line("Content-Length", length.cast("string")), F.lit(END), http, F.when(response, F.col("body")).otherwise(""),
    )


def write_archive(pages: DataFrame, path: str, date: str = "1970-01-01T00:00:00Z", min_bytes: int = MIN_BYTES) -> None:
    """Writes gzip WARC files to a folder: headers, and for the one response of each larger payload the store's bytes."""
    pages = pages.select("page_id", "url", "html")
    headers = cut(plan_records(pages, min_bytes), "warc-headers")
    alone = (F.col("record_type") == "response") & (F.col("bytes") >= min_bytes)
    stored = headers.where(alone).drop("body").join(payload_store(pages, min_bytes), ["strong", "bytes"]).withColumnRenamed("stored", "body")
    records = headers.where(~alone).unionByName(stored)
    records.select(record_text(date).alias("value")).write.option("lineSep", END).option("compression", "gzip").option("maxRecordsPerFile", RECORDS_A_FILE).text(path)


def parse_records(stream) -> Iterator[tuple[str, dict[str, str], bytes]]:
    """(exact header, its fields, block) of each record of a file, one at a time."""
    while first := stream.readline():
        lines = [first]
        while (line := stream.readline()) != b"\r\n":
            if not line:
                raise ValueError("the last record is cut")
            lines.append(line)
        header = b"".join(lines)[:-2].decode("utf-8", "surrogateescape")
        if not header.startswith("WARC/1."):
            raise ValueError(f"no record begins with {header[:40]!r}")
        fields = dict(line.split(": ", 1) for line in header.split(CRLF)[1:])
        size = int(fields["Content-Length"])
        block = stream.read(size)
        if len(block) != size or stream.read(4) != END.encode():
            raise ValueError(f"the record {fields.get('WARC-Record-ID')} is cut")
        yield header, fields, block


def _reader(kinds: tuple[str, ...]):
    names = [c.split(" ")[0] for c in READ_SCHEMA.split(", ")]
    types = [{"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}[c.split(" ")[1]] for c in READ_SCHEMA.split(", ")]
    number = lambda x: None if x is None else int(x)
    as_batch = lambda rows: pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), types, strict=True)], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column(0):
                rows, size = [], 0
                for header, f, block in parse_records(gzip.GzipFile(fileobj=io.BytesIO(content.as_py()))):
                    kind, digest, strong = f["WARC-Type"], f["WARC-Payload-Digest"].removeprefix("sha1:"), f["WARC-X-Payload-Strong-Digest"].removeprefix("sha256:")
                    if kind not in kinds:
                        continue
                    payload = None
                    if kind == "response":
                        payload = block[block.index(b"\r\n\r\n") + 4:]
                        if hashlib.sha1(payload).hexdigest() != digest or hashlib.sha256(payload).hexdigest() != strong:
                            raise ValueError(f"the payload of {f['WARC-Record-ID']} isn't what its digest says")
                    rows.append((f["WARC-Record-ID"], number(f.get("WARC-X-Page")), kind, f["WARC-Target-URI"], header, digest, strong, number(f.get("WARC-X-Shared")) or 1, number(f.get("WARC-X-Refers-To-Page")), payload))
                    size += len(block) + len(header)
                    if size > 8 << 20:
                        yield as_batch(rows)
                        rows, size = [], 0
                if rows:
                    yield as_batch(rows)

    return run


def read_archive(spark: SparkSession, path: str, kinds: tuple[str, ...] = ("response", "revisit")) -> DataFrame:
    """The records of an archive, payloads verified; revisits have none of their own."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.gz").load(path).select("content")
    return files.mapInArrow(_reader(kinds), READ_SCHEMA)


def restore(spark: SparkSession, path: str) -> DataFrame:
    """Every record of an archive with the payload that it stands for: revisits by a join on the strong digest with the responses that are shared."""
    responses, revisits = (read_archive(spark, path, (kind,)) for kind in ("response", "revisit"))
    stored = responses.where("shared > 1").select("strong", F.col("payload").alias("stored"))
    again = revisits.join(stored, "strong", "left").withColumn("payload", F.col("stored")).drop("stored")
    return responses.unionByName(again)


def op10_warc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Writes all ``pages`` to an archive in the shared folder and reads them back; lengths and digests are those of the restored payloads."""
    path = scratch_path(spark, "warc")
    write_archive(read(spark, sf_dir, "pages"), path)
    pages = restore(spark, path)
    return pages.select("page_id", F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha1("payload").alias("payload_digest"), "record_type", "refers_to")


OP10_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS body, row_number() OVER () AS rn FROM pages),
d AS (SELECT page_id, rn, CAST(octet_length(encode(body)) AS BIGINT) AS payload_bytes, sha1(body) AS payload_digest FROM p),
r AS (SELECT *, row_number() OVER (PARTITION BY payload_digest ORDER BY page_id DESC NULLS LAST, rn) AS k, first_value(page_id) OVER (PARTITION BY payload_digest ORDER BY page_id DESC NULLS LAST, rn) AS top FROM d)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN payload_bytes < 1000 OR k = 1 THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN payload_bytes < 1000 OR k = 1 THEN NULL ELSE top END AS refers_to
FROM r
"""

register_pickle_by_value(sys.modules[__name__])
