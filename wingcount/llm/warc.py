"""WARC archives with revisit records for repeated payloads.

A page's payload is its html in UTF-8. Headers alone are shuffled by payload digest; of the records of one digest the one with the largest page_id is the
response, the others become revisit records that name it and carry no payload. Only digests that occur more than once go into the join, and
headers are salted, so a payload that a third of all pages share is spread over tasks. Archives are written by Spark's text writer: a record is UTF-8 text
(its header block, an empty line, the payload) and two line ends close it, so files are WARC/1.1, each compressed as one gzip member, and a lost task is written anew.

Null html is an empty payload. Rows that repeat both page_id and html each get a record of the same kind. page_id null: never named by a
revisit unless all ids of the payload are null; then all of them are responses. An empty table gives an empty archive. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wingcount.shared import written

LINE = "\r\n"
RECORD_END = LINE * 2
SALTS = 16


def digest_base32(hexed: Column) -> Column:
    """Upper-case base32 of 40 hex digits: every five of them are four letters."""
    groups = []
    for k in range(8):
        value = F.conv(F.substring(hexed, 5 * k + 1, 5), 16, 10).cast("int")
        groups += [F.substring(F.lit("ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"), F.shiftright(value, 5 * (3 - j)).bitwiseAND(F.lit(31)) + 1, F.lit(1)) for j in range(4)]
    return F.concat(*groups)


def headers(pages: DataFrame) -> DataFrame:
    """page_id, url, payload_bytes, digest (hex) and a cheap hash of each page, without the payload."""
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    return pages.select("page_id", "url", F.octet_length(payload).cast("long").alias("payload_bytes"), F.sha1(payload).alias("digest"), F.xxhash64(payload).alias("cheap"))


def resolved(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """headers() with refers_to and refers_url: the response of the same payload, null for responses and for payloads under `least_bytes`. Payloads are hashed once: headers are
    written, as both the search for responses and the verdicts read them."""
    own = written(headers(pages), "headers")
    originals = own.where(F.col("payload_bytes") >= least_bytes).groupBy("digest").agg(F.max(F.struct("page_id", "url")).alias("first"), F.count(F.lit(1)).alias("n"))
    repeated = originals.where("n > 1").select("digest", F.col("first.page_id").alias("first_id"), F.col("first.url").alias("first_url"), F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    salted = own.withColumn("salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)).cast("int"))
    revisit = F.col("first_id").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first_id"))
    return salted.join(repeated, ["digest", "salt"], "left").select(
        "page_id", "url", "payload_bytes", digest_base32(F.col("digest")).alias("digest"), "cheap", F.when(revisit, F.col("first_id")).alias("refers_to"), F.when(revisit, F.col("first_url")).alias("refers_url")
    )


def record(date: str) -> Column:
    """A row's record: fresh header lines, an empty line, the block (an HTTP header, and the payload for responses)."""
    uri = F.coalesce(F.regexp_replace("url", r"[\r\n]", ""), F.lit(""))
    name = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(c.cast("string"), F.lit("null")), F.lit(">"))
    is_revisit = F.col("refers_to").isNotNull()
    http = F.concat(F.lit("HTTP/1.1 200 OK" + LINE + "Content-Type: text/html; charset=utf-8" + LINE + "Content-Length: "), F.col("payload_bytes").cast("string"), F.lit(RECORD_END))
    block = F.concat(http, F.when(is_revisit, F.lit("")).otherwise(F.coalesce(F.col("html"), F.lit(""))))
    lines = [
        F.lit("WARC/1.1"),
        F.concat(F.lit("WARC-Type: "), F.when(is_revisit, F.lit("revisit")).otherwise(F.lit("response"))),
        F.concat(F.lit("WARC-Record-ID: "), name(F.col("page_id"))),
        F.concat(F.lit("WARC-Date: "), F.lit(date)),
        F.concat(F.lit("WARC-Target-URI: "), uri),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("digest")),
        F.when(is_revisit, F.lit("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")),
        F.when(is_revisit, F.concat(F.lit("WARC-Refers-To: "), name(F.col("refers_to")))),
        F.when(is_revisit, F.concat(F.lit("WARC-Refers-To-Target-URI: "), F.coalesce(F.regexp_replace("refers_url", r"[\r\n]", ""), F.lit("")))),
        F.lit("Content-Type: application/http; msgtype=response"),
        F.concat(F.lit("Content-Length: "), F.octet_length(block).cast("string")),
    ]
    return F.concat(F.concat_ws(LINE, *lines), F.lit(RECORD_END), block)


def write_warc(pages: DataFrame, path: str, least_bytes: int = 0, date: str = "2000-01-01T00:00:00Z", records_per_file: int = 4000) -> None:
    """Writes a record for each page to archives under `path`. Payloads are shuffled once, by page_id and the cheap hash; those of revisits stay behind. Only payloads of one page_id
    and one cheap hash whose digests differ are told apart by hashing them anew."""
    verdict = resolved(pages, least_bytes).select(F.col("page_id").alias("id"), "cheap", "payload_bytes", "digest", "refers_to", "refers_url")
    same = Window.partitionBy("id", "cheap")
    verdict = verdict.withColumn("alone", F.min("digest").over(same) == F.max("digest").over(same)).dropDuplicates(["id", "cheap", "digest"])
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    own = pages.select("page_id", "url", "html", F.xxhash64(payload).alias("own_cheap"))
    alike = F.col("page_id").eqNullSafe(F.col("id")) & (F.col("own_cheap") == F.col("cheap"))
    joined = own.join(verdict, alike & (F.col("alone") | (digest_base32(F.sha1(payload)) == F.col("digest"))))
    joined.select(record(date).alias("value")).write.option("lineSep", RECORD_END).option("maxRecordsPerFile", records_per_file).option("compression", "gzip").text(path)


def parse(raw: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields (lower-case names) and block of each record of an archive."""
    at = 0
    while at < len(raw):
        end = raw.index(b"\r\n\r\n", at)
        version, *lines = raw[at:end].decode().split(LINE)
        if not version.startswith("WARC/"):
            raise ValueError(f"no WARC record at byte {at}")
        fields = {k.strip().lower(): v.strip() for k, v in (x.split(":", 1) for x in lines)}
        stop = end + 4 + int(fields["content-length"])
        if raw[stop : stop + 4] != b"\r\n\r\n":
            raise ValueError(f"the record at byte {at} does not end where its length says")
        yield fields, raw[end + 4 : stop]
        at = stop + 4


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """page_id, record_type, refers_to, url, payload_bytes, payload_digest and payload (null for revisits). A response's payload is measured and hashed anew
    and must agree with its header; a revisit's length and digest are its headers'."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = lambda x: None if x == "<urn:page:null>" else int(x[len("<urn:page:") : -1])
        for batch in batches:
            for raw in batch.column("content"):
                out: dict[str, list] = {c: [] for c in ("page_id", "record_type", "refers_to", "url", "payload_bytes", "payload_digest", "payload")}
                size = 0
                for fields, block in parse(gzip.decompress(raw.as_py())):
                    head, _, payload = block.partition(b"\r\n\r\n")
                    length = int(next(x.split(b":", 1)[1] for x in head.split(b"\r\n") if x.lower().startswith(b"content-length:")))
                    digest = fields["warc-payload-digest"].removeprefix("sha1:")
                    revisit = fields["warc-type"] == "revisit"
                    if not revisit and (len(payload) != length or base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest):
                        raise ValueError(f"the payload of {fields['warc-record-id']} is not what its header says")
                    row = (number(fields["warc-record-id"]), fields["warc-type"], number(fields["warc-refers-to"]) if revisit else None, fields["warc-target-uri"], length, digest, None if revisit else payload.decode("utf-8"))
                    for c, v in zip(out, row, strict=True):
                        out[c].append(v)
                    size += len(payload)
                    if size > 4 << 20:
                        yield pa.RecordBatch.from_pydict(out, schema)
                        out, size = {c: [] for c in out}, 0
                yield pa.RecordBatch.from_pydict(out, schema)

    schema = pa.schema([("page_id", pa.int64()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("payload", pa.string())])
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
    return files.mapInArrow(read, "page_id long, record_type string, refers_to long, url string, payload_bytes long, payload_digest string, payload string")
