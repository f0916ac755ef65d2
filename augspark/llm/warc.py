"""WARC archives: a writer that stays in the JVM, and a Python data source that reads them back.

Writing: one record a page, as HTTP response, or as a revisit record where an earlier page has the same payload. Records
are built by SQL functions and written by Spark's text writer with the record end as line separator, so they reach any
store Spark reaches and a lost executor only costs a retried task. Files are as large as the partitions written.

Reading: ``spark.read.format("warc")``. Files are planned into partitions by size on the driver; inside a partition
headers are parsed first, and a record whose headers fail the predicates (record types, header equalities; from options
or pushed down by Spark) is skipped by its Content-Length without touching its payload. The option ``payload`` says what
is done with the others: ``skip`` passes over them too, ``digest`` hashes and counts them in pieces as they stream past
(read_digest, read_length), ``bytes`` does that and returns them. A gzip file is one stream, read by one task.

``verified`` takes types and references from headers alone, and length and digest from the payloads of the responses.

Defined results: null html is an empty payload; an empty table writes no record and reads back as an empty table (also
if Spark wrote no file); repeated rows write repeated records, all as response or all pointing to the smallest page_id;
control characters in a url are percent-encoded in its header; a null url is an empty header; extra columns are ignored.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import json
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition

from augspark.cluster import list_files, materialize
from augspark.llm.components import join_groups

BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
DATE = "2024-01-01T00:00:00Z"
END = "\r\n\r\n"
URN = "urn:page:"
LENGTH_HEADER = "X-Payload-Length"
SCHEMA = "record_id string, record_type string, target_uri string, payload_digest string, refers_to string, payload_length long, content_length long, headers map<string,string>, read_digest string, read_length long, payload binary"


def base32_of(hexed: Column) -> Column:
    """Upper-case base32 of 40 hex digits, by SQL functions: each 5 hex digits are 4 letters."""
    letters = []
    for group in range(8):
        number = F.conv(F.substring(hexed, 5 * group + 1, 5), 16, 10).cast("int")
        letters += [F.substring(F.lit(BASE32), F.shiftright(number, shift).bitwiseAND(F.lit(31)) + 1, F.lit(1)) for shift in (15, 10, 5, 0)]
    return F.concat(*letters)


def plan_records(pages: DataFrame, min_revisit_bytes: int = 0) -> DataFrame:
    """(page_id, url, html, payload_bytes, payload_digest, refers_to); refers_to is null for responses.

    Each repeated payload's smallest page_id is aggregated from (digest, page_id) alone, with partial minima, and written.
    Pages meet that table, so payloads are shuffled only where there are too many repeated ones to broadcast it.
    """
    hexed = F.sha1(F.coalesce("html", F.lit("")).cast("binary"))
    again = pages.select(hexed.alias("_sha"), "page_id").groupBy("_sha").agg(F.min("page_id").alias("first_id"), F.count("*").alias("n")).filter("n > 1")
    first = materialize(again.select("_sha", "first_id"), "repeated-payloads")
    named = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html"), hexed.alias("payload_sha"))
    joined = named.join(first, F.col("payload_sha") == F.col("_sha"), "left")
    size = F.octet_length("html").cast("long")
    revisit = (size >= min_revisit_bytes) & F.col("first_id").isNotNull() & (~F.col("page_id").eqNullSafe(F.col("first_id")))
    return joined.select("page_id", "url", "html", size.alias("payload_bytes"), base32_of(F.col("payload_sha")).alias("payload_digest"), F.when(revisit, F.col("first_id")).alias("refers_to"))


def record_text(date: str = DATE) -> Column:
    """One WARC/1.1 record without its end, from the columns of plan_records."""
    url = F.coalesce(F.regexp_replace(F.regexp_replace(F.regexp_replace("url", "\r", "%0D"), "\n", "%0A"), r"[\x00-\x1F]", "%20"), F.lit(""))
    http = F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n")
    revisit = F.col("refers_to").isNotNull()
    body = F.when(revisit, http).otherwise(F.concat(http, F.col("html")))
    line = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit("\r\n"))
    urn = lambda c: F.concat(F.lit(f"<{URN}"), F.coalesce(c.cast("string"), F.lit("")), F.lit(">"))
    return F.concat(
        F.lit("WARC/1.1\r\n"),
        line("WARC-Type", F.when(revisit, "revisit").otherwise("response")),
        line("WARC-Record-ID", urn(F.col("page_id"))),
        line("WARC-Date", F.lit(date)),
        line("WARC-Target-URI", url),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("payload_digest"))),
        F.when(revisit, F.concat(line("WARC-Profile", F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")), line("WARC-Refers-To", urn(F.col("refers_to"))))).otherwise(""),
        line(LENGTH_HEADER, F.col("payload_bytes").cast("string")),
        line("Content-Type", F.lit("application/http; msgtype=response")),
        line("Content-Length", F.octet_length(body).cast("string")),
        F.lit("\r\n"),
        body,
    )


def write_archives(pages: DataFrame, path: str, min_revisit_bytes: int = 0, compress: bool = True) -> None:
    """Write the pages as WARC files below ``path``."""
    records = plan_records(pages, min_revisit_bytes).select(record_text().alias("value"))
    records.write.mode("overwrite").option("lineSep", END).option("compression", "gzip" if compress else "none").text(path)


class _Files(InputPartition):
    def __init__(self, uris: list[str]) -> None:
        self.uris = uris


def _open(uri: str):
    from pyarrow import fs

    system, path = fs.FileSystem.from_uri(uri if "://" in uri else "file://" + uri.removeprefix("file:"))
    raw = system.open_input_stream(path, buffer_size=1 << 20, compression=None)
    return io.BufferedReader(gzip.GzipFile(fileobj=raw), 1 << 20) if uri.endswith(".gz") else io.BufferedReader(raw, 1 << 20)


SKIP, DIGEST, BYTES = "skip", "digest", "bytes"
PIECE = 1 << 20


def _blocks(stream, left: int) -> Iterator[bytes]:
    """A record's block in pieces, read to its end."""
    while left:
        piece = stream.read(min(left, PIECE))
        if not piece:
            raise EOFError("a record ends before its Content-Length")
        left -= len(piece)
        yield piece


def _body(pieces: Iterator[bytes], http: bool) -> Iterator[bytes]:
    """What follows the HTTP headers of an http block, else the block."""
    held = b""
    for piece in pieces:
        if http:
            held += piece
            _, found, rest = held.partition(b"\r\n\r\n")
            if found:
                http, piece = False, rest
            else:
                continue
        yield piece


def read_records(stream, wanted=None, payload: str = BYTES) -> Iterator[tuple[dict[str, str], str | None, int | None, bytes | None]]:
    """(headers, digest, length, payload) of each record whose headers ``wanted`` accepts; names in lower case.

    Digest (bare upper-case base32 SHA-1) and length are of the payload as read, null where it is skipped.
    """
    while line := stream.readline():
        if not line.strip():
            continue
        if not line.startswith(b"WARC/"):
            raise ValueError(f"no WARC record starts with {line[:40]!r}")
        headers = {}
        while (line := stream.readline()) not in (b"\r\n", b"\n", b""):
            name, _, value = line.decode("utf-8", "replace").partition(":")
            headers[name.strip().lower()] = value.strip()
        block = _blocks(stream, int(headers.get("content-length", 0)))
        take = wanted is None or wanted(headers)
        if not take or payload == SKIP:
            for _ in block:
                pass
            if take:
                yield headers, None, None, None
            continue
        sha, size, kept = hashlib.sha1(usedforsecurity=False), 0, []
        for piece in _body(block, headers.get("content-type", "").startswith("application/http")):
            sha.update(piece)
            size += len(piece)
            if payload == BYTES:
                kept.append(piece)
        yield headers, base64.b32encode(sha.digest()).decode(), size, b"".join(kept) if payload == BYTES else None


def _urn(value: str | None) -> str | None:
    return value.strip("<>") if value else None


class WarcReader(DataSourceReader):
    """Options: files (JSON list of [uri, bytes]), types (comma-separated), headers (JSON of equalities), payload, partitionBytes."""

    def __init__(self, options) -> None:
        self.files = json.loads(options.get("files", "[]"))
        types = options.get("types")
        self.types = set(types.split(",")) if types else None
        self.equal = {k.lower(): v for k, v in json.loads(options.get("headers", "{}")).items()}
        self.payload = options.get("payload", BYTES)
        self.size = int(options.get("partitionbytes", options.get("partitionBytes", str(128 << 20))))

    def pushFilters(self, filters):
        """Equality and IN on record_type and equality on target_uri run while headers are read; the rest goes back to Spark."""
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("record_type",):
                self.types = {f.value} if self.types is None else self.types & {f.value}
            elif isinstance(f, In) and f.attribute == ("record_type",):
                self.types = set(f.value) if self.types is None else self.types & set(f.value)
            elif isinstance(f, EqualTo) and f.attribute == ("target_uri",):
                self.equal["warc-target-uri"] = f.value
            else:
                yield f

    def partitions(self):
        """Whole files, the largest first, packed up to a size."""
        plans: list[tuple[int, list[str]]] = []
        for uri, size in sorted(self.files, key=lambda x: -x[1]):
            if plans and plans[-1][0] + size <= self.size:
                plans[-1] = (plans[-1][0] + size, [*plans[-1][1], uri])
            else:
                plans.append((size, [uri]))
        return [_Files(uris) for _, uris in plans] or [_Files([])]

    def _wanted(self, headers: dict[str, str]) -> bool:
        return (self.types is None or headers.get("warc-type") in self.types) and all(headers.get(k) == v for k, v in self.equal.items())

    def read(self, partition):
        for uri in partition.uris:
            with _open(uri) as stream:
                for h, digest, size, payload in read_records(stream, self._wanted, self.payload):
                    full = h.get(LENGTH_HEADER.lower())
                    yield (
                        _urn(h.get("warc-record-id")),
                        h.get("warc-type"),
                        h.get("warc-target-uri"),
                        h.get("warc-payload-digest", "").removeprefix("sha1:") or None,
                        _urn(h.get("warc-refers-to")),
                        int(full) if full else None,
                        int(h.get("content-length", 0)),
                        h,
                        digest,
                        size,
                        payload,
                    )


class WarcSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return WarcReader(self.options)


def read_archives(spark: SparkSession, path: str, types: str | None = None, headers: dict[str, str] | None = None, payload: str = BYTES, partition_bytes: int | None = None) -> DataFrame:
    """The records of all archives directly below a folder, with the columns of SCHEMA.

    Files are packed into partitions of 128 MB, or of less where that would leave cores of the cluster idle.
    """
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")  # a run-time setting that readers with pushFilters need
    spark.dataSource.register(WarcSource)
    files = [x for x in list_files(spark, path) if x[1]]
    if partition_bytes is None:
        partition_bytes = min(128 << 20, max(1, sum(n for _, n in files) // (2 * spark.sparkContext.defaultParallelism)))
    read = spark.read.format("warc").option("files", json.dumps(files)).option("payload", payload).option("partitionBytes", str(partition_bytes))
    read = read.option("types", types) if types else read
    return (read.option("headers", json.dumps(headers)) if headers else read).load()


def verified(spark: SparkSession, path: str) -> DataFrame:
    """(record_id, record_type, refers_to, payload_length, payload_digest) of all records.

    One read takes headers only. A second is restricted to responses, by a filter that Spark pushes into the reader, and
    hashes their payloads: length and digest are what was read. A revisit has those of the response it refers to, and nulls
    where that holds no payload of the revisit's stated digest; so has a response whose payload differs from its own.
    """
    meta = read_archives(spark, path, payload=SKIP).select("record_id", "record_type", "refers_to", F.col("payload_digest").alias("stated"), F.concat_ws(" ", F.coalesce("refers_to", "record_id"), "payload_digest").alias("body"))
    meta = materialize(meta, "warc-headers")
    bodies = read_archives(spark, path, payload=DIGEST).filter("record_type = 'response'")
    bodies = bodies.select(F.concat_ws(" ", "record_id", "read_digest").alias("body"), "read_length", "read_digest").distinct()
    counts = meta.groupBy("body").agg(F.count("*").alias("size"))
    groups = counts.join(bodies.withColumnRenamed("body", "_body"), F.col("body") == F.col("_body"), "left").select("body", "size", F.col("read_length").alias("payload_length"), F.col("read_digest").alias("payload_digest"))
    found = join_groups(meta, "body", groups, "size", meta.count(), F.col("record_id"))
    return found.select("record_id", "record_type", "refers_to", "payload_length", "payload_digest")


def page_of(urn: Column) -> Column:
    """The page number in a record id of this writer, null for others."""
    return F.when(urn.startswith(URN), F.substring(urn, len(URN) + 1, 30)).try_cast("long")
