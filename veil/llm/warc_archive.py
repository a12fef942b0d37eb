"""WARC writing with revisit resolution, and reading back.

Headers (page, URL, payload digest), never payloads, are shuffled by digest;
records whose payload equals another's are joined to the response that holds
it, and archives are written with fresh headers: one ``response`` per payload,
``revisit`` records for the rest. Payloads move once, by page, to be written.

Archives are what standard readers expect: gzip files that begin with a
``warcinfo`` record and hold one gzip member per record, so that a record can be
read from its offset alone. Python tasks pack members into files of bounded
bytes and Spark's text writer writes one such value a file, so archives live on
any file system that Spark reaches, and a lost executor's part is written again
by the usual commit protocol. Files are read whole and parsed as a stream, by
``Content-Length``.

Defined results: null payloads are empty and count as equal; payloads shorter
than ``least`` bytes are all responses; a null page id sorts below every other
and has no page header; rows repeated with one page id and payload make the
same decision; line breaks in URLs are percent-encoded; a record larger than
``file_bytes`` has a file of its own, and Spark's limit for one value (2 GB) is
the limit of a payload; columns other than ``page_id, url, html`` take no part;
an empty table gives an archive without records.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from veil.sources.shared import in_arrow, materialize, shared_path, small_batches

ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"
#: Compressed bytes after which a new archive file begins; a task holds one file in memory.
FILE_BYTES = 32 << 20
SCHEMA = "page_id long, url string, record_type string, payload_bytes long, payload_digest string, refers_to long, payload binary"


def base32(digest: Column) -> Column:
    """Upper-case base32 of a hex SHA-1: eight groups of 20 bits, four letters each."""
    letters = []
    for g in range(8):
        bits = F.conv(F.substr(digest, F.lit(5 * g + 1), F.lit(5)), 16, 10).cast("int")
        letters += [F.substr(F.lit(ALPHABET), F.shiftright(bits, 15 - 5 * k).bitwiseAND(F.lit(31)) + 1, F.lit(1)) for k in range(4)]
    return F.concat(*letters)


def _record_id(page: Column, digest: Column) -> Column:
    h = F.md5(F.concat_ws("|", F.coalesce(page.cast("string"), F.lit("")), digest))
    return F.concat(F.lit("<urn:uuid:"), F.regexp_replace(h, "^(.{8})(.{4})(.{4})(.{4})(.{12})$", "$1-$2-$3-$4-$5"), F.lit(">"))


def headers(pages: DataFrame) -> DataFrame:
    """``page_id, mark, digest, size`` of every record, written once: one scan hashes the payloads.

    ``mark`` is a cheap hash of the payload, by which rows find their header again.
    """
    body = F.coalesce(F.col("html"), F.lit(""))
    heads = pages.select("page_id", F.xxhash64(body).alias("mark"), F.sha1(body).alias("sha"), F.octet_length(body).alias("size"))
    return materialize(heads.distinct(), "warc-heads").withColumn("digest", base32(F.col("sha"))).drop("sha")


def resolve(heads: DataFrame, least: int = 0) -> DataFrame:
    """Adds to each header the response it refers to, null for responses.

    The response of a payload is the record with the largest page id.
    """
    heads = heads.withColumn("same", F.when(F.col("size") >= least, F.col("digest")))
    first = heads.filter("same is not null").groupBy(F.col("same").alias("__d")).agg(F.max("page_id").alias("response_id"))
    joined = heads.join(first, F.col("same") == F.col("__d"), "left")
    own = F.col("response_id").isNull() | F.col("page_id").eqNullSafe(F.col("response_id"))
    return joined.select(
        F.col("page_id").alias("__p"),
        F.col("mark").alias("__m"),
        "digest",
        "size",
        own.alias("is_response"),
        F.when(~own, F.col("response_id")).alias("refers_to"),
    )


def records(pages: DataFrame, least: int = 0) -> DataFrame:
    """One WARC record per row of ``page_id, url, html``: column ``value`` without its last line break."""
    known = resolve(headers(pages), least)
    body = F.coalesce(F.col("html"), F.lit(""))
    p = pages.select("page_id", "url", body.alias("body"), F.xxhash64(body).alias("mark"))
    r = p.join(known, F.col("page_id").eqNullSafe(F.col("__p")) & (F.col("mark") == F.col("__m")))
    uri = F.replace(F.replace(F.coalesce("url", F.lit("")), F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A"))
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.col("size").cast("string"), F.lit("\r\n\r\n"))
    block = F.when(F.col("is_response"), F.concat(http, F.col("body"))).otherwise(http)

    def line(name: str, value: Column) -> Column:
        return F.coalesce(F.concat(F.lit(f"{name}: "), value, F.lit("\r\n")), F.lit(""))

    head = F.concat(
        F.lit("WARC/1.1\r\n"),
        line("WARC-Type", F.when(F.col("is_response"), "response").otherwise("revisit")),
        line("WARC-Record-ID", _record_id(F.col("page_id"), F.col("digest"))),
        line("WARC-Date", F.lit(DATE)),
        line("WARC-Target-URI", F.when(F.col("url").isNotNull(), uri)),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))),
        line("WARC-Profile", F.when(~F.col("is_response"), PROFILE)),
        line("WARC-Refers-To", F.when(~F.col("is_response"), _record_id(F.col("refers_to"), F.col("digest")))),
        line("X-Page-Id", F.col("page_id").cast("string")),
        line("X-Refers-To-Page-Id", F.col("refers_to").cast("string")),
        line("Content-Type", F.lit("application/http;msgtype=response")),
        line("Content-Length", F.octet_length(block).cast("string")),
    )
    return r.select(F.concat(head, F.lit("\r\n"), block, F.lit("\r\n")).alias("value"))


def _member(record: bytes) -> bytes:
    """One gzip member, without name and time, so that equal records give equal bytes."""
    z = zlib.compressobj(6, zlib.DEFLATED, 31)
    return z.compress(record) + z.flush()


def _info(first: bytes) -> bytes:
    """The ``warcinfo`` record of the archive that begins with the record ``first``."""
    fields = b"software: veil\r\nformat: WARC File Format 1.1\r\n"
    name = uuid.UUID(bytes=hashlib.sha1(b"warcinfo" + first).digest()[:16])
    head = f"WARC/1.1\r\nWARC-Type: warcinfo\r\nWARC-Record-ID: <urn:uuid:{name}>\r\nWARC-Date: {DATE}\r\nContent-Type: application/warc-fields\r\nContent-Length: {len(fields)}\r\n\r\n"
    return head.encode() + fields + b"\r\n\r\n"


def _pack(batches: Iterator[pa.RecordBatch], schema: pa.Schema, file_bytes: int) -> Iterator[pa.RecordBatch]:
    """Whole archive files, one a row.

    The writer ends a value with a zero byte. A member's last byte is zero if
    its record has less than 16 MB, so that byte is left to the writer; after a
    larger record the zero is padding, which gzip readers skip.
    """

    def archive_of(members: list[bytes]) -> pa.RecordBatch:
        whole = b"".join(members)
        return pa.RecordBatch.from_arrays([pa.array([whole[:-1] if whole[-1] == 0 else whole], schema[0].type)], schema=schema)

    members: list[bytes] = []
    held = 0
    for b in batches:
        for value in b.column("value"):
            record = value.as_buffer().to_pybytes() + b"\r\n"
            member = _member(record)
            if members and held + len(member) > file_bytes:
                yield archive_of(members)
                members, held = [], 0
            if not members:
                members.append(_member(_info(record)))
                held = len(members[0])
            members.append(member)
            held += len(member)
    if members:
        yield archive_of(members)


def _name_archives(spark: SparkSession, path: str) -> None:
    """Rename the writer's files to ``.warc.gz``: one metadata operation a file, no data."""
    to = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    p = to(path)
    fs = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    for f in fs.listStatus(p):
        name = f.getPath().getName()
        if name.endswith(".txt") and not fs.rename(f.getPath(), to(p, name.removesuffix(".txt") + ".warc.gz")):
            raise OSError(f"could not rename {name}")


def write(pages: DataFrame, path: str, least: int = 0, file_bytes: int = FILE_BYTES) -> None:
    """Write deduplicated archives of about ``file_bytes`` compressed bytes at most below ``path``."""
    spark = pages.sparkSession
    with small_batches(spark):
        files = in_arrow(records(pages, least), _pack, "value binary", file_bytes)
        out = files.select(F.col("value").cast("string")).write.option("lineSep", "\0")
        out.option("maxRecordsPerFile", 1).text(path)
    _name_archives(spark, path)


def parse_stream(f: io.BufferedIOBase) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and block of each record of an uncompressed archive stream."""
    while line := f.readline():
        if line != b"WARC/1.1\r\n":
            raise ValueError(f"not the start of a record: {line[:40]!r}")
        head: dict[str, str] = {}
        while (line := f.readline()) not in (b"\r\n", b""):
            name, _, value = line.decode().rstrip("\r\n").partition(": ")
            head[name.lower()] = value
        block = f.read(int(head["content-length"]))
        if f.read(4) != b"\r\n\r\n":
            raise ValueError("a record does not end where its length says")
        yield head, block


def _rows(files: Iterator[pa.RecordBatch], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    def batch(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(zip(*rows), schema)], schema=schema)

    for b in files:
        for content in b.column("content"):
            rows: list[tuple] = []
            held = 0
            with gzip.open(io.BytesIO(content.as_py())) as f:
                for head, block in parse_stream(f):
                    kind = head["warc-type"]
                    if kind == "warcinfo":
                        continue
                    http, _, payload = block.partition(b"\r\n\r\n")
                    if kind == "response":
                        size, digest = len(payload), base64.b32encode(hashlib.sha1(payload).digest()).decode()
                        if f"sha1:{digest}" != head["warc-payload-digest"]:
                            raise ValueError("a payload does not have the digest of its header")
                    else:
                        size, digest = int(http.rpartition(b": ")[2]), head["warc-payload-digest"].partition(":")[2]
                        payload = None
                    page, to = head.get("x-page-id"), head.get("x-refers-to-page-id")
                    rows.append((page and int(page), head.get("warc-target-uri"), kind, size, digest, to and int(to), payload))
                    held += len(block)
                    if held > 8 << 20:
                        yield batch(rows)
                        rows, held = [], 0
            if rows:
                yield batch(rows)


def read(spark: SparkSession, path: str, payload: bool = True) -> DataFrame:
    """The records of the archives below ``path``."""
    files = spark.read.format("binaryFile").load(path).select("content")
    rows = in_arrow(files, _rows, SCHEMA)
    return rows if payload else rows.drop("payload")


def archive(pages: DataFrame, least: int = 0) -> DataFrame:
    """Write archives in the shared folder and return what reading them back gives."""
    spark = pages.sparkSession
    path = shared_path(spark, "warc")
    write(pages, path, least)
    return read(spark, path)
