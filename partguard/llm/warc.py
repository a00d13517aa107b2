"""Web archives: records written as WARC 1.1 files, read back, and put together by transaction.

Every record is a gzip member of its own. Members are made in Arrow batches and gathered to chunks of about a megabyte, each
a row of Spark's text writer. Its line separator is the zero byte that ends a member of less than 16 MB (the high byte of the
length there); a longer record is followed by an empty member, which ends so too. So the files are plain WARC files on any
store that Spark writes, and hold so many chunks each, whatever the number and the length of the pages.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import load, release, shared_path, slices, small_batches, stored, text_of

_END = b"\r\n\r\n"
#: Fixed value: the profile of a revisit that was found by its payload's digest.
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_CONTROL = re.compile(r"[\x00-\x20]")
_AUTHORITY = re.compile(r"^([a-z]+://([^/?#]*))?(.*?)(#.*)?$")
_EMPTY_MEMBER = zlib.compress(b"", wbits=31)


def transactions(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """One row per page: page_id, url, html (bytes), digest (SHA-1 in hex), size, nth and, for a payload of at least ``min_bytes`` that a page with a smaller id has too, that page's id in ``first_id``.

    The smallest id of each digest is aggregated before and after one shuffle of (digest, id); only digests of two rows or
    more go back to the pages, by a join that adaptive execution can split where a digest is hot. Null html and url are empty;
    a page without id can repeat another page but not be repeated; equal rows with the smallest id are all responses.
    ``nth`` numbers rows that agree in id and digest, so that their records can be told apart; only where ids repeat at all, which
    a count of the ids alone tells, are the rows sorted for it.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.coalesce(F.col("url").cast("string"), F.lit("")).alias("url"), text_of("html").cast("binary").alias("html"))
    rows = rows.withColumn("digest", F.sha1("html")).withColumn("size", F.octet_length("html").cast("long"))
    again = rows.filter(F.col("size") >= min_bytes).groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count("*").alias("n")).filter("n > 1").select("digest", "first_id")
    found = rows.join(again, "digest", "left").withColumn("first_id", F.when(~F.col("first_id").eqNullSafe(F.col("page_id")), F.col("first_id")))
    if rows.groupBy("page_id").agg(F.count("*").alias("n")).filter("n > 1").isEmpty():
        return found.withColumn("nth", F.lit(1))
    return found.withColumn("nth", F.row_number().over(Window.partitionBy("page_id", "digest").orderBy("url")))


def record_id(page_id: int | None, digest: str, nth: int = 1, part: str = "answer") -> str:
    """The id of a page's answer, request or metadata record: a name-based UUID, so a revisit can name a record of another file."""
    return f"<{uuid.UUID(bytes=hashlib.md5(f'{part}|{page_id}|{digest}|{nth}'.encode()).digest(), version=3).urn}>"


def _member(kind: str, fields: list[tuple[str, str | None]], content: str, block: bytes, level: int | None) -> bytes:
    lines = ["WARC/1.1", f"WARC-Type: {kind}", *(f"{name}: {value}" for name, value in fields if value is not None), f"Content-Type: {content}", f"Content-Length: {len(block)}"]
    raw = b"".join(("\r\n".join(lines).encode("utf-8", "surrogatepass"), _END, block, _END))
    if level is None:
        return raw
    return zlib.compress(raw, level, wbits=31) + _EMPTY_MEMBER * (len(raw) >= 1 << 24)


def _page_records(page: dict, date: str, level: int | None) -> Iterator[bytes]:
    """Request, response or revisit, and metadata of a page."""
    page_id, digest, nth, first = page["page_id"], page["digest"], page["nth"], page["first_id"]
    uri = _CONTROL.sub("", page["url"])
    _, host, target, _ = _AUTHORITY.match(uri).groups()
    answer = record_id(page_id, digest, nth)
    common = [("WARC-Target-URI", uri), ("WARC-Date", date)]
    path = target if target.startswith("/") else f"/{target}"
    yield _member("request", [("WARC-Record-ID", record_id(page_id, digest, nth, "request")), *common, ("WARC-Concurrent-To", answer)], "application/http; msgtype=request", f"GET {path} HTTP/1.1\r\nHost: {host or ''}\r\n\r\n".encode("utf-8", "surrogatepass"), level)
    repeat = [] if first is None else [("WARC-Refers-To", record_id(first, digest)), ("WARC-Profile", _PROFILE)]
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {page['size']}\r\n\r\n".encode()
    payload = ("WARC-Payload-Digest", f"sha1:{base64.b32encode(bytes.fromhex(digest)).decode()}")
    yield _member("response" if first is None else "revisit", [("WARC-Record-ID", answer), *common, payload, *repeat], "application/http; msgtype=response", head + (page["html"] if first is None else b""), level)
    note = b"" if page_id is None else f"pageId: {page_id}\r\n".encode()
    yield _member("metadata", [("WARC-Record-ID", record_id(page_id, digest, nth, "metadata")), *common, ("WARC-Concurrent-To", answer)], "application/warc-fields", note, level)


def write_warc(rows: DataFrame, path: str, date: str = "2024-01-01T00:00:00Z", file_chunks: int = 32, chunk_bytes: int = 1 << 20, level: int | None = 6) -> None:
    """Write a response or revisit record per row of ``transactions``, with a request and a metadata record concurrent to it.

    A revisit's refers-to is the record id of the response that holds its payload. A file has ``file_chunks`` chunks of
    ``chunk_bytes`` and one record more at most. ``level`` is that of the compression, None for plain files.
    """

    separator = b"\0" if level is not None else _END

    def archive(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        members: list[bytes] = []
        held = 0

        def chunk() -> pa.RecordBatch:
            raw = b"".join(members)
            return pa.RecordBatch.from_arrays([pa.array([raw[: -len(separator)]], pa.binary())], ["chunk"])

        for batch in slices(batches, column="html"):
            for page in batch.to_pylist():
                for member in _page_records(page, date, level):
                    members.append(member)
                    held += len(member)
                if held >= chunk_bytes:
                    yield chunk()
                    members, held = [], 0
        if members:
            yield chunk()

    small_batches(rows.sparkSession)
    chunks = rows.select("page_id", "url", "html", "digest", "size", "first_id", "nth").mapInArrow(archive, "chunk binary")
    chunks.select(F.col("chunk").cast("string")).write.options(lineSep=separator.decode(), compression="none", maxRecordsPerFile=file_chunks).text(path)


def _inflated(file: memoryview, step: int = 8192) -> Iterator[bytes]:
    """The bytes of a file, plain or of any number of gzip members, some at a time."""
    if bytes(file[:2]) != b"\x1f\x8b":
        for at in range(0, len(file), 1 << 20):
            yield bytes(file[at : at + (1 << 20)])
        return
    at = 0
    while at < len(file):
        member, size = zlib.decompressobj(31), step
        while not member.eof:
            if at >= len(file):
                raise ValueError("the archive ends inside a gzip member")
            data = file[at : at + size]
            at += len(data)
            got = member.decompress(data, 1 << 20)
            while got:
                yield got
                got = member.decompress(member.unconsumed_tail, 1 << 20) if not member.eof and member.unconsumed_tail else b""
            size = 1 << 18
        at -= len(member.unused_data)


def records_in(pieces: Iterable[bytes]) -> Iterator[tuple[dict[str, str], bytes]]:
    """(fields by lower-case name, block) of each record, found by its length alone, so any bytes may stand in a block; no more than one is held."""
    held, begin, size, fields = bytearray(), 0, 0, None
    for piece in pieces:
        held += piece
        while True:
            if fields is None:
                while held[:2] == b"\r\n":
                    del held[:2]
                stop = held.find(_END)
                if stop < 0:
                    break
                lines = held[:stop].decode("utf-8", "surrogatepass").split("\r\n")
                if not lines[0].startswith("WARC/"):
                    raise ValueError("not a WARC record")
                fields = {name.lower(): value for name, value in (x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines[1:])}
                begin, size = stop + 4, int(fields["content-length"])
            if len(held) < begin + size + 4:
                break
            yield fields, bytes(held[begin : begin + size])
            del held[: begin + size + 4]
            fields = None
    if held.strip(b"\r\n"):
        raise ValueError("the archive ends inside a record")


RECORDS = "record_id string, type string, concurrent_to string, refers_to string, uri string, date string, digest string, payload_bytes long, page_id long, request string"


def _http(block: bytes) -> tuple[int, int | None]:
    """Where the payload of an HTTP message begins, and its length by its header."""
    stop = block.find(_END)
    if stop < 0:
        return len(block), None
    for line in block[:stop].split(b"\r\n")[1:]:
        name, _, value = line.partition(b":")
        if name.strip().lower() == b"content-length" and value.strip().isdigit():
            return stop + 4, int(value)
    return stop + 4, None


def read_records(spark: SparkSession, path: str, with_payload: bool = False, batch_rows: int = 2000, batch_bytes: int = 4 << 20) -> DataFrame:
    """Every record of the archives, one after the other: a worker holds a file as it is stored, one record and ``batch_rows`` rows (or ``batch_bytes`` of payload).

    A response's ``payload_bytes`` is its HTTP length or, without that, what follows the HTTP head; a revisit without HTTP length
    has null. An empty file gives no row, a truncated or damaged one an error.
    """
    columns = [x.split() for x in RECORDS.split(", ")] + [["payload", "binary"]] * with_payload
    kinds = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        held = 0

        def made() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(x, kinds[kind]) for x, (_, kind) in zip(zip(*rows), columns)], [name for name, _ in columns])

        for batch in batches:
            for file in batch.column("content"):
                for fields, block in records_in(_inflated(memoryview(file.as_buffer()))):
                    page = length = request = body = None
                    kind = fields["warc-type"]
                    if kind in ("response", "revisit"):
                        begin, length = _http(block)
                        if length is None and kind == "response":
                            length = len(block) - begin
                        if with_payload and kind == "response":
                            body = block[begin:]
                            held += len(body)
                    elif kind == "request":
                        request = block.split(b"\r\n", 1)[0].decode("utf-8", "replace")
                    elif kind == "metadata":
                        found = re.search(rb"^pageId: (-?\d+)\r?$", block, re.MULTILINE)
                        page = int(found[1]) if found else None
                    rows.append((fields["warc-record-id"], kind, fields.get("warc-concurrent-to"), fields.get("warc-refers-to"), fields.get("warc-target-uri"), fields.get("warc-date"), fields.get("warc-payload-digest"), length, page, request, *[body] * with_payload))
                    if len(rows) >= batch_rows or held >= batch_bytes:
                        yield made()
                        rows, held = [], 0
        if rows:
            yield made()
        release()

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(parse, RECORDS + ", payload binary" * with_payload)


def assemble(records: DataFrame) -> DataFrame:
    """One nested row per capture: the response or revisit with the request and the metadata that name it in their concurrent-to field.

    A capture without request or metadata keeps nulls there; of several the smallest record id counts; requests and metadata
    that name no capture are left out.
    """
    main = records.filter("type in ('response', 'revisit')").drop("concurrent_to", "page_id", "request")
    by_id = lambda kind, *fields: records.filter(F.col("type") == kind).groupBy(F.col("concurrent_to").alias("record_id")).agg(F.min(F.struct(F.col("record_id").alias("id"), *fields)).alias(kind))
    whole = main.join(by_id("request", F.col("request").alias("line")), "record_id", "left").join(by_id("metadata", "page_id"), "record_id", "left")
    return whole.withColumn("page_id", F.col("metadata.page_id"))


def with_referred(captures: DataFrame) -> DataFrame:
    """Follow each revisit's refers-to, a record id, to the page id of that response: ``referred_page``, null where it is in none of the archives.

    A capture that refers to none is dealt by its own id, or all of them would meet in one task."""
    first = captures.filter("type = 'response'").groupBy(F.col("record_id").alias("followed")).agg(F.min("page_id").alias("found_page"))
    found = captures.withColumn("followed", F.coalesce("refers_to", "record_id")).join(first, "followed", "left")
    return found.withColumn("referred_page", F.when(F.col("refers_to").isNotNull(), F.col("found_page"))).drop("followed", "found_page")


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = shared_path(spark, "warc")
    write_warc(transactions(load(spark, sf_dir, "pages")), path)
    captures = with_referred(assemble(stored(read_records(spark, path), "records")))
    return captures.select("page_id", "payload_bytes", F.regexp_replace("digest", "^sha1:", "").alias("payload_digest"), F.col("type").alias("record_type"), F.col("referred_page").alias("refers_to"), F.col("request.line").alias("request_line"), F.col("uri").alias("target_uri"))


OP10_SQL = r"""
WITH p AS (SELECT page_id, url, coalesce(html, '') AS html FROM pages),
d AS (SELECT page_id, regexp_replace(url, '[\x00-\x20]', '', 'g') AS uri, octet_length(encode(html))::BIGINT AS payload_bytes, sha1(html) AS h FROM p),
f AS (SELECT *, min(page_id) OVER (PARTITION BY h) AS first_id,
  array_to_string(list_transform(range(0, 8), lambda i: array_to_string(list_transform([32768, 1024, 32, 1], lambda k: 'ABCDEFGHIJKLMNOPQRSTUVWXYZ234567'[(('0x' || h[i * 5 + 1 : i * 5 + 5])::INT // k) % 32 + 1]), '')), '') AS payload_digest FROM d)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = first_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id <> first_id THEN first_id END AS refers_to, uri AS target_uri,
  'GET ' || CASE WHEN starts_with(t, '/') THEN t ELSE '/' || t END || ' HTTP/1.1' AS request_line
FROM (SELECT *, regexp_replace(uri, '^[a-z]+://[^/?#]*|#.*$', '', 'g') AS t FROM f)
"""
