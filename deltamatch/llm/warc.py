"""WARC archives in Zstandard: a dictionary in the leading skippable frame, one frame per record.

Writing: tasks turn rows into records, compress each into a frame of its own and close an
archive at `archive_bytes`; its dictionary is trained on a bounded share of that archive's
own records and stored in front. The bytes go out through Spark's text writer, one archive
a file, to any file system Spark can reach and under its commit protocol: the writer's
line separator is an empty skippable frame, which readers pass over, so the files are valid
archives. Reading: files come through Spark's binary reader; each frame is decoded with the
archive's dictionary, and versions, mandatory headers, lengths and digests are checked.

A response's block is an HTTP message whose body is the payload. Payloads of at least
`least_bytes` that occur more than once are stored once: the record with the smallest
page_id is the response, the others are revisits that refer to it by address and date, and
by page in a header of this module (rows that repeat that very page_id are responses too).
Every record has a name of its own, whatever its page_id. Null html is an empty payload.
Null page_ids come last among equal payloads and are written without a number; null or
empty addresses are written as about:blank and read as null; characters that an address
can't hold are percent-encoded. Empty tables give an empty archive folder and an empty
result. Extra columns are ignored.
"""

from __future__ import annotations

import re
import struct
import uuid
from collections.abc import Iterator
from datetime import datetime, timezone
from hashlib import sha256

import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import map_rows, rekeyed, shared_dir, small_batches

DICTIONARY_MAGIC = 0x184D2A5D
#: An empty skippable frame; all of it is ASCII, so it can serve as a line separator.
SEPARATOR = struct.pack("<II", 0x184D2A50, 0).decode("ascii")
_HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n"
_BLANK = "about:blank"
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_PLAIN_DICTIONARY = b"WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:uuid:\r\nWARC-Date: 20\r\nWARC-Target-URI: http://\r\nWARC-Payload-Digest: sha256:\r\nContent-Type: application/http;msgtype=response\r\nContent-Length: \r\n\r\n" + _HTTP + b"<!DOCTYPE html><html><head><title></title></head><body></body></html>\r\n\r\n"
_DATE = re.compile(r"\d{4}(-\d\d(-\d\d(T\d\d:\d\d(:\d\d(\.\d{1,9})?)?Z)?)?)?")
_HEADER = re.compile(rb"([A-Za-z][A-Za-z0-9-]*):[ \t]*([^\r\n]*)")


class BadArchive(ValueError):
    """An archive or record that breaks the format."""


def address(url: str | None) -> str:
    return re.sub(r"[\x00-\x20\x7f<>]", lambda m: f"%{ord(m[0]):02X}", url or "") or _BLANK


def record(name: str, date: str, page_id: int | None, url: str | None, payload: bytes, digest: str, first: int | None = None, first_url: str | None = None) -> bytes:
    """One record called `name` (a URI); `first` makes it a revisit of that page, at first_url."""
    lines = ["WARC/1.1", f"WARC-Type: {'response' if first is None else 'revisit'}", f"WARC-Record-ID: <{name}>", f"WARC-Date: {date}", f"WARC-Target-URI: {address(url)}", f"WARC-Payload-Digest: sha256:{digest}", f"Page-Payload-Length: {len(payload)}"]
    if page_id is not None:
        lines.append(f"Page-Number: {page_id}")
    if first is not None:
        lines += [f"WARC-Profile: {_PROFILE}", f"WARC-Refers-To-Target-URI: {address(first_url)}", f"WARC-Refers-To-Date: {date}", f"Page-Refers-To: {first}"]
    block = _HTTP % len(payload) + payload if first is None else b""
    lines += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Headers (lower-case names) and block of one record; raises BadArchive where it breaks the format."""
    head, gap, rest = raw.partition(b"\r\n\r\n")
    first, _, lines = head.partition(b"\r\n")
    if not gap or first not in (b"WARC/1.0", b"WARC/1.1"):
        raise BadArchive("no WARC version line")
    headers: dict[str, str] = {}
    for line in filter(None, lines.split(b"\r\n")):
        m = _HEADER.fullmatch(line)
        if not m:
            raise BadArchive(f"malformed header {line[:80]!r}")
        headers[m[1].decode().lower()] = m[2].decode("utf-8", "replace")
    missing = [n for n in ("warc-type", "warc-record-id", "warc-date", "content-length") if n not in headers]
    if missing:
        raise BadArchive(f"headers missing: {missing}")
    if not _DATE.fullmatch(headers["warc-date"]):
        raise BadArchive(f"date {headers['warc-date'][:40]!r}")
    if not headers["content-length"].isdigit() or len(rest) != int(headers["content-length"]) + 4 or rest[-4:] != b"\r\n\r\n":
        raise BadArchive("the block isn't as long as Content-Length says")
    return headers, rest[:-4]


def payload_of(headers: dict[str, str], block: bytes) -> bytes:
    """The body of an HTTP message, or the whole block of any other type."""
    if not block or not headers.get("content-type", "").startswith("application/http"):
        return block
    head, gap, body = block.partition(b"\r\n\r\n")
    if not gap or not head.startswith(b"HTTP/"):
        raise BadArchive("a block that should be an HTTP message isn't one")
    return body


def build_dictionary(records: list[bytes], size: int = 16_384, sample_bytes: int = 1 << 20) -> zstandard.ZstdCompressionDict:
    """Trained on the first sample_bytes of records; a plain one where they are too few to train on."""
    sample, total = [], 0
    for r in records:
        if total >= sample_bytes:
            break
        sample.append(r[:65_536])
        total += len(sample[-1])
    try:
        return zstandard.train_dictionary(min(size, max(1024, total // 10)), sample, k=256, d=8)
    except zstandard.ZstdError:
        return zstandard.ZstdCompressionDict(_PLAIN_DICTIONARY, dict_type=zstandard.DICT_TYPE_RAWCONTENT)


def archive(records: list[bytes], level: int = 3) -> bytes:
    """The dictionary frame and one frame per record."""
    trained = build_dictionary(records)
    raw = trained.as_bytes()
    pack = zstandard.ZstdCompressor(level=level, dict_data=trained, write_content_size=True, write_checksum=True).compress
    return b"".join([struct.pack("<II", DICTIONARY_MAGIC, len(raw)), raw, *map(pack, records)])


def frames(data: bytes) -> Iterator[bytes]:
    """Decoded records of one archive, one frame at a time."""
    view, at, known = memoryview(data), 0, None
    while at < len(data):
        if len(data) - at < 8:
            raise BadArchive("cut short")
        magic, length = struct.unpack_from("<II", data, at)
        if 0x184D2A50 <= magic <= 0x184D2A5F:
            if at + 8 + length > len(data):
                raise BadArchive("a skippable frame is cut short")
            if magic == DICTIONARY_MAGIC and at == 0:
                raw = bytes(view[8 : 8 + length])
                if raw[:4] == b"\x28\xb5\x2f\xfd":  # the dictionary may itself be compressed
                    raw = zstandard.ZstdDecompressor().decompress(raw)
                known = zstandard.ZstdCompressionDict(raw)
            at += 8 + length
            continue
        opened = zstandard.ZstdDecompressor(dict_data=known).decompressobj() if known else zstandard.ZstdDecompressor().decompressobj()
        parts, step, end = [], at, None
        try:
            while end is None:
                if step >= len(data):
                    raise BadArchive("a frame is cut short")
                part = view[step : step + 65_536]
                parts.append(opened.decompress(part))
                step += len(part)
                if opened.eof:
                    end = step - len(opened.unused_data)
        except zstandard.ZstdError as e:
            raise BadArchive(f"a frame can't be decoded: {e}") from e
        at = end
        yield b"".join(parts)


def write_archives(pages: DataFrame, path: str, *, least_bytes: int = 100, archive_bytes: int = 16 << 20, date: str | None = None) -> None:
    """Archives of all rows of pages (page_id, url, html) under path, dated `date` (UTC; the start of the job unless given)."""
    date = date or datetime.now(timezone.utc).strftime("%Y-%m-%dT%H:%M:%SZ")
    job = uuid.uuid4()
    rows = pages.select(F.col("page_id").cast("bigint").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html"), F.lit("")).alias("html"))
    rows = rows.withColumn("digest", F.sha2(F.col("html").cast("binary"), 256)).withColumn("long", F.octet_length("html") >= least_bytes)
    # Only digests of repeated payloads take part; a copy's key stands in for its html in the first shuffle.
    named = F.min(F.when(F.col("page_id").isNotNull(), F.struct("page_id", "url")))
    first = rows.where("long").groupBy("digest").agg(named.alias("least"), F.count("*").alias("n")).where("n > 1")
    first = first.select(F.concat("digest", F.lit("")).alias("digest"), F.col("least.page_id").alias("first_id"), F.col("least.url").alias("first_url")).select("digest", rekeyed("first_id"), "first_url")
    met = rows.join(first, "digest", "left").select("page_id", "url", "html", "digest", F.when(F.col("long") & ~F.col("page_id").eqNullSafe(F.col("first_id")), F.col("first_id")).alias("first_id"), "first_url")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[bytes] = []
        total = made = 0
        task = TaskContext.get().partitionId()
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                part = batch.slice(at, 64).to_pydict()
                for page_id, url, html, digest, first_id, first_url in zip(*(part[c] for c in ("page_id", "url", "html", "digest", "first_id", "first_url"))):
                    # A task that runs again gives its records the same names.
                    held.append(record(uuid.uuid5(job, f"{task}-{made}").urn, date, page_id, url, html.encode(), digest, first_id, first_url))
                    made += 1
                    total += len(held[-1])
                    if total >= archive_bytes:
                        yield pa.RecordBatch.from_arrays([pa.array([archive(held)], pa.binary())], ["value"])
                        held, total = [], 0
        if held:
            yield pa.RecordBatch.from_arrays([pa.array([archive(held)], pa.binary())], ["value"])

    small_batches(pages.sparkSession)
    packed = met.mapInArrow(run, "value binary").select(F.col("value").cast("string").alias("value"))
    packed.write.mode("overwrite").option("lineSep", SEPARATOR).option("maxRecordsPerFile", 1).option("compression", "none").text(path)


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """(record_id, page_id, url, record_type, refers_to, payload_bytes, payload_digest, payload) of every response and revisit under path, checked; records of other types are passed over."""

    def number(text: str | None) -> int | None:
        if text is not None and not re.fullmatch(r"-?\d+", text):
            raise BadArchive(f"page number {text[:40]!r}")
        return None if text is None else int(text)

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            for data in got["content"]:
                out: dict[str, list] = {k: [] for k in ("record_id", "page_id", "url", "record_type", "refers_to", "payload_bytes", "payload_digest", "payload")}
                size = 0
                for raw in frames(data):
                    headers, block = parse(raw)
                    kind, digest = headers["warc-type"], headers.get("warc-payload-digest", "").removeprefix("sha256:")
                    if kind not in ("response", "revisit"):
                        continue
                    payload = payload_of(headers, block)
                    length = int(headers.get("page-payload-length", len(payload)))
                    if kind == "response" and (length != len(payload) or sha256(payload).hexdigest() != digest):
                        raise BadArchive(f"the payload of {headers['warc-record-id']} isn't what its headers say")
                    if kind == "revisit" and not {"warc-profile", "warc-refers-to-target-uri", "warc-refers-to-date", "page-refers-to"} <= headers.keys():
                        raise BadArchive("a revisit that refers to nothing")
                    url = headers.get("warc-target-uri")
                    row = (headers["warc-record-id"], number(headers.get("page-number")), None if url == _BLANK else url, kind, number(headers.get("page-refers-to")), length, digest, payload)
                    for k, v in zip(out, row):
                        out[k].append(v)
                    size += len(payload)
                    if size > 4 << 20:
                        yield out
                        out, size = {k: [] for k in out}, 0
                yield out

    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).where(F.col("length") > 0)
    return map_rows(files, ["content"], "record_id string, page_id bigint, url string, record_type string, refers_to bigint, payload_bytes bigint, payload_digest string, payload binary", run)


def unresolved(records: DataFrame) -> DataFrame:
    """Revisits among records (as read_archives returns them) without a response of that page and payload."""
    told = records.where("record_type = 'response'").select(F.col("page_id").alias("refers_to"), "payload_digest")
    return records.where("record_type = 'revisit'").join(told, ["refers_to", "payload_digest"], "left_anti")


def round_trip(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to) as read back from archives in the shared folder."""
    path = f"{shared_dir(spark)}/archives-{uuid.uuid4().hex}"
    write_archives(pages, path)
    return read_archives(spark, path).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
