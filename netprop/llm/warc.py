"""WARC archives compressed with Zstandard and a shared dictionary: writer and reader.

An archive opens with a skippable frame that holds the dictionary (raw, or
compressed as a frame of its own); then each record is one frame compressed with
that dictionary, so a reader can start at any record. The reader loads the
dictionary from the leading frame, decodes one frame a record, and checks version
line, mandatory headers, declared length, record end and payload digest.

Archives of a table are rows of bytes (``archive``, ``data``) in the shared
store; :func:`read_files` reads ``*.warc.zst`` files of any Spark file system.
"""

from __future__ import annotations

import base64
import hashlib
import itertools
import uuid

import pyarrow as pa
import zstandard as zstd
from pyspark.sql import DataFrame, SparkSession, functions as F

from netprop.llm import common

#: Fixed values of the formats.
SKIPPABLE_MAGIC = 0x184D2A5D
FRAME_MAGIC = b"\x28\xb5\x2f\xfd"
VERSION = b"WARC/1.1"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

#: Bytes of records in one archive, about.
ARCHIVE_BYTES = 8 << 20
#: Dictionary: bytes, and bytes of the archive's own first records that it is trained on.
DICTIONARY_BYTES, SAMPLE_BYTES = 16 << 10, 1 << 20


class InvalidRecord(ValueError):
    """An archive or record that breaks the format."""


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


#: What an archive that breaks the format raises.
ERRORS = (InvalidRecord, zstd.ZstdError, UnicodeDecodeError)


# -------------------------------------------------------------------- records


def build_record(headers: list[tuple[str, str]], block: bytes) -> bytes:
    """Header values keep no line breaks; the block is followed by two line ends."""
    lines = [VERSION] + [f"{k}: {' '.join(v.split())}".encode() for k, v in headers] + [b"Content-Length: %d" % len(block)]
    return b"\r\n".join(lines) + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_record(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Headers (names in lower case) and block of one whole record; InvalidRecord otherwise."""
    head, found, rest = raw.partition(b"\r\n\r\n")
    lines = head.split(b"\r\n")
    if not found or not lines[0].startswith(b"WARC/1."):
        raise InvalidRecord("no version line or no end of headers")
    headers: dict[str, str] = {}
    for line in lines[1:]:
        name, colon, value = line.decode("utf-8").partition(":")
        if not colon:
            raise InvalidRecord(f"header without a colon: {name[:40]}")
        headers[name.strip().lower()] = value.strip()
    for name in ("warc-record-id", "warc-type", "warc-date", "content-length"):
        if not headers.get(name):
            raise InvalidRecord(f"no {name}")
    if not headers["content-length"].isdigit():
        raise InvalidRecord("content-length is no number")
    size = int(headers["content-length"])
    if len(rest) != size + 4 or rest[size:] != b"\r\n\r\n":
        raise InvalidRecord(f"content-length {size}, but {len(rest) - 4} bytes stand before the end")
    return headers, rest[:size]


def http_response(payload: bytes) -> bytes:
    return b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload) + payload


def http_payload(block: bytes) -> bytes:
    head, found, body = block.partition(b"\r\n\r\n")
    if not found or not head.startswith(b"HTTP/"):
        raise InvalidRecord("no HTTP header in a response")
    return body


# ------------------------------------------------------------------- archives


def build_archive(records: list[bytes], level: int = 3) -> bytes:
    """Dictionary in a leading skippable frame (compressed), then one frame a record."""
    sample, size = [], 0
    for r in records:
        sample.append(r[: 1 << 16])
        size += len(sample[-1])
        if size > SAMPLE_BYTES:
            break
    try:
        dictionary = zstd.train_dictionary(min(DICTIONARY_BYTES, max(256, size // 8)), sample, level=level).as_bytes()
    except zstd.ZstdError:  # too few records to learn from: a plain-content dictionary
        dictionary = (b"".join(sample) or VERSION)[:DICTIONARY_BYTES].ljust(8, b" ")
    held = zstd.ZstdCompressor(level=level).compress(dictionary)
    shared = zstd.ZstdCompressionDict(dictionary)
    packer = zstd.ZstdCompressor(level=level, dict_data=shared, write_checksum=True, write_content_size=True)
    return b"".join([SKIPPABLE_MAGIC.to_bytes(4, "little"), len(held).to_bytes(4, "little"), held, *map(packer.compress, records)])


def read_archive(data: bytes):
    """Headers and block of each record, in order. Archives without a dictionary are read too."""
    at, options = 0, {}
    if int.from_bytes(data[:4], "little") == SKIPPABLE_MAGIC:
        size = int.from_bytes(data[4:8], "little")
        held = data[8 : 8 + size]
        if len(held) != size:
            raise InvalidRecord("the dictionary frame is cut short")
        if held[:4] == FRAME_MAGIC:
            held = zstd.ZstdDecompressor().decompressobj().decompress(held)
        options["dict_data"] = zstd.ZstdCompressionDict(held)
        at = 8 + size
    reader = zstd.ZstdDecompressor(**options)
    view = memoryview(data)
    while at < len(data):
        if data[at : at + 4] != FRAME_MAGIC:
            raise InvalidRecord(f"no frame at byte {at}")
        frame, out = reader.decompressobj(), []
        while not frame.eof and at < len(data):
            part = view[at : at + (1 << 16)]
            out.append(frame.decompress(part))
            at += len(part)
        if not frame.eof:
            raise InvalidRecord("the last frame is cut short")
        at -= len(frame.unused_data)
        yield parse_record(b"".join(out))


# ------------------------------------------------------------------ operators


def plan_records(pages: DataFrame, min_bytes: int = 0, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``(page_id, url, payload, refers_to)``: rows with ``refers_to`` are revisits of the page of that id.

    Of pages with equal payloads of ``min_bytes`` or more, the smallest id is the response.
    """
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.coalesce(F.col(url_col).cast("string"), F.lit("")).alias("url"), F.coalesce(F.col(html_col).cast("binary"), F.lit(b"")).alias("payload"))
    rows = rows.withColumn("digest", F.unhex(F.sha1("payload")))
    firsts = rows.where(F.octet_length("payload") >= min_bytes).groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").select("digest", "first")
    found = rows.join(firsts, "digest", "left")
    return found.select("page_id", "url", "payload", F.when(F.col("page_id") != F.col("first"), F.col("first")).alias("refers_to"))


def write_archives(records: DataFrame, date: str = "2024-01-01T00:00:00Z", level: int = 3, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """``(archive, n_records, data)`` of :func:`plan_records` rows; a revisit's block is empty."""

    def run(batches):
        def out():
            name = str(uuid.uuid5(uuid.NAMESPACE_URL, hashlib.sha1(b"".join(held)).hexdigest()))
            data = build_archive(held, level)
            return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([len(held)], pa.int32()), pa.array([data], pa.binary())], names=["archive", "n_records", "data"])

        held, size = [], 0
        for batch in batches:
            for page, url, payload, first in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                name = lambda x: f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_OID, str(x))}>"
                headers = [("WARC-Type", "response" if first is None else "revisit"), ("WARC-Record-ID", name(page)), ("WARC-Date", date), ("WARC-Target-URI", url), ("WARC-Payload-Digest", f"sha1:{payload_digest(payload)}"), ("X-Page-ID", "" if page is None else str(page)), ("X-Payload-Length", str(len(payload)))]
                if first is None:
                    block = http_response(payload)
                    headers.append(("Content-Type", "application/http;msgtype=response"))
                else:
                    block = b""
                    headers += [("WARC-Profile", REVISIT_PROFILE), ("WARC-Refers-To", name(first)), ("X-Refers-To-Page", str(first))]
                held.append(build_record(headers, block))
                size += len(held[-1])
                if size > archive_bytes:
                    yield out()
                    held, size = [], 0
        if held:
            yield out()

    return records.select("page_id", "url", "payload", "refers_to").mapInArrow(run, "archive string, n_records int, data binary")


_READ_DDL = "archive string, page_id long, url string, record_type string, payload_bytes long, payload_digest string, refers_to long, payload binary"


def checked_records(data: bytes):
    """Headers, block and payload of each record (None for other kinds than responses), whose digest must fit."""
    for head, block in read_archive(data):
        body = http_payload(block) if head["warc-type"] == "response" else None
        digest = head.get("warc-payload-digest", "").removeprefix("sha1:")
        if body is not None and digest and payload_digest(body) != digest:
            raise InvalidRecord(f"payload of {head['warc-record-id']} has another digest")
        yield head, digest, body


def rejected(archives: DataFrame, name_col: str = "archive", data_col: str = "data") -> DataFrame:
    """``(archive, error, n_read)`` of the archives that break the format: what is wrong, and after how many sound records."""

    def run(batches):
        for batch in batches:
            out = []
            for name, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                n = 0
                try:
                    for _ in checked_records(data or b""):
                        n += 1
                except ERRORS as e:
                    out.append((name, str(e), n))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate((pa.string(), pa.string(), pa.int64()))], names=["archive", "error", "n_read"])

    return archives.select(F.col(name_col).alias("archive"), F.col(data_col).alias("data")).mapInArrow(run, "archive string, error string, n_read long")


def read_archives(archives: DataFrame, name_col: str = "archive", data_col: str = "data", keep_payload: bool = True, strict: bool = True) -> DataFrame:
    """One row per record of the archives. A malformed archive or a wrong digest raises InvalidRecord, or with ``strict=False`` ends that archive: see :func:`rejected`.

    ``payload`` is null for revisits, whose length and digest are those of the page they refer to.
    """

    def sound(data):
        try:
            yield from checked_records(data)
        except ERRORS:
            if strict:
                raise

    def run(batches):
        for batch in batches:
            for name, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                records = sound(data or b"")
                while some := list(itertools.islice(records, 256)):
                    out = []
                    for head, digest, body in some:
                        kind = head["warc-type"]
                        size = len(body) if body is not None else int(head.get("x-payload-length") or 0)
                        number = lambda k, head=head: int(head[k]) if head.get(k) else None
                        out.append((name, number("x-page-id"), head.get("warc-target-uri"), kind, size, digest, number("x-refers-to-page"), body if keep_payload else None))
                    kinds = (pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], kind) for i, kind in enumerate(kinds)], names=["archive", "page_id", "url", "record_type", "payload_bytes", "payload_digest", "refers_to", "payload"])

    return archives.select(F.col(name_col).alias("archive"), F.col(data_col).alias("data")).mapInArrow(run, _READ_DDL)


def read_files(spark: SparkSession, path: str, keep_payload: bool = True) -> DataFrame:
    """Records of the ``*.warc.zst`` files under ``path``."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.zst").load(path)
    return read_archives(files.select("path", "content"), "path", "content", keep_payload)


def export_files(archives: DataFrame, folder: str) -> int:
    """Write archives as files into a folder that the driver sees, one after the other; for small exports and tests."""
    n = 0
    for row in archives.toLocalIterator():
        with open(f"{folder}/{row.archive}.warc.zst", "wb") as out:
            out.write(row.data)
        n += 1
    return n


def round_trip(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """Write all pages to archives in the shared store, read these back: one row per page.

    Null html is an empty payload. Repeated rows give a record each; rows of one
    id with equal payloads are all responses, as none comes before the other.
    Rows with a null id are responses unless a page with an id has their payload.
    """
    archives = common.stored(write_archives(plan_records(pages, min_bytes)), "archives")
    return read_archives(archives, keep_payload=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url")
