"""WARC archives in the dictionary-compressed layout (.warc.zst).

An archive starts with a skippable frame that holds a Zstandard dictionary built
from the archive's own records; each record follows as a frame of its own, so
any record can be read alone. Records with equal payloads of at least
`least_bytes` bytes are written once, as the response with the largest page id;
the others become revisit records without a body.

Fault tolerance: an attempt of a task writes files under names of its own and
reports them as rows; the reader opens only files reported by attempts that
ended well. Nothing is overwritten, and a lost executor leaves unreported files.

Defined results: null html is an empty payload; a null page id is kept as null;
a null url is archived under a urn of its page id; of repeated rows with the
largest page id each is a response; an empty table gives no archives; columns
beside page_id, url and html are not archived.
"""

from __future__ import annotations

import base64
import hashlib
import os
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import shared_dir, written

# Fixed values of the public formats: magic number of the skippable frame that holds the dictionary, the revisit profile, the version line.
DICTIONARY_MAGIC = 0x184D2A5D
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
VERSION_LINE = "WARC/1.1"

#: Uncompressed bytes of records in one archive, bytes of its dictionary, and bytes of records (spread evenly over the archive) that the dictionary is built from.
ARCHIVE_BYTES, DICTIONARY_BYTES, TRAINING_BYTES = 24_000_000, 65_536, 1_500_000
#: Payloads that repeat, up to which they are broadcast (60 bytes each).
MOST_BROADCAST = 200_000


def file_system(uri: str) -> tuple[pafs.FileSystem, str]:
    if uri.startswith("file:"):
        return pafs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return pafs.FileSystem.from_uri(uri)


# ---------------------------------------------------------------- records


def header_value(text: str) -> str:
    """A header holds no control characters or blanks."""
    return "".join(c if c > " " and c != "\x7f" else f"%{ord(c):02X}" for c in text)


def record(page_id: int | None, url: str | None, payload: bytes, digest: bytes, refers_to: int | None, date: str) -> bytes:
    name = "none" if page_id is None else str(page_id)
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    body = http if refers_to is not None else http + payload
    lines = [
        VERSION_LINE,
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{name}:{digest.hex()}')}>",
        f"WARC-Target-URI: {header_value(url) if url else 'urn:page:' + name}",
        f"WARC-Date: {date}",
        f"WARC-Payload-Digest: sha1:{base64.b32encode(digest).decode()}",
        *([] if page_id is None else [f"X-Page-Id: {page_id}"]),
        *([] if refers_to is None else [f"WARC-Profile: {REVISIT_PROFILE}", f"WARC-Refers-To: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{refers_to}:{digest.hex()}')}>", f"X-Refers-To-Page: {refers_to}"]),
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(body)}",
    ]
    return "\r\n".join(lines).encode("utf-8", "surrogatepass") + b"\r\n\r\n" + body + b"\r\n\r\n"


def parsed(raw: bytes) -> tuple[dict[str, str], dict[str, str], bytes]:
    """Headers of the record, of its HTTP block, and the payload."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    warc = dict(x.split(": ", 1) for x in head.decode("utf-8", "surrogatepass").split("\r\n")[1:])
    block = rest[: int(warc["Content-Length"])]
    http_head, _, payload = block.partition(b"\r\n\r\n")
    return warc, dict(x.split(": ", 1) for x in http_head.decode().split("\r\n")[1:]), payload


# ---------------------------------------------------------------- archives


def dictionary(records: list[bytes]) -> zstandard.ZstdCompressionDict:
    """From records spread evenly over the archive; too few for training: the records' own bytes are the dictionary."""
    step = max(1, -(-sum(map(len, records)) // TRAINING_BYTES))
    chosen = records[::step]
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, chosen, k=256, d=8)
    except zstandard.ZstdError:
        return zstandard.ZstdCompressionDict(b"".join(chosen)[-DICTIONARY_BYTES:] or b"\0" * 8, dict_type=zstandard.DICT_TYPE_RAWCONTENT)


def archive_bytes(records: list[bytes], level: int) -> bytes:
    d = dictionary(records)
    held = d.as_bytes()
    z = zstandard.ZstdCompressor(level=level, dict_data=d, write_content_size=True)
    return struct.pack("<II", DICTIONARY_MAGIC, len(held)) + held + b"".join(map(z.compress, records))


def frames(data: bytes) -> Iterator[bytes]:
    """The records of an archive, one after the other."""
    magic, size = struct.unpack_from("<II", data)
    if magic != DICTIONARY_MAGIC:
        raise ValueError("no dictionary frame at the start of the archive")
    held = data[8 : 8 + size]
    kind = zstandard.DICT_TYPE_FULLDICT if held[:4] == b"\x37\xa4\x30\xec" else zstandard.DICT_TYPE_RAWCONTENT
    z, at, view = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(held, dict_type=kind)), 8 + size, memoryview(data)
    while at < len(data):
        one, parts = z.decompressobj(), []
        while not one.eof:
            if at >= len(data):
                raise ValueError("the archive ends inside a record")
            chunk = view[at : at + 8192]
            parts.append(one.decompress(chunk))
            at += len(chunk) - (len(one.unused_data) if one.eof else 0)
        yield b"".join(parts)


# ---------------------------------------------------------------- Spark


def with_revisits(pages: DataFrame, least_bytes: int) -> DataFrame:
    """page_id, url, html, digest, refers_to. One partial aggregate finds the responses of payloads that repeat; up to a counted bound they go to
    every task and no page is shuffled. Beyond it, pages are joined by digest: those of the most frequent payloads where they stand, short ones not at all."""
    size = F.octet_length("html")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html")).withColumn("digest", F.sha1(F.encode("html", "UTF-8")))
    heads = rows.where(size >= least_bytes).groupBy("digest").agg(F.max("page_id").alias("head"), F.count(F.lit(1)).alias("n")).where("n > 1 and head is not null")
    heads = written(heads)
    if heads.limit(MOST_BROADCAST + 1).count() <= MOST_BROADCAST:
        joined = rows.join(F.broadcast(heads.drop("n")), "digest", "left")
    else:
        total = heads.agg(F.sum("n")).first()[0]
        frequent = F.broadcast(heads.where(F.col("n") > total // max(1, MOST_BROADCAST)).drop("n"))  # fewer than MOST_BROADCAST
        long = rows.where(size >= least_bytes)
        rare = long.join(frequent, "digest", "left_anti").join(heads.drop("n"), "digest", "left")
        joined = rare.unionByName(long.join(frequent, "digest")).unionByName(rows.where(size < least_bytes), allowMissingColumns=True)
    return joined.select("page_id", "url", "html", "digest", F.when(~F.col("page_id").eqNullSafe(F.col("head")), F.col("head")).alias("refers_to"))


def write_archives(pages: DataFrame, folder: str, least_bytes: int = 1000, date: str = "2024-01-01T00:00:00Z", level: int = 6) -> DataFrame:
    """Writes the archives; returns (archive string, records long, bytes long), the files of tasks that ended well."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, top = file_system(folder)
        store.create_dir(top, recursive=True)
        tag, made, held, size = uuid.uuid4().hex[:16], 0, [], 0

        def flush() -> pa.RecordBatch:
            name = f"{tag}-{made:05d}.warc.zst"
            data = archive_bytes(held, level)
            with store.open_output_stream(f"{top}/{name}") as out:
                out.write(data)
            return pa.RecordBatch.from_pydict({"archive": [name], "records": pa.array([len(held)], pa.int64()), "bytes": pa.array([len(data)], pa.int64())})

        for b in batches:
            for page_id, url, html, digest, refers in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                held.append(record(page_id, url, html.encode("utf-8", "surrogatepass"), bytes.fromhex(digest), refers, date))
                size += len(held[-1])
                if size >= ARCHIVE_BYTES:
                    yield flush()
                    made, held, size = made + 1, [], 0
        if held:
            yield flush()

    return with_revisits(pages, least_bytes).mapInArrow(run, "archive string, records long, bytes long")


READ = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"


def read_archives(archives: DataFrame, folder: str, payloads: bool = True) -> DataFrame:
    """One row a record. Digest and length of a response are computed from the payload as read and must equal its header; those of a revisit come from its headers. payload is null for revisits, and where payloads is False."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, top = file_system(folder)
        schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())])
        for b in batches:
            for name in b.column(0).to_pylist():
                with store.open_input_stream(f"{top}/{name}") as f:
                    data = f.read()
                rows = []
                for raw in frames(data):
                    warc, http, payload = parsed(raw)
                    digest = base64.b32decode(warc["WARC-Payload-Digest"].removeprefix("sha1:")).hex()
                    kind = warc["WARC-Type"]
                    if kind == "response" and (hashlib.sha1(payload).hexdigest() != digest or len(payload) != int(http["Content-Length"])):
                        raise ValueError(f"a record of {name} does not match its digest")
                    page, refers = warc.get("X-Page-Id"), warc.get("X-Refers-To-Page")
                    rows.append({"page_id": page and int(page), "url": warc["WARC-Target-URI"], "payload_bytes": int(http["Content-Length"]), "payload_digest": digest, "record_type": kind, "refers_to": refers and int(refers), "payload": payload if payloads and kind == "response" else None})
                    if len(rows) == 2000:
                        yield pa.RecordBatch.from_pylist(rows, schema)
                        rows = []
                yield pa.RecordBatch.from_pylist(rows, schema)

    return archives.select("archive").repartition(max(1, archives.count() // 2)).mapInArrow(run, READ)


def archive_round_trip(spark: SparkSession, pages: DataFrame, least_bytes: int = 1000) -> DataFrame:
    """Writes all pages to archives in the shared folder and reads them back."""
    folder = os.path.join(shared_dir(spark), "warc")
    manifest = written(write_archives(pages, folder, least_bytes), spark)
    return read_archives(manifest, folder, payloads=False).drop("payload")
