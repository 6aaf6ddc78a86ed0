"""What the operators of this folder share: words, word hashes, tables in the
cluster's shared folder, and a lookup of 64-bit keys between batches of rows.

The lookup ("key exchange") is the one shuffle shape used for corpus-wide
counts: a batch of documents sends each distinct key once, cut by key range
into buckets; a bucket adds up what all batches sent and answers every batch
in the order of its keys. A key that a third of all rows hold therefore costs
one entry a batch, and no bucket grows with the copies of a key.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.shared import shared_dir, written

__all__ = ["shared_dir", "written"]

#: Bytes below 0x80 that are letters or digits keep their place, A-Z lower-cased; the rest become blanks.
ALNUM_TABLE = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))
LOWER_TABLE = bytes(range(256)).lower()
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def ascii_lower(col):
    """A-Z only; other letters stay as they are."""
    return F.translate(col, UPPER, LOWER)


def blank_words(text: str | None) -> list[bytes]:
    """Words ``[^\\x20\\x09-\\x0D]+`` of a text in UTF-8 (bytes.split() cuts at just these six bytes)."""
    return (text or "").encode("utf-8", "surrogatepass").split()


def alnum_words(text: str | None) -> list[bytes]:
    """Words of letters, digits and non-ASCII characters, A-Z lower-cased."""
    return (text or "").encode("utf-8", "surrogatepass").translate(ALNUM_TABLE).split()


def mix64(x: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_BASE, _CHUNK, LONG_WORD = 0xD1342543DE82EF95, 1 << 17, 128
_powers: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of the base and of its inverse, modulo 2^64."""
    if len(_powers.get("up", ())) < n:
        n = max(n, _CHUNK + 4096)
        for name, base in (("up", _BASE), ("down", pow(_BASE, -1, 1 << 64))):
            p = np.full(n, base, np.uint64)
            p[0] = 1
            _powers[name] = np.multiply.accumulate(p)
    return _powers["up"], _powers["down"]


_BLANK = np.zeros(256, bool)
_BLANK[[32, 9, 10, 11, 12, 13]] = True


def word_spans(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte offsets of the words between blanks: starts, ends."""
    inside = np.zeros(len(data) + 2, np.int8)
    inside[1:-1] = ~_BLANK[data]
    step = np.diff(inside)
    return np.nonzero(step == 1)[0], np.nonzero(step == -1)[0]


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte spans in order: a polynomial from running sums, then mixed with the length. Works through about 128 KB at a time.
    Polynomials modulo 2^64 agree on certain words of a thousand letters and more, so words of over LONG_WORD bytes are hashed one by one."""
    out, i, n = np.empty(len(starts), np.uint64), 0, len(starts)
    while i < n:
        low = int(starts[i])
        j = int(np.searchsorted(starts, low + _CHUNK, "left"))
        high = int(ends[j - 1])
        up, down = powers(high - low + 1)
        sums = np.zeros(high - low + 1, np.uint64)
        np.cumsum((data[low:high].astype(np.uint64) + np.uint64(1)) * up[: high - low], out=sums[1:])
        a, z = starts[i:j] - low, ends[i:j] - low
        out[i:j] = mix64((sums[z] - sums[a]) * down[a] + (z - a).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        i = j
    for k in np.nonzero(ends - starts > LONG_WORD)[0].tolist():
        out[k] = xxhash.xxh3_64_intdigest(np.ascontiguousarray(data[starts[k] : ends[k]]).tobytes())
    return out


def task_partition() -> int:
    from pyspark import TaskContext

    return TaskContext.get().partitionId()


def as_number(setting: str) -> int:
    """A setting in bytes or rows: digits, or digits with a unit as in 64MB."""
    digits = setting.strip().lower().rstrip("b")
    return int(digits[:-1]) << 10 * ("kmgt".index(digits[-1]) + 1) if digits[-1:] in ("k", "m", "g", "t") else int(digits)


def few_rows_a_batch(spark, most: int = 1000, most_bytes: int = 4 << 20) -> None:
    """Arrow batches of whole texts: at most so many rows and bytes in one, so that long texts and pages take bounded memory on both
    sides of the pipe. These are session settings, as a lazy result is read later; lower ones are kept."""
    for key, bound in (("maxRecordsPerBatch", most), ("maxBytesPerBatch", most_bytes)):
        key = f"spark.sql.execution.arrow.{key}"
        if not 0 < as_number(spark.conf.get(key)) <= bound:
            spark.conf.set(key, str(bound))


def give_back() -> None:
    """Returns freed memory to the system. Python workers serve one stage after the other; without this each keeps the most that any stage needed."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def frugal(fn: Callable) -> Callable:
    """A function for mapInArrow that gives memory back when its task ends."""

    def run(batches):
        yield from fn(batches)
        give_back()

    return run


def frugal_group(fn: Callable) -> Callable:
    """A function for applyInPandas that gives memory back after each group: groups here are large and few."""

    def run(pdf):
        out = fn(pdf)
        give_back()
        return out

    run.__annotations__ = {}
    return run


# ---------------------------------------------------------------- pages of documents

PAGE_SCHEMA = "page long, ids binary, body binary, n_words long, rest binary"
PAGE_CHARS = 2_000_000


def pack_rows(ids: list, texts: list) -> tuple[bytes, bytes]:
    """Ids (null: a marked place) and texts (null: length -1) of some rows in two compressed blobs."""
    raw = [None if t is None else t.encode("utf-8", "surrogatepass") for t in texts]
    sizes = np.array([-1 if t is None else len(t) for t in raw], np.int64)
    held = np.array([0 if i is None else i for i in ids], np.int64)
    null = np.array([i is None for i in ids], np.uint8)
    z = zstandard.ZstdCompressor(level=1)
    head = np.int64(len(ids)).tobytes() + held.tobytes() + null.tobytes() + sizes.tobytes()
    return z.compress(head), z.compress(b"".join((t or b"") + b"\n" for t in raw))


def unpack_rows(head: bytes, body: bytes) -> tuple[list, np.ndarray, bytes]:
    """Ids, sizes in bytes (-1: null) and the texts in a row, each with a line end after it."""
    z = zstandard.ZstdDecompressor()
    head = z.decompress(head)
    n = int(np.frombuffer(head, np.int64, 1)[0])
    ids = np.frombuffer(head, np.int64, n, 8).tolist()
    null = np.frombuffer(head, np.uint8, n, 8 + 8 * n)
    sizes = np.frombuffer(head, np.int64, n, 8 + 9 * n)
    return [None if x else i for i, x in zip(ids, null.tolist(), strict=True)], sizes, z.decompress(body)


def text_of(sizes: np.ndarray, body: bytes) -> list[bytes | None]:
    at = np.cumsum(np.maximum(sizes, 0) + 1).tolist()
    return [None if s < 0 else body[e - 1 - s : e - 1] for s, e in zip(sizes.tolist(), at, strict=True)]


class Page:
    """The documents of a page as one array of word hashes, with a sentinel (0) before the first and after each."""

    def __init__(self, head: bytes, body: bytes, table: bytes | None = None):
        self.ids, self.chars, self.body = unpack_rows(head, body)
        raw = self.body if table is None else self.body.translate(table)
        data = np.frombuffer(raw, np.uint8)
        self.data = data
        self.starts, self.ends = starts, ends = word_spans(data)
        close = np.cumsum(np.maximum(self.chars, 0) + 1)
        upto = np.searchsorted(starts, close)
        self.sizes = np.diff(upto, prepend=0)
        docs = np.arange(len(self.sizes))
        self.begin = upto - self.sizes + docs + 1
        self.flat = np.zeros(len(starts) + len(docs) + 1, np.uint64)
        self.end = np.zeros(len(self.flat), bool)
        self.end[0] = True
        self.end[self.begin + self.sizes] = True
        self.flat[~self.end] = span_hashes(data, starts, ends)

    def texts(self) -> list[bytes | None]:
        return text_of(self.chars, self.body)


def page_rows(batches: Iterator[pa.RecordBatch], base: int | None, page_chars: int = PAGE_CHARS) -> Iterator[pa.RecordBatch]:
    """Pages of rows of id, text and other columns, numbered from base, or, without base, by a hash of what they hold. The other columns go along as an Arrow stream."""
    made, ids, texts, chars, others = 0, [], [], 0, []

    def page() -> pa.RecordBatch:
        head, body = pack_rows(ids, texts)
        n = sum(len((t or "").split()) for t in texts)
        sink = pa.BufferOutputStream()
        if others:
            with pa.ipc.new_stream(sink, others[0].schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                for x in others:
                    out.write_batch(x)
        rest = sink.getvalue().to_pybytes()
        number = base + made if base is not None else (xxhash.xxh3_64_intdigest(head + body) >> 1)
        return pa.RecordBatch.from_pydict({"page": pa.array([number], pa.int64()), "ids": pa.array([head], pa.binary()), "body": pa.array([body], pa.binary()), "n_words": pa.array([n], pa.int64()), "rest": pa.array([rest], pa.binary())})

    for b in (whole.slice(i, 500) for whole in batches for i in range(0, whole.num_rows, 500)):  # few rows at a time as Python strings
        extra, done = b.select(b.schema.names[2:]) if b.num_columns > 2 else None, 0
        for k, (i, t) in enumerate(zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True), 1):
            ids.append(i)
            texts.append(t)
            chars += len(t or "")
            if chars >= page_chars or len(ids) >= 50_000:
                if extra is not None:
                    others.append(extra.slice(done, k - done))
                    done = k
                yield page()
                made, ids, texts, chars, others = made + 1, [], [], 0, []
        if extra is not None and done < b.num_rows:
            others.append(extra.slice(done))
    if ids:
        yield page()


def pages(docs: DataFrame, id_col: str, text_col: str, others: list[str] | None = None) -> DataFrame:
    """Documents in pages of about 2 MB of text each, whole texts, written to the shared folder: rows (page, ids, body, n_words, rest)."""
    few_rows_a_batch(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long"), F.col(text_col).cast("string"), *(others or []))
    return written(rows.mapInArrow(frugal(lambda batches: page_rows(batches, task_partition() << 32)), PAGE_SCHEMA))


# ---------------------------------------------------------------- key exchange

REQUEST_SCHEMA = "page long, bucket int, keys binary, vals binary"
KEYS_PER_BUCKET = 2_000_000


def buckets_for(n_keys: int) -> int:
    """Buckets such that one holds about 2 million keys at most: the number follows the data, the size of a bucket doesn't."""
    return max(24, -(-int(n_keys) // KEYS_PER_BUCKET))


def requests(page: int, keys: np.ndarray, vals: np.ndarray, buckets: int) -> list[dict]:
    """keys: (n, lanes) of uint64, sorted by the first lane; vals: n numbers of 8 bytes. One row for each bucket that has keys."""
    first = keys[:, 0]
    edges = np.array([(i << 64) // buckets for i in range(1, buckets)], dtype=np.uint64)
    cuts = [0, *np.searchsorted(first, edges).tolist(), len(first)]
    return [{"page": page, "bucket": b, "keys": keys[i:j].tobytes(), "vals": vals[i:j].tobytes()} for b, (i, j) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)) if j > i]


def as_batch(rows: list[dict], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_pylist(rows, schema)


REQUEST_ARROW = pa.schema([("page", pa.int64()), ("bucket", pa.int32()), ("keys", pa.binary()), ("vals", pa.binary())])


def exchange(asked: DataFrame, lanes: int, answer: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> DataFrame:
    """(page, said): for each page the answers to its keys, in their order, in parts to be joined.

    answer(group, vals): group numbers equal keys alike (0..g-1), vals are what
    the pages sent with them; it returns one array, aligned with them, of the
    dtype in which answers are stored.
    """
    return answers(exchange_rows(asked, lanes, answer))


def answers(said: DataFrame) -> DataFrame:
    return said.groupBy("page").agg(F.sort_array(F.collect_list(F.struct("bucket", "said"))).alias("parts")).select("page", F.expr("transform(parts, x -> x.said)").alias("said"))


def exchange_rows(asked: DataFrame, lanes: int, answer: Callable[[np.ndarray, np.ndarray], np.ndarray], note: Callable[[np.ndarray, np.ndarray, np.ndarray], bytes] | None = None) -> DataFrame:
    """Answers by page and bucket; with note(keys, group, vals) also a row of page -1 for each bucket, with what it noted."""
    import pandas as pd

    def reduce(pdf: pd.DataFrame) -> pd.DataFrame:
        sizes = [len(v) // 8 for v in pdf["vals"]]
        keys = np.frombuffer(b"".join(pdf["keys"]), np.uint64).reshape(-1, lanes)
        vals = np.frombuffer(b"".join(pdf["vals"]), np.int64)
        order = np.lexsort(tuple(keys[:, i] for i in range(lanes - 1, -1, -1))) if lanes > 1 else np.argsort(keys[:, 0], kind="stable")
        s = keys[order]
        new = np.ones(len(s), bool)
        new[1:] = (s[1:] != s[:-1]).any(axis=1)
        group = np.empty(len(s), np.int64)
        group[order] = np.cumsum(new) - 1
        said = answer(group, vals)
        ends = np.cumsum(sizes)
        out = pd.DataFrame({"page": pdf["page"], "bucket": pdf["bucket"], "said": [said[e - n : e].tobytes() for n, e in zip(sizes, ends, strict=True)]})
        if note:
            out = pd.concat([out, pd.DataFrame({"page": [-1], "bucket": pdf["bucket"].iloc[:1], "said": [note(keys, group, vals)]})], ignore_index=True)
        return out

    return asked.groupBy("bucket").applyInPandas(frugal_group(reduce), "page long, bucket int, said binary")


def sum_by(group: np.ndarray, vals: np.ndarray) -> np.ndarray:
    """Each key's sum over all pages, exact for sums below 2^53."""
    return np.bincount(group, weights=vals.astype(np.float64))[group].astype(np.int64)
