"""Repeated passages by recompression.

A page of documents is a row of word symbols. Rounds shorten it: a run of equal
symbols becomes one symbol, then each pair whose left symbol falls on the left
side and whose right symbol on the right side of the round becomes one. Names
and sides are hashes of what they name, so every page gives equal tokens equal
names, without a dictionary that all pages would have to share. Each symbol also
carries the stretch of words on which its coming to be depends: two equal
windows of words agree on every symbol whose stretch lies inside them.

A window's anchor is the symbol of the highest level that its own words
determine (at level 0 a single word, so each window has one). Anchors are looked
up over the whole corpus: a window whose anchor stands nowhere else repeats
nowhere. Of the others a 128-bit print of their own words, again over the whole
corpus, verifies the repeat.

Both look-ups send keys, once a page, by key range (common.exchange); a passage
that a third of all documents hold is one key a page.

Defined results: a null or empty text has no words; documents shorter than the
window keep all; repeated rows repeat each other; null ids are kept as null.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import REQUEST_ARROW, REQUEST_SCHEMA, Page, buckets_for, exchange, frugal, mix64, pages, requests, sum_by, written

WINDOW = 35
_M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
_B1, _B2 = 0xD1342543DE82EF95, 0xAF251AF3B0F025B5


def window_starts(page: Page, n: int) -> np.ndarray:
    """Places where a window of n words starts."""
    count = np.maximum(page.sizes - n + 1, 0)
    return np.repeat(page.begin - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))


def levels(page: Page, n: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(name, first, last) of the symbols of each level, sentinels left out: [first, last] are the words that a symbol depends on."""
    sym, end = page.flat, page.end
    first = np.arange(len(sym), dtype=np.int32)
    last = first.copy()
    level = 0
    while True:
        own = ~end & (last - first < n)
        if not own.any():
            return
        yield mix64(sym[own] + np.uint64(level * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)), first[own], last[own]
        level += 1
        if level % 3 == 1:
            # Runs, in every third round. A symbol depends on the next symbol on either side: it differs from it. How long a run that symbol is in does not matter.
            same = (sym[1:] == sym[:-1]) & ~end[1:] & ~end[:-1]
            lead = np.nonzero(np.concatenate([[True], ~same]))[0]
            length = np.diff(np.append(lead, len(sym)))
            tail = lead + length - 1
            f, z = first[lead], last[tail]
            first = np.minimum(f, np.concatenate([f[:1], first[tail[:-1]]]))
            last = np.maximum(z, np.concatenate([last[lead[1:]], z[-1:]]))
            sym, end = sym[lead], end[lead]
            many = length > 1
            sym = np.where(many, mix64(sym * _M2 + length.astype(np.uint64)), sym)
        # Pairs. A symbol on the left side depends on the next, on the right side on the one before, if it stays alone.
        side = (mix64(sym ^ np.uint64((level * 0x5851F42D4C957F2D) & 0xFFFFFFFFFFFFFFFF)) >> np.uint64(63)).astype(bool)
        pair = np.zeros(len(sym), bool)
        pair[:-1] = ~side[:-1] & side[1:] & ~end[:-1] & ~end[1:]
        second = np.concatenate([[False], pair[:-1]])
        nxt_last, nxt_sym = np.append(last[1:], last[-1:]), np.append(sym[1:], sym[-1:])
        prev_first = np.concatenate([first[:1], first[:-1]])
        merged_last = np.where(pair | ~side, np.maximum(last, nxt_last), last)
        merged_first = np.where(~pair & side, np.minimum(first, prev_first), first)
        sym = np.where(pair, mix64(sym * _M1 + mix64(nxt_sym ^ _M2)), sym)
        keep = ~second
        sym, end, first, last = sym[keep], end[keep], merged_first[keep], merged_last[keep]


def anchors(page: Page, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts of all windows, the key of each window's anchor, and whether the anchor is another place than that of the window before."""
    starts = window_starts(page, n)
    key, place = np.zeros(len(starts), np.uint64), np.full(len(starts), -1, np.int64)
    if len(starts):
        open_ = np.arange(len(starts))
        for level, (name, first, last) in reversed(list(enumerate(levels(page, n)))):
            s = starts[open_]
            j = np.searchsorted(first, s)
            ok = j < len(first)
            j[~ok] = 0
            ok &= (last[j] <= s + n - 1) & (first[j] >= s)
            key[open_[ok]] = name[j[ok]]
            place[open_[ok]] = (level << 40) + j[ok]
            open_ = open_[~ok]
            if not len(open_):
                break
    return starts, key, np.diff(place, prepend=-1) != 0


def prints(page: Page, starts: np.ndarray, n: int) -> np.ndarray:
    """Two independent 64-bit polynomial prints of each window, odd bases, modulo 2^64."""
    out = np.empty((len(starts), 2), np.uint64)
    size = len(page.flat)
    for lane, (base, x) in enumerate(((_B1, page.flat), (_B2, mix64(page.flat ^ _M1)))):
        power = np.full(size + 1, base, np.uint64)
        power[0] = 1
        np.multiply.accumulate(power, out=power)
        back = np.full(size + 1, pow(base, -1, 1 << 64), np.uint64)
        back[0] = 1
        np.multiply.accumulate(back, out=back)
        sums = np.zeros(size + 1, np.uint64)
        np.cumsum(x * power[:size], out=sums[1:])
        out[:, lane] = mix64((sums[starts + n] - sums[starts]) * back[starts])
    return out


def distinct(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct rows, how often each stands, and where each given row went."""
    order = np.lexsort((keys[:, 1], keys[:, 0])) if keys.shape[1] == 2 else np.argsort(keys[:, 0], kind="stable")
    s = keys[order]
    new = np.ones(len(s), bool)
    new[1:] = (s[1:] != s[:-1]).any(axis=1)
    at = np.nonzero(new)[0]
    where = np.empty(len(s), np.int64)
    where[order] = np.cumsum(new) - 1
    return s[at], np.diff(np.append(at, len(s))), where


def shared(said: list[bytes] | None) -> np.ndarray:
    return np.frombuffer(b"".join(said or []), np.uint8).astype(bool)


def occurs_twice(group: np.ndarray, vals: np.ndarray) -> np.ndarray:
    return (sum_by(group, vals) > 1).astype(np.uint8)


def covered(page: Page, repeated: np.ndarray, n: int) -> np.ndarray:
    """Words inside windows that start at the given places."""
    step = np.zeros(len(page.flat) + n + 1, np.int32)
    np.add.at(step, repeated, 1)
    np.add.at(step, repeated + n, -1)
    return np.cumsum(step)[: len(page.flat)] > 0


def repeated_words(docs: DataFrame, emit: Callable[[Page, np.ndarray, bytes], pa.RecordBatch], schema, n: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", others: list[str] | None = None) -> DataFrame:
    """Finds, over all documents, the words inside windows of n words that stand more than once, and hands each page, its mask and its other columns to emit()."""
    spark = docs.sparkSession
    packed = pages(docs, id_col, text_col, others=others)
    total = packed.agg(F.sum("n_words")).first()[0] or 0
    some, most = buckets_for(total // 8), buckets_for(total // 2)

    def ask_anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for number, head, body in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                _, key, new = anchors(Page(head, body), n)
                keys, count, _ = distinct(key[new][:, None])
                yield pa.RecordBatch.from_pylist(requests(number, keys, np.minimum(count, 2), some), REQUEST_ARROW)

    first = written(exchange(packed.select("page", "ids", "body").mapInArrow(frugal(ask_anchors), REQUEST_SCHEMA), 1, occurs_twice), spark)

    def candidates(page: Page, said: list[bytes] | None) -> np.ndarray:
        starts, key, new = anchors(page, n)
        if not len(starts):
            return starts
        _, _, where = distinct(key[new][:, None])
        return starts[shared(said)[where][np.cumsum(new) - 1]]

    def ask_prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for number, head, body, said in zip(*(c.to_pylist() for c in b.columns), strict=True):
                page = Page(head, body)
                keys, count, _ = distinct(prints(page, candidates(page, said), n))
                yield pa.RecordBatch.from_pylist(requests(number, keys, np.minimum(count, 2), most), REQUEST_ARROW)

    with_first = packed.join(first, "page", "left").select("page", "ids", "body", "said")
    second = exchange(with_first.mapInArrow(frugal(ask_prints), REQUEST_SCHEMA), 2, occurs_twice).withColumnRenamed("said", "said2")

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for head, body, rest, said, said2 in zip(*(c.to_pylist() for c in b.columns), strict=True):
                page = Page(head, body)
                starts = candidates(page, said)
                _, _, where = distinct(prints(page, starts, n))
                hit = starts[shared(said2)[where]] if len(starts) else starts
                yield emit(page, covered(page, hit, n), rest)

    return packed.join(first.join(second, "page", "left"), "page", "left").select("ids", "body", "rest", "said", "said2").mapInArrow(frugal(finish), schema)


DIGEST = "doc_id long, n_words long, n_removed long, kept_sha256 string"


def removed_digest(docs: DataFrame, n: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (of the kept words, joined by one space)."""

    def emit(page: Page, gone: np.ndarray, _: bytes) -> pa.RecordBatch:
        out_n, out_sha = [], []
        for at, w in zip(page.begin.tolist(), page.texts(), strict=True):
            w = (w or b"").split()
            mask = gone[at : at + len(w)]
            kept = [x for x, g in zip(w, mask.tolist(), strict=True) if not g] if mask.any() else w
            out_n.append(len(w) - len(kept))
            out_sha.append(hashlib.sha256(b" ".join(kept)).hexdigest())
        return pa.RecordBatch.from_arrays([pa.array(page.ids, pa.int64()), pa.array(page.sizes), pa.array(out_n, pa.int64()), pa.array(out_sha)], names=["doc_id", "n_words", "n_removed", "kept_sha256"])

    return repeated_words(docs, emit, DIGEST, n)


_WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def cut(text: bytes, gone: np.ndarray) -> bytes:
    """The text without the words that are gone and the blanks after them; the rest stays as it was."""
    out, at, skip = [], 0, False
    for m, g in zip(_WORD.finditer(text), gone.tolist(), strict=True):
        if g and not skip:
            out.append(text[at : m.start()])
        elif skip and not g:
            at = m.start()
        skip = g
    if not skip:
        out.append(text[at:])
    return b"".join(out)


def without_repeats(docs: DataFrame, n: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", chars_col: str | None = "n_chars") -> DataFrame:
    """The rows of docs, all their columns, the text without repeated passages (null stays null; texts without any stay byte for byte), chars_col its new length."""
    others = [c for c in docs.columns if c not in (id_col, text_col)]
    schema = docs.select(F.col(id_col).cast("long"), F.col(text_col).cast("string"), *others).schema

    def emit(page: Page, gone: np.ndarray, rest: bytes) -> pa.RecordBatch:
        texts, sizes = [], []
        for at, w, t in zip(page.begin.tolist(), page.sizes.tolist(), page.texts(), strict=True):
            mask = gone[at : at + w]
            kept = cut(t, mask) if mask.any() else t
            texts.append(None if kept is None else kept.decode("utf-8", "surrogatepass"))
            sizes.append(len(texts[-1]) if mask.any() else None)
        columns = [pa.array(page.ids, pa.int64()), pa.array(texts, pa.string())]
        if rest:
            extra = pa.ipc.open_stream(rest).read_all().combine_chunks()
            for name in others:
                x = extra.column(name).combine_chunks() if extra.column(name).num_chunks != 1 else extra.column(name).chunk(0)
                columns.append(pa.array([old if new is None else new for old, new in zip(x.to_pylist(), sizes, strict=True)], x.type) if name == chars_col else x)
        return pa.RecordBatch.from_arrays(columns, names=[id_col, text_col, *others])

    return repeated_words(docs, emit, schema, n, id_col, text_col, others).select(docs.columns)
