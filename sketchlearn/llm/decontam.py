"""Benchmark decontamination: one Aho-Corasick automaton over the word windows of
the test items, and one scan of each text.

Words are runs of letters, digits and non-ASCII characters, A-Z lower-cased. The
automaton's alphabet is the items' own vocabulary (every other word of a text is
one further symbol that no pattern holds), so a text is mapped to small integers
and walked once. A hit is a run of words; its place in the original text is
found from the word's character offsets, for texts with hits only.

Defined results: a null or empty text has no words and no hits; items with null
id or text, or without words, take no part; the same item given twice counts
once; repeated document rows are each answered; other columns pass unread.
"""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterator
from itertools import repeat

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import alnum_words, few_rows_a_batch, frugal

#: The same words in a text whose capitals still stand.
WORD = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")
#: Windows that one automaton may hold; more items are scanned in further passes of so many.
MOST_WINDOWS = 500_000

RESULT = "doc_id long, n_words long, n_hit long, items array<long>, spans array<struct<start:int,stop:int>>"
_ITEMS = pa.list_(pa.int64())
_SPANS = pa.list_(pa.struct([("start", pa.int32()), ("stop", pa.int32())]))


def windows_of(words: list[bytes], n: int) -> list[tuple[bytes, ...]]:
    """All runs of n words; a shorter item that has words is one window."""
    if not words:
        return []
    return [tuple(words[i : i + n]) for i in range(max(1, len(words) - n + 1))]


def build(items: list[tuple[int, list[bytes]]], n: int) -> tuple[dict[bytes, int], ahocorasick.Automaton]:
    vocabulary: dict[bytes, int] = {}
    owners: dict[tuple[int, ...], set[int]] = {}
    for item, words in items:
        for w in windows_of(words, n):
            owners.setdefault(tuple(vocabulary.setdefault(x, len(vocabulary) + 1) for x in w), set()).add(item)
    found = ahocorasick.Automaton(ahocorasick.STORE_ANY, ahocorasick.KEY_SEQUENCE)
    for key, who in owners.items():
        found.add_word(key, (len(key), tuple(who)))
    if owners:
        found.make_automaton()
    return vocabulary, found


def scan(words: list[bytes], vocabulary: dict[bytes, int], found: ahocorasick.Automaton, shortest: int) -> tuple[list[tuple[int, int]], set[int]]:
    """Word runs [start, stop) that windows cover, merged, and the items they belong to."""
    runs: list[tuple[int, int]] = []
    items: set[int] = set()
    ids = np.fromiter(map(vocabulary.get, words, repeat(0)), np.int32, len(words))
    # A word outside the vocabulary sends the automaton to its root, so the stretches between such words are walked apart, and those shorter than any window not at all.
    edges = np.nonzero(np.diff(np.concatenate([[0], ids != 0, [0]]).astype(np.int8)))[0].reshape(-1, 2)
    for begin, end in edges[edges[:, 1] - edges[:, 0] >= shortest].tolist():
        for last, (length, who) in found.iter(tuple(ids[begin:end].tolist())):
            start, stop = begin + last - length + 1, begin + last + 1
            while runs and start <= runs[-1][1]:  # ends come in order, so only the last runs can touch
                before = runs.pop()
                start, stop = min(start, before[0]), max(stop, before[1])
            runs.append((start, stop))
            items.update(who)
    return runs, items


def _blocks(items: Iterator[tuple[int, list[bytes]]], n: int) -> Iterator[list[tuple[int, list[bytes]]]]:
    """Blocks of items with MOST_WINDOWS windows at most (an item of more is a block by itself); one empty block if there are none."""
    block, held, any_ = [], 0, False
    for item in items:
        more = max(1, len(item[1]) - n + 1)
        if held and held + more > MOST_WINDOWS:
            yield block
            block, held, any_ = [], 0, True
        block.append(item)
        held += more
    if block or not any_:
        yield block


#: The automaton that this Python worker built last, by its block's name: one build a worker, not one a task.
_built: dict[tuple[str, int], tuple] = {}


def sent(spark, block: list[tuple[int, list[bytes]]]):
    """A block's name and its broadcast."""
    return uuid.uuid4().hex, spark.sparkContext.broadcast(block)


def automaton(held, n: int) -> tuple[dict[bytes, int], ahocorasick.Automaton, int, bool]:
    """Vocabulary, automaton, the shortest window and whether there is any, for a block that was sent."""
    key = (held[0], n)
    if key not in _built:
        _built.clear()
        block = held[1].value
        _built[key] = (*build(block, n), min((min(len(w), n) for _, w in block), default=n), bool(block))
    return _built[key]


def bench_items(bench: DataFrame, item_col: str = "item_id", item_text_col: str = "text") -> Iterator[tuple[int, list[bytes]]]:
    """Items with words, read in a stream: the driver holds a block at a time."""
    rows = bench.where(F.col(item_col).isNotNull() & F.col(item_text_col).isNotNull()).select(F.col(item_col).cast("long").alias("i"), F.col(item_text_col).cast("string").alias("t"))
    return ((r.i, w) for r in rows.toLocalIterator() if (w := alnum_words(r.t)))


def without_contaminated(docs: DataFrame, bench: DataFrame, n: int = 10, text_col: str = "text") -> DataFrame:
    """The rows of docs, all their columns, in which no window of an item stands."""
    few_rows_a_batch(docs.sparkSession)
    at, out = docs.columns.index(text_col), docs
    for held in (sent(docs.sparkSession, block) for block in _blocks(bench_items(bench), n)):

        def run(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            vocabulary, found, shortest, some = automaton(held, n)
            for b in batches:
                yield b.filter(pa.array([not (some and (w := alnum_words(t)) and scan(w, vocabulary, found, shortest)[0]) for t in b.column(at).to_pylist()], pa.bool_()))

        out = out.mapInArrow(frugal(run), docs.schema)
    return out


def decontaminate(docs: DataFrame, bench: DataFrame, n: int = 10, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """One row a document: doc_id, n_words, n_hit (words inside any window's occurrence), items (sorted ids), spans (character offsets of the hit runs).

    The items are read to the driver in a stream and broadcast in blocks of
    MOST_WINDOWS windows (some 100 MB as an automaton): however large the
    benchmark, the driver holds one block and a worker one automaton, and the
    texts pass through the blocks one after the other.
    """
    few_rows_a_batch(docs.sparkSession)
    blocks = [sent(docs.sparkSession, block) for block in _blocks(bench_items(bench, item_col, item_text_col), n)]

    def pass_over(held, last: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            vocabulary, found, shortest, some = automaton(held, n)
            for b in batches:
                out_n, out_hit, out_items, out_runs, out_spans = [], [], [], [], []
                before = zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True)
                for text, (had, was) in zip(b.column(1).to_pylist(), before, strict=True):
                    words = alnum_words(text)
                    runs, who = scan(words, vocabulary, found, shortest) if some and words else ([], set())
                    who |= set(had or ())
                    runs = merged(runs, [(x["start"], x["stop"]) for x in was or ()])
                    out_n.append(len(words))
                    out_hit.append(sum(y - x for x, y in runs))
                    out_items.append(sorted(who))
                    out_runs.append([{"start": x, "stop": y} for x, y in runs])
                    out_spans.append(offsets(text, runs) if last else None)
                if last:
                    yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out_n, pa.int64()), pa.array(out_hit, pa.int64()), pa.array(out_items, _ITEMS), pa.array(out_spans, _SPANS)], names=["doc_id", "n_words", "n_hit", "items", "spans"])
                else:
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(out_items, _ITEMS), pa.array(out_runs, _SPANS)], names=["doc_id", "text", "items", "runs"])

        return run

    df = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.lit(None).cast("array<long>").alias("items"), F.lit(None).cast("array<struct<start:int,stop:int>>").alias("runs"))
    for held in blocks[:-1]:
        df = df.mapInArrow(frugal(pass_over(held, False)), df.schema)
    return df.mapInArrow(frugal(pass_over(blocks[-1], True)), RESULT)


def merged(a: list[tuple[int, int]], b: list[tuple[int, int]]) -> list[tuple[int, int]]:
    if not b:
        return a
    out: list[tuple[int, int]] = []
    for x, y in sorted([*a, *b]):
        if out and x <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], y))
        else:
            out.append((x, y))
    return out


def offsets(text: str | None, runs: list[tuple[int, int]]) -> list[dict]:
    """Character offsets of runs of words in the original text."""
    if not runs:
        return []
    at = np.array([m.span() for m in WORD.finditer(text)], np.int64)
    return [{"start": int(at[x, 0]), "stop": int(at[y - 1, 1])} for x, y in runs]
