"""Product features: originals, pairs, and a sampled share of triples."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.digests import LANES, md5_upper_one, upper_bits
from ..functions.sets import let, md5_number

#: Items of a set up to which its triples are laid out at once, and numbers that are put together in 64-bit words.
AT_ONCE, LARGEST = 64, 9_999_999


def feature_products(sets: DataFrame, pairs: bool = True, triple_rate: int = 0, seed: int = 7) -> DataFrame:
    """(id, feature): "t1", "t1|t2" for t1 < t2, and the triples whose hash is 0 modulo triple_rate (the same triples in every row). In-row: nothing is shuffled."""
    def products(items):
        parts = [F.transform(items, lambda t: t.cast("string"))]
        two = F.flatten(F.transform(items, lambda a: F.transform(F.filter(items, lambda b: b > a), lambda b: F.struct(a.alias("a"), b.alias("b")))))
        if pairs:
            parts.append(F.transform(two, lambda x: F.concat_ws("|", x["a"].cast("string"), x["b"].cast("string"))))
        if triple_rate:
            name = lambda x, c: F.concat_ws("|", x["a"].cast("string"), x["b"].cast("string"), c.cast("string"))
            parts.append(F.flatten(F.transform(two, lambda x: F.filter(F.transform(F.filter(items, lambda c: c > x["b"]), lambda c: name(x, c)), lambda g: md5_number(F.concat_ws("|", F.lit(f"{seed}|tri"), g), triple_rate) == 0))))
        return F.concat(*parts)

    return sets.select("id", F.explode(let(F.array_sort("items"), products)).alias("feature"))


@lru_cache(AT_ONCE)
def _all_triples(n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return tuple(np.array(list(combinations(range(n), 3)), np.int32).reshape(-1, 3).T.copy())


def triple_places(n: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """All i < j < k below n, a bounded number at a time."""
    if n <= AT_ONCE:
        if n > 2:
            yield _all_triples(n)
        return
    for i in range(n - 2):
        at = i + 1
        while at < n - 1:
            j = np.arange(at, min(n - 1, at + max(1, 4 * LANES // (n - at))))
            sizes = n - 1 - j
            yield np.full(int(sizes.sum()), i), np.repeat(j, sizes), np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes - j - 1, sizes)
            at = int(j[-1]) + 1


def _decimal(x: np.ndarray, after: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of 7 digits at most as text, followed by a byte, in 64 bits, lowest byte first; and their bytes."""
    rows = [str(v).encode() + after for v in x.tolist()]
    return np.array([int.from_bytes(r, "little") for r in rows], np.uint64), np.array([len(r) for r in rows], np.uint64)


class Triples:
    """Counts the triples of sets whose hash is 0 modulo rate: those of feature_products."""

    def __init__(self, rate: int, seed: int = 7):
        self.rate, self.prefix, self.waiting, self.n = rate, f"{seed}|tri|".encode(), [], 0
        self.count: dict[int, int] = {}

    def add(self, number: int, items: np.ndarray) -> None:
        """items: distinct, ascending."""
        if len(self.prefix) > 7 or (len(items) and (items[0] < 0 or items[-1] > LARGEST)):
            names = [str(x).encode() for x in items.tolist()]
            self.count[number] = sum(md5_upper_one(self.prefix + b"|".join(t)) % self.rate == 0 for t in combinations(names, 3))
            return
        one, eight = np.uint64(1), np.uint64(8)
        middle, wide = _decimal(items, b"|")
        last, _ = _decimal(items, b"\x80")
        start, begin = np.uint64(int.from_bytes(self.prefix, "little")), np.uint64(8 * len(self.prefix))
        for i, j, k in triple_places(len(items)):
            pair = i.astype(np.int64) * len(items) + j
            new = np.concatenate([[True], pair[1:] != pair[:-1]])
            which, a, b = np.cumsum(new) - 1, i[new], j[new]  # triples come pair by pair
            # The first word begins with the prefix; a text of 8 bytes that begins at a bit of one word ends in the next.
            w0, w1 = start | (middle[a] << begin), (middle[a] >> one) >> (np.uint64(63) - begin)
            at = begin + eight * wide[a]
            low, high = middle[b] << (at & np.uint64(63)), (middle[b] >> one) >> (np.uint64(63) - (at & np.uint64(63)))
            first = at < 64
            w0, w1, w2 = w0 | np.where(first, low, 0), w1 | np.where(first, high, low), np.where(first, 0, high)
            at += eight * wide[b]
            turn, here = (at & np.uint64(63))[which], np.where(at < 128, np.uint64((1 << 64) - 1), np.uint64(0))[which]
            c = last[k]
            low, high = c << turn, (c >> one) >> (np.uint64(63) - turn)
            bits = at[which] + eight * (wide[k] - one)
            self.waiting.append((np.full(len(k), number, np.int64), w0[which], w1[which] | (low & here), w2[which] | (high & here) | (low & ~here), high & ~here, bits))
            self.n += len(k)
            if self.n >= LANES:
                self.flush()

    def flush(self) -> None:
        if not self.waiting:
            return
        number, *words, bits = (np.concatenate(c) for c in zip(*self.waiting, strict=True))
        self.waiting, self.n = [], 0
        for at in range(0, len(number), LANES):
            halves = [np.ascontiguousarray(w[at : at + LANES].view("<u4")[i::2]) for w in words for i in (0, 1)]
            value = upper_bits([*halves, *[0] * 6, bits[at : at + LANES].astype(np.uint32), 0])
            hit, n = np.unique(number[at : at + LANES][value % self.rate == 0], return_counts=True)
            for x, y in zip(hit.tolist(), n.tolist(), strict=True):
                self.count[x] = self.count.get(x, 0) + y


def product_sizes(sets: DataFrame, triple_rate: int, seed: int = 7) -> DataFrame:
    """(id, f): how many features feature_products(sets, triple_rate=triple_rate) makes of each set (id, items: distinct numbers) that is not empty. Every triple is hashed; none is written."""
    schema = T.StructType([sets.schema["id"], T.StructField("f", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            triples, sizes = Triples(triple_rate, seed), b.column(1).value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            flat, ends = b.column(1).flatten().to_numpy(zero_copy_only=False), np.cumsum(sizes)
            for i, (n, end) in enumerate(zip(sizes.tolist(), ends.tolist(), strict=True)):
                triples.add(i, np.sort(flat[end - n : end]))
            triples.flush()
            kept = np.array([triples.count.get(i, 0) for i in range(len(sizes))], np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sizes + sizes * (sizes - 1) // 2 + kept)], names=["id", "f"])

    # A set of 40 items has 9,880 triples: small sets are much work, so they are dealt over all cores.
    dealt = sets.where(F.size("items") > 0).select("id", "items").repartition(4 * sets.sparkSession.sparkContext.defaultParallelism)
    return dealt.mapInArrow(run, schema)
