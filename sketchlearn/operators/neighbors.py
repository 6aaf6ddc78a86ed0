"""Re-use of signatures: copies, near copies, clusters, neighbours and passage overlap."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.shared import written
from .graph import connected_components
from .skew import spread_join

#: Least bits of a set's parity, distinct sets in a block of a bucket, rows of bands in a task.
PARITY, BLOCK, TASK_ROWS = 512, 1024, 100_000
#: Sets of a family that are verified together, items and pairs in a task of that, rows up to which what is needed goes to every task.
FAMILY, TASK_ITEMS, TASK_PAIRS, FEW = 512, 4_000_000, 1_000_000, 100_000
#: Buckets of items whose sets are counted, slices of these in a shuffle, first items in a task of exact_pairs, tasks at least, and pairs that one makes at a time.
BUCKETS, SLICES, TASK_HEADS, LEAST_GROUPS, MEETINGS = 1 << 23, 64, 4_000_000, 16, 2_000_000
_STEP = np.uint64(0x9E3779B97F4A7C15)


def exact_groups(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, group_id, copies): equal texts; one aggregate by md5, so a frequent text is summed before the shuffle and joined back without one."""
    hashed = written(df.select(F.col(id_col).alias("id"), F.md5(F.coalesce(F.col(text_col), F.lit(""))).alias("h")))
    groups = hashed.groupBy("h").agg(F.min("id").alias("group_id"), F.count(F.lit(1)).alias("copies"))
    return spread_join(hashed, groups, "h", "inner").select("id", "group_id", "copies")


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def parity_bits(mixed: np.ndarray) -> bytes:
    """A parity bit for each bucket of the items, whose mixed numbers are given: PARITY buckets, or the power of two above the number of items, so that
    bits of unlike sets differ however large these are. Folded by halves, bits are those of half as many buckets."""
    width = PARITY << max(0, len(mixed).bit_length() - (PARITY - 1).bit_length())
    return np.packbits(np.bincount((mixed % np.uint64(width)).astype(np.int64), minlength=width).astype(np.uint8) & 1).tobytes()


def folded(bits: list[bytes], words: int) -> np.ndarray:
    """Parity bits folded to so many words of 64 bits, a row a set."""
    out, size = np.zeros((len(bits), words), np.uint64), np.array([len(b) // 8 for b in bits], np.int64)
    for w in np.unique(size).tolist():
        at = np.nonzero(size == w)[0]
        out[at] = np.bitwise_xor.reduce(np.frombuffer(b"".join(bits[i] for i in at.tolist()), np.uint64).reshape(len(at), w // words, words), axis=1)
    return out


def described(signed: DataFrame, bands: int, rows: int) -> DataFrame:
    """(id, fp, f, parity, bands, sig): a 128-bit fingerprint of the set, its size, its parity_bits, and the bands' minima as bytes, 8 * rows a band."""
    names = ["id", "fp", "f", "parity", "bands", "sig"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp, f, parity, keys = [], [], [], []
            for items, sig in zip(b.column(1), b.column(2), strict=True):
                x = np.unique(items.values.to_numpy(zero_copy_only=False)).view(np.uint64)
                m = _mixed(x + _STEP)
                fp.append(np.array([m.sum(dtype=np.uint64), _mixed(m ^ _STEP).sum(dtype=np.uint64)]).tobytes())
                f.append(len(x))
                parity.append(parity_bits(m))
                keys.append(sig.values.to_numpy(zero_copy_only=False)[: bands * rows].tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), pa.array(fp, pa.binary()), pa.array(f, pa.int64()), pa.array(parity, pa.binary()), pa.array(keys, pa.binary()), b.column(2)], names=names)

    return signed.where("sig is not null").select("id", "items", "sig").mapInArrow(run, "id long, fp binary, f long, parity binary, bands binary, sig array<long>")


def alike(f1: np.ndarray, p1: np.ndarray, f2: np.ndarray, p2: np.ndarray, tau: float) -> tuple[np.ndarray, np.ndarray]:
    """Places of all pairs whose resemblance can reach tau. Each item that only one of two sets has turns one parity bit, so that
    the bits that differ are at most the items that do, and these are at most (f1 + f2)(1 - tau)/(1 + tau) at resemblance tau: no pair of tau is lost."""
    differ = np.zeros((len(f1), len(f2)), np.uint16)
    for w in range(p1.shape[1]):
        differ += np.bitwise_count(p1[:, w, None] ^ p2[None, :, w])
    low, high = np.minimum(f1[:, None], f2), np.maximum(f1[:, None], f2)
    return np.nonzero((differ <= (low + high) * ((1 - tau) / (1 + tau)) + 1e-6) & (low >= tau * high - 1e-6))


def still_alike(x: np.ndarray, y: np.ndarray, f: np.ndarray, bits: list[bytes], size: np.ndarray, tau: float, known: int = PARITY // 64) -> np.ndarray:
    """Which of the pairs of sets at places x and y can reach tau by all bits that both have (see alike); size: 64-bit words of the bits. Pairs that share no more than the known words are kept."""
    out, words = np.ones(len(x), bool), np.minimum(size[x], size[y])
    for w in np.unique(words[words > known]).tolist():
        pairs = np.nonzero(words == w)[0]
        who = np.unique(np.concatenate([x[pairs], y[pairs]]))
        table = folded([bits[i] for i in who.tolist()], w)
        for some in (pairs[i : i + (1 << 22) // w] for i in range(0, len(pairs), (1 << 22) // w)):
            differ = np.bitwise_count(table[np.searchsorted(who, x[some])] ^ table[np.searchsorted(who, y[some])]).sum(1, dtype=np.int64)
            out[some] = differ <= (f[x[some]] + f[y[some]]) * ((1 - tau) / (1 + tau)) + 1e-6
    return out


def band_candidates(reps: DataFrame, bands: int, rows: int, tau: float) -> DataFrame:
    """(id1, id2): all pairs of distinct sets that share a band and can reach tau, each once. A bucket of more than BLOCK sets is cut into blocks, each pair of blocks a task."""
    width = 8 * rows
    sliced = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda i: F.struct(i.alias("band"), F.substring("bands", i * width + 1, F.lit(width)).alias("h")))
    long = reps.select("id", "f", "parity", "bands", F.explode(sliced).alias("x")).select("id", "f", "parity", "bands", "x.band", "x.h")
    sizes = long.groupBy("band", "h").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    large = sizes.where(F.col("n") > BLOCK).select("band", "h", F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks"))
    dealt = long.join(F.broadcast(large), ["band", "h"], "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    dealt = dealt.withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")})
    tasks = max(16, -(-reps.count() * bands // TASK_ROWS))

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["band", "h", "i", "j"], ignore_index=True)
        ids, f, own, band = (pdf[c].to_numpy() for c in ("id", "f", "own", "band"))
        bits = pdf["parity"].tolist()
        parity, words = folded(bits, PARITY // 64), np.array([len(b) // 8 for b in bits], np.int64)
        minima = np.frombuffer(b"".join(pdf["bands"]), np.int64).reshape(len(pdf), bands, rows)
        i, j, h = pdf["i"].to_numpy(), pdf["j"].to_numpy(), pdf["h"].to_numpy()
        new = (band[1:] != band[:-1]) | (h[1:] != h[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])
        cuts = np.concatenate([[0], np.nonzero(new)[0] + 1, [len(pdf)]])
        left, right = [], []
        for begin, end in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            if end - begin < 2:
                continue
            at = np.arange(begin, end)
            a, b = (at, at) if i[begin] == j[begin] else (at[own[at] == i[begin]], at[own[at] == j[begin]])
            x, y = alike(f[a], parity[a], f[b], parity[b], tau)
            x, y = a[x], b[y]
            once = ids[x] < ids[y] if a is b else np.ones(len(x), bool)
            x, y = x[once], y[once]
            # The first band that both share makes the pair, no other.
            first = (minima[x] == minima[y]).all(2).argmax(1) == band[begin]
            x, y = x[first], y[first]
            able = still_alike(x, y, f, bits, words, tau)
            left.append(ids[x[able]])
            right.append(ids[y[able]])
        l, r = (np.concatenate([np.zeros(0, np.int64), *side]) for side in (left, right))
        return pd.DataFrame({"id1": np.minimum(l, r), "id2": np.maximum(l, r)})

    grouped = dealt.select("id", "f", "parity", "bands", "band", "h", "i", "j", "own").groupBy(F.pmod(F.xxhash64("band", "h", "i", "j"), F.lit(tasks)))
    return grouped.applyInPandas(solve, "id1 long, id2 long")


def verified(pairs: DataFrame, reps: DataFrame, items_of: Callable[[DataFrame], DataFrame], tau: float) -> DataFrame:
    """(id1, id2, matches, r) of the pairs (a written table) that reach tau. Pairs meet by family, the component of the pairs: a set's items go once to
    its family, not to each pair; a family of more than FAMILY sets is cut into blocks, and a set goes to each pair of blocks in which it has a pair."""
    family = connected_components(pairs, "id1", "id2")
    large = family.groupBy("root").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > FAMILY).select("root", F.ceil(F.col("n") / FAMILY).cast("int").alias("blocks"))
    nodes = written(family.join(F.broadcast(large), "root", "left").withColumn("blocks", F.coalesce("blocks", F.lit(1))))
    block = lambda c: F.pmod(F.xxhash64(c), F.col("blocks")).cast("int")
    sides = {"i": F.least("own", "other"), "j": F.greatest("own", "other")}
    placed = written(pairs.join(nodes.withColumnRenamed("node", "id1"), "id1").withColumns({"own": block("id1"), "other": block("id2")}).select("id1", "id2", "root", *(c.alias(n) for n, c in sides.items())))
    # A set goes to those pairs of blocks only in which it has a pair: a family that unlike sets hold together has few of these for each set.
    sent = placed.select(F.explode(F.array("id1", "id2")).alias("id"), "root", "i", "j").distinct()
    volume = sent.join(reps.select("id", "f"), "id").agg(F.sum("f")).first()[0] or 0
    tasks = max(16, -(-volume // TASK_ITEMS), -(-pairs.count() // TASK_PAIRS))
    task = F.pmod(F.xxhash64("root", "i", "j"), F.lit(tasks)).cast("int")
    met = placed.select("id1", "id2", task.alias("task"))
    dealt = sent.groupBy("id").agg(F.collect_set(task).alias("tasks"))
    needed = written(dealt.join(reps.select("id", "sig"), "id"))
    needed = F.broadcast(needed) if needed.count() <= FEW else needed
    held = items_of(needed).select("id", "items", "sig", F.explode("tasks").alias("at"))

    def compare(left: pa.Table, right: pa.Table) -> pa.Table:
        ids, first = np.unique(right.column("id").to_numpy(), return_index=True)
        lists = right.column("items").combine_chunks()
        names, flat = np.unique(lists.flatten().to_numpy(zero_copy_only=False), return_inverse=True)
        at = np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64)
        sets = [np.unique(flat[at[i] : at[i + 1]]) for i in first.tolist()]
        sig = right.column("sig").combine_chunks().take(pa.array(first))
        sig = sig.flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1) if len(ids) else np.zeros((0, 1), np.int64)
        a, b = left.column("id1").to_numpy(), left.column("id2").to_numpy()
        order = np.argsort(a, kind="stable")
        a, b = a[order], b[order]
        x, y = np.searchsorted(ids, a), np.searchsorted(ids, b)
        both, marked = np.zeros(len(a), np.int64), np.zeros(len(names), bool)
        cuts = np.concatenate([[0], np.nonzero(np.diff(x))[0] + 1, [len(x)]]) if len(x) else np.zeros(1, np.int64)
        for i, j in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            marked[sets[x[i]]] = True
            for k in range(i, j):
                both[k] = np.count_nonzero(marked[sets[y[k]]])
            marked[sets[x[i]]] = False
        sizes = np.array([len(z) for z in sets], np.int64)
        r = both / np.maximum(sizes[x] + sizes[y] - both, 1) if len(x) else np.zeros(0)
        good = np.nonzero(r >= tau)[0]
        same = np.concatenate([np.zeros(0, np.int64), *((sig[x[p]] == sig[y[p]]).sum(1) for p in (good[i : i + 10_000] for i in range(0, len(good), 10_000)))])
        return pa.table({"id1": a[good], "id2": b[good], "matches": same.astype(np.int64), "r": r[good]})

    return met.groupBy("task").cogroup(held.groupBy("at")).applyInArrow(compare, "id1 long, id2 long, matches long, r double")


def distinct_links(signed: DataFrame, bands: int, rows: int, tau: float, items_of: Callable[[DataFrame], DataFrame] | None = None) -> tuple[DataFrame, DataFrame]:
    """(id1, id2, matches, r) of all pairs of distinct sets that share a band and reach tau, each set by the smallest id that has it; and (id, rep, k), the smallest id of each id's set and the signature's length.

    items_of: rows (id, ...) with their items, made anew for the few sets that are in a pair, so that no items are stored.
    """
    every = written(described(signed, bands, rows))
    reps = written(every.groupBy("fp").agg(F.min(F.struct("id", "f", "parity", "bands", "sig")).alias("x")).select("fp", "x.*"))
    member = every.select("id", "fp", F.size("sig").alias("k")).join(reps.select("fp", F.col("id").alias("rep")), "fp").select("id", "rep", "k").distinct()
    pairs = written(band_candidates(reps, bands, rows, tau))
    found = verified(pairs, reps, items_of or (lambda needed: signed.select("id", "items").join(needed, "id")), tau)
    return found, member


def near_classes(signed: DataFrame, bands: int, rows: int, tau: float, items_of: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """(id1, id2, matches, r): the pairs of near_pairs between the smallest ids of distinct sets, and each copy beside the smallest id of its set."""
    found, member = distinct_links(signed, bands, rows, tau, items_of)
    return found.unionByName(member.where("id <> rep").select(F.col("rep").alias("id1"), F.col("id").alias("id2"), F.col("k").cast("long").alias("matches"), F.lit(1.0).alias("r")))


def near_pairs(signed: DataFrame, bands: int, rows: int, tau: float) -> DataFrame:
    """(id1, id2, matches, r): all pairs that share a band and whose exact resemblance reaches tau. Equal sets are compared once and written out as pairs at the end, so that the rows made are those of the result."""
    found, member = distinct_links(signed, bands, rows, tau)
    member = written(member)
    side = lambda n: member.select(F.col("rep").alias(f"r{n}"), F.col("id").alias(f"m{n}"))
    ends = lambda df, *more: df.select(F.least("m1", "m2").alias("id1"), F.greatest("m1", "m2").alias("id2"), *more)
    across = ends(found.withColumnsRenamed({"id1": "r1", "id2": "r2"}).join(side(1), "r1").join(side(2), "r2"), "matches", "r")
    copies = member.select(F.col("rep").alias("r1"), F.col("id").alias("m1"), "k").join(side(2), F.col("r1") == F.col("r2")).where("m1 < m2")
    return across.unionByName(ends(copies, F.col("k").cast("long").alias("matches"), F.lit(1.0).alias("r")))


def _buckets(items: np.ndarray) -> np.ndarray:
    return (_mixed(items.view(np.uint64) + _STEP) % np.uint64(BUCKETS)).astype(np.int64)


def bucket_counts(sets: DataFrame) -> np.ndarray:
    """In how many sets (id, items) the items of each of BUCKETS buckets stand, all sets counted (65,535 and more are alike); 16 MB, whatever the data."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(BUCKETS, np.uint32)
        for b in batches:
            n += np.bincount(_buckets(b.column(0).flatten().to_numpy(zero_copy_only=False).astype(np.int64)), minlength=BUCKETS).astype(np.uint32)
        z = zstandard.ZstdCompressor(level=1)
        if n.any():
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(SLICES, dtype=np.int32)), pa.array([z.compress(x.tobytes()) for x in np.split(np.minimum(n, 65535).astype(np.uint16), SLICES)], pa.binary())], names=["slice", "n"])

    def add(pdf: pd.DataFrame) -> pd.DataFrame:
        n, z = np.zeros(BUCKETS // SLICES, np.int64), zstandard.ZstdDecompressor()
        for x in pdf["n"]:
            n += np.frombuffer(z.decompress(x), np.uint16)
        return pd.DataFrame({"slice": pdf["slice"].iloc[:1], "n": [np.minimum(n, 65535).astype(np.uint16).tobytes()]})

    rows = sets.select("items").mapInArrow(count, "slice int, n binary").groupBy("slice").applyInPandas(add, "slice int, n binary").orderBy("slice").collect()
    return np.frombuffer(b"".join(r.n for r in rows), np.uint16) if rows else np.zeros(BUCKETS, np.uint16)


def least_common(f1: np.ndarray, f2: np.ndarray, tau: float) -> np.ndarray:
    """How many items the heads (see exact_pairs) of two sets of resemblance tau have in common at least: all their common items but those behind
    the head that ends first, which are no more than its set has there, at most ceil(tau f) - 1 of the larger set."""
    both = np.ceil((f1 + f2) * (tau / (1 + tau)) - 1e-6)
    return np.maximum(both - np.ceil(tau * np.maximum(f1, f2) - 1e-9) + 1, 1)


def meeting(ids: np.ndarray, f: np.ndarray, heads: list[bytes], tau: float, groups: int) -> tuple[np.ndarray, np.ndarray]:
    """(smaller, larger id) of the sets whose heads have so many hashed items in common, in this one of so many groups of items, as pairs of resemblance
    tau have in one group or another. All meetings of a set with those after it by size are counted together, some MEETINGS at a time."""
    order = np.lexsort((ids, f))
    ids, f = ids[order], f[order]
    parts = [np.frombuffer(heads[i], np.uint32) for i in order.tolist()]
    n, own = len(ids), np.repeat(np.arange(len(ids)), [len(x) for x in parts])
    key = np.sort(np.concatenate([np.zeros(0, np.int64), *parts]).astype(np.int64) * n + own)
    t, own = np.divmod(key, max(n, 1))
    # An item's sets lie by size: each meets those after it whose size is not above f / tau.
    upto = np.searchsorted(key, t * n + np.searchsorted(f, (f + 1e-6) / tau, "right")[own])
    meets = np.maximum(upto - np.arange(len(key)) - 1, 0)
    held = np.nonzero(meets)[0]
    held = held[np.argsort(own[held], kind="stable")]
    total = np.cumsum(meets[held])
    first = np.concatenate([[0], np.nonzero(np.diff(own[held]))[0] + 1]) if len(held) else np.zeros(0, np.int64)  # where a set begins
    slot = (total[first] - meets[held][first]) // MEETINGS
    cuts = np.concatenate([first[np.nonzero(np.diff(slot, prepend=-1))[0]], [len(held)]]) if len(held) else [0]
    left, right = [ids[:0]], [ids[:0]]
    for i, j in zip(cuts[:-1], cuts[1:], strict=True):
        e = held[i:j]
        m = meets[e]
        x = np.repeat(own[e], m)
        y = own[np.repeat(e + 1, m) + np.arange(len(x)) - np.repeat(np.cumsum(m) - m, m)]
        pair = np.sort(x * n + y)
        begin = np.nonzero(np.diff(pair, prepend=-1))[0]
        count = np.diff(begin, append=len(pair))
        x, y = np.divmod(pair[begin], n)
        good = (x != y) & (count >= np.ceil(least_common(f[x], f[y], tau) / groups))
        left.append(ids[x[good]])
        right.append(ids[y[good]])
    l, r = np.concatenate(left), np.concatenate(right)
    return np.minimum(l, r), np.maximum(l, r)


def exact_pairs(reps: DataFrame, tau: float) -> DataFrame:
    """(id1, id2, r): all pairs of resemblance tau among sets (id, items; a written table), as the standard that banding is measured by. Whatever
    the order of items, of two such sets the first f - ceil(tau f) + 1 of each, their heads, have one in common, and of sets of like size many
    more (least_common): items of rare buckets go first, so that few unlike sets meet. Only heads are shuffled, as 32-bit hashes, by groups of items;
    a pair leaves a group if it meets there as often as one of tau must in some group. Sizes and parity bits rule out pairs, then items are compared."""
    spark = reps.sparkSession
    often = spark.sparkContext.broadcast(bucket_counts(reps))
    held = reps.select("id", F.col("items").cast("array<bigint>").alias("items"))

    def fact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sets = [np.unique(items.values.to_numpy(zero_copy_only=False)) for items in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(x) for x in sets], pa.int64()), pa.array([parity_bits(_mixed(x.view(np.uint64) + _STEP)) for x in sets], pa.binary())], names=["id", "f", "parity"])

    facts = written(held.mapInArrow(fact, "id long, f long, parity binary"))
    groups = max(LEAST_GROUPS, -(-int((1 - tau) * (facts.agg(F.sum("f")).first()[0] or 0)) // TASK_HEADS))

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (whole.slice(i, 500) for whole in batches for i in range(0, whole.num_rows, 500)):
            rows = []
            for number, items in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                x = np.unique(items.values.to_numpy(zero_copy_only=False))
                k = len(x) - math.ceil(tau * len(x) - 1e-9) + 1 if len(x) else 0
                m = _mixed(x[np.lexsort((x, often.value[_buckets(x)]))[:k]].view(np.uint64) + _STEP)
                group = (m % np.uint64(groups)).astype(np.int64)
                by = np.argsort(group, kind="stable")
                names, begin = np.unique(group[by], return_index=True)
                rows += [(number, len(x), g, part.tobytes()) for g, part in zip(names.tolist(), np.split((m[by] >> np.uint64(32)).astype(np.uint32), begin[1:]), strict=False)]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [()] * 4, (pa.int64(), pa.int64(), pa.int32(), pa.binary()), strict=True)], names=["id", "f", "part", "head"])

    def meet(table: pa.Table) -> pa.Table:
        l, r = meeting(table.column("id").to_numpy(), table.column("f").to_numpy(), table.column("head").to_pylist(), tau, groups)
        return pa.table({"id1": l, "id2": r})

    heads = held.mapInArrow(first, "id long, f long, part int, head binary")
    pairs = written(heads.groupBy("part").applyInArrow(meet, "id1 long, id2 long").distinct())
    side = lambda n: facts.select(F.col("id").alias(f"id{n}"), F.col("f").alias(f"f{n}"), F.col("parity").alias(f"p{n}"))

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            bits, at = [*b.column("p1").to_pylist(), *b.column("p2").to_pylist()], np.arange(b.num_rows)
            f = np.concatenate([b.column("f1").to_numpy(), b.column("f2").to_numpy()])
            can = still_alike(at, b.num_rows + at, f, bits, np.array([len(x) // 8 for x in bits], np.int64), tau, 0)
            yield b.select(["id1", "id2"]).filter(pa.array(can))

    able = written(pairs.join(side(1), "id1").join(side(2), "id2").select("id1", "id2", "f1", "f2", "p1", "p2").mapInArrow(keep, "id1 long, id2 long"))
    return verified(able, facts.select("id", "f", F.array("f").alias("sig")), lambda needed: held.join(needed, "id"), tau).select("id1", "id2", "r")


def near_links(signed: DataFrame, bands: int, rows: int, tau: float, items_of: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """(id1, id2): links with the components of near_pairs; copies are tied to the smallest id of their set, not to one another."""
    found, member = distinct_links(signed, bands, rows, tau, items_of)
    return found.select("id1", "id2").unionByName(member.where("id <> rep").select(F.col("rep").alias("id1"), F.col("id").alias("id2")))


def clusters(pairs: DataFrame) -> DataFrame:
    """(id, cluster_id): components of the pairs."""
    return connected_components(pairs, "id1", "id2").select(F.col("node").alias("id"), F.col("root").alias("cluster_id"))


def top_k(signed: DataFrame, queries: DataFrame, m: int, k: int) -> DataFrame:
    """(query, id, matches, rank): by agreeing minima, found through an equi-join on (j, z); ties to the smaller id. The order is that of the estimated resemblance, which is not computed."""
    long = signed.where("sig is not null").select("id", F.posexplode("sig").alias("j", "z"))
    asked = queries.where("sig is not null").select(F.col("id").alias("query"), F.posexplode("sig").alias("j", "z"))
    hits = asked.join(long, ["j", "z"]).where("query <> id").groupBy("query", "id").agg(F.count(F.lit(1)).alias("matches"))
    w = Window.partitionBy("query").orderBy(F.desc("matches"), "id")
    return hits.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= m)


def containment(passages: DataFrame, docs: DataFrame, least: float) -> DataFrame:
    """(item_id, doc_id, a, f, share): passages of whose items at least a share stands in a document. Equi-join on items; the passages are the small side."""
    p = passages.select(F.col("id").alias("item_id"), F.explode("items").alias("t"))
    f = passages.select(F.col("id").alias("item_id"), F.size("items").cast("long").alias("f"))
    d = docs.select(F.col("id").alias("doc_id"), F.explode("items").alias("t"))
    hit = p.join(d, "t").groupBy("item_id", "doc_id").agg(F.count(F.lit(1)).alias("a"))
    return hit.join(f, "item_id").withColumn("share", F.col("a") / F.col("f")).where(F.col("share") >= least)


def library_join(vectors: DataFrame, tau: float, tables: int = 5):
    """The library's own MinHash join, as a baseline (rows only)."""
    from pyspark.ml.feature import MinHashLSH

    model = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=tables, seed=7).fit(vectors)
    return model.approxSimilarityJoin(vectors, vectors, 1 - tau, "distance").where("datasetA.id < datasetB.id")
