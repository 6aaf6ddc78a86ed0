"""Resemblance of sets, its estimators from minima and codes, and their variances."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.shared import written

#: Ids in a block of pairs (a power of two), and pairs compared at a time.
PAIR_BLOCK, PAIRS_AT_ONCE = 512, 1 << 14
#: Pairs that are counted at a time, ids in a batch that is dealt to blocks, and sets up to which their sizes go to every task.
PAIRS_COUNTED, DEALT, FEW_SETS = 1 << 22, 1 << 20, 1_000_000


def resemblance(a: Column, b: Column) -> Column:
    both = F.size(F.array_intersect(a, b))
    return both / F.nullif(F.size(a) + F.size(b) - both, F.lit(0))


def resemblance3(a: Column, b: Column, c: Column) -> Column:
    return F.size(F.array_intersect(F.array_intersect(a, b), c)) / F.nullif(F.size(F.array_union(F.array_union(a, b), c)), F.lit(0))


def common_counts(s: DataFrame) -> DataFrame:
    """(id1, id2, a): in how many t both ids of each pair stand, of distinct rows (id, t). The ids of an item go once to each block of ids that it has
    ids in, from the block's first on, not as pairs; a block's pairs are made and counted there, some at a time."""
    shift = PAIR_BLOCK.bit_length() - 1
    listed = s.where("id is not null and t is not null").groupBy("t").agg(F.array_sort(F.collect_list(F.col("id").cast("long"))).alias("ids")).where(F.size("ids") > 1)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (whole.slice(i, 2000) for whole in batches for i in range(0, whole.num_rows, 2000)):
            ids, n = b.column(0).flatten().to_numpy(zero_copy_only=False), b.column(0).value_lengths().to_numpy(zero_copy_only=False)
            row, ends, block = np.repeat(np.arange(len(n)), n), np.cumsum(n), ids >> shift
            first = np.nonzero((np.diff(row, prepend=-1) != 0) | (np.diff(block, prepend=block[:1]) != 0))[0]
            own, size = np.diff(first, append=len(ids)), ends[row[first]] - first
            first, own, size = first[size > 1], own[size > 1], size[size > 1]
            cuts = np.cumsum(size)
            for i, j in zip(*(lambda at: (at[:-1], at[1:]))(np.unique(np.concatenate([[0], np.searchsorted(cuts, np.arange(DEALT, (cuts[-1] if len(cuts) else 0) + DEALT, DEALT)), [len(cuts)]])).clip(0, len(cuts))), strict=True):
                m = size[i:j]
                at = np.repeat(first[i:j], m) + np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(m)]), pa.int32()), pa.array(ids[at]))
                yield pa.RecordBatch.from_arrays([pa.array(block[first[i:j]]), pa.array(own[i:j]), lists], names=["block", "own", "ids"])

    def count(table: pa.Table) -> pa.Table:
        lists = table.column("ids").combine_chunks()
        flat, n, own = lists.flatten().to_numpy(zero_copy_only=False), lists.value_lengths().to_numpy(zero_copy_only=False), table.column("own").to_numpy()
        names, place = np.unique(flat, return_inverse=True)
        start = np.cumsum(n) - n
        # An id of the block meets those after it in its list.
        left = np.repeat(start, own) + np.arange(own.sum()) - np.repeat(np.cumsum(own) - own, own)
        meets = np.repeat(start + n, own) - left - 1
        left, meets = left[meets > 0], meets[meets > 0]
        order = np.argsort(place[left], kind="stable")
        left, meets = left[order], meets[order]
        key, total = place[left], np.cumsum(meets)
        begin = np.nonzero(np.diff(key, prepend=-1))[0]  # where an id begins: its pairs are counted together
        slot = (total[begin] - meets[begin]) // PAIRS_COUNTED
        cuts, out = [*begin[np.nonzero(np.diff(slot, prepend=-1))[0]].tolist(), len(left)], []
        for i, j in zip(cuts[:-1], cuts[1:], strict=True):
            m = meets[i:j]
            x = np.repeat(key[i:j], m)
            y = place[np.repeat(left[i:j] + 1, m) + np.arange(len(x)) - np.repeat(np.cumsum(m) - m, m)]
            pair = np.sort(x * len(names) + y)
            new = np.nonzero(np.diff(pair, prepend=-1))[0]
            out.append((pair[new], np.diff(new, append=len(pair))))
        pair, a = (np.concatenate([np.zeros(0, np.int64), *(o[k] for o in out)]) for k in (0, 1))
        return pa.table({"id1": names[pair // max(1, len(names))], "id2": names[pair % max(1, len(names))], "a": a})

    return listed.select("ids").mapInArrow(deal, "block long, own long, ids array<long>").groupBy("block").applyInArrow(count, "id1 long, id2 long, a long")


def resemblance_pairs(long: DataFrame, id_col: str = "id") -> DataFrame:
    """(id1, id2, f1, f2, a, r) of all pairs that share an item, of distinct rows (id, t). Pairs made: the sum over items of the squared number of sets."""
    s = long.select(F.col(id_col).alias("id"), "t")
    f = written(s.groupBy("id").agg(F.count(F.lit(1)).alias("f")))
    held = F.broadcast(f) if f.count() <= FEW_SETS else f
    sized = common_counts(s).join(held.select(F.col("id").alias("id1"), F.col("f").alias("f1")), "id1").join(held.select(F.col("id").alias("id2"), F.col("f").alias("f2")), "id2")
    return sized.select("id1", "id2", "f1", "f2", "a", (F.col("a") / (F.col("f1") + F.col("f2") - F.col("a"))).alias("r"))


def matches(s1: Column, s2: Column) -> Column:
    """In how many places two signatures or codes agree."""
    return F.aggregate(F.zip_with(s1, s2, lambda x, y: (x == y).cast("int")), F.lit(0), lambda n, x: n + x)


def pair_matches(pairs: DataFrame, signed: DataFrame, bits: tuple[int, ...] = (0,)) -> DataFrame:
    """pairs (id1, id2, ...; a written table) whose two ids have a signature, with matches array<long>: in how many places the signatures agree, whole (0) or in their lowest bits.

    A signature goes once to each pair of blocks of ids that holds pairs, not to each pair; such a pair of blocks has at most PAIR_BLOCK squared pairs and is compared in numpy.
    """
    shift = PAIR_BLOCK.bit_length() - 1
    block = lambda c: F.shiftright(F.col(c).cast("long"), shift)
    dealt = pairs.withColumns({"b1": block("id1"), "b2": block("id2")})
    ends = dealt.select(F.col("b1").alias("c1"), F.col("b2").alias("c2")).distinct().withColumn("b", F.explode(F.array_distinct(F.array("c1", "c2"))))
    held = signed.where("sig is not null").select(F.col("id").cast("long").alias("id"), "sig", block("id").alias("b"))
    names = pairs.columns

    def compare(left: pa.Table, right: pa.Table) -> pa.Table:
        ids = right.column("id").to_numpy()
        order = np.argsort(ids)
        if not len(ids):
            return left.select(names).slice(0, 0).append_column("matches", pa.array([], pa.list_(pa.int64())))
        sig = right.column("sig").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)[order]
        ids = ids[order]
        x, y = (np.searchsorted(ids, left.column(c).to_numpy()) for c in ("id1", "id2"))
        last = len(ids) - 1
        both = (ids[np.minimum(x, last)] == left.column("id1").to_numpy()) & (ids[np.minimum(y, last)] == left.column("id2").to_numpy())
        x, y = x[both], y[both]
        found = np.zeros((len(x), len(bits)), np.int64)
        for i in range(0, len(x), PAIRS_AT_ONCE):
            differ = sig[x[i : i + PAIRS_AT_ONCE]] ^ sig[y[i : i + PAIRS_AT_ONCE]]
            for k, b in enumerate(bits):
                found[i : i + PAIRS_AT_ONCE, k] = ((differ & ((1 << b) - 1) if b else differ) == 0).sum(1)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * len(bits), pa.int32()), pa.array(found.ravel()))
        return left.select(names).filter(pa.array(both)).append_column("matches", lists)

    schema = T.StructType([*pairs.schema.fields, T.StructField("matches", T.ArrayType(T.LongType()))])
    return dealt.groupBy("b1", "b2").cogroup(ends.join(held, "b").groupBy("c1", "c2")).applyInArrow(compare, schema)


def sized_pairs(long: DataFrame) -> DataFrame:
    """resemblance_pairs, written once: ids and counts are kept, the resemblance is taken from them."""
    return written(resemblance_pairs(long).drop("r")).withColumn("r", F.col("a") / (F.col("f1") + F.col("f2") - F.col("a")))


def match_fraction(s1: Column, s2: Column) -> Column:
    return matches(s1, s2) / F.size(s1)


def match_fraction3(s1: Column, s2: Column, s3: Column) -> Column:
    pair = F.zip_with(s1, s2, lambda x, y: F.when(x == y, x))
    return F.aggregate(F.zip_with(pair, s3, lambda x, y: F.coalesce((x == y).cast("int"), F.lit(0))), F.lit(0), lambda n, x: n + x) / F.size(s1)


def var_minwise(r: Column, k: int) -> Column:
    return r * (1 - r) / k


def constants(f1: Column, f2: Column, d, b: int) -> dict[str, Column]:
    """a1, a2, c1, c2 of the match probability c1 + (1 - c2) R. expm1 and log1p keep them exact for tiny sets; a full set has a = 0."""
    width = 1 << b

    def a(f: Column) -> Column:
        r = f / d
        log_rest = F.log1p(-r)
        return F.when(r >= 1, F.lit(0.0)).when(r <= 0, F.lit(1.0 / width)).otherwise(r * F.exp((width - 1) * log_rest) / -F.expm1(width * log_rest))

    a1, a2, total = a(f1), a(f2), f1 + f2
    return {"a1": a1, "a2": a2, "c1": a1 * f2 / total + a2 * f1 / total, "c2": a1 * f1 / total + a2 * f2 / total}


def match_probability(r: Column, f1: Column, f2: Column, d, b: int, mode: str = "general") -> Column:
    if mode == "sparse":
        return F.lit(1.0 / (1 << b)) + (1 - 1.0 / (1 << b)) * r
    c = constants(f1, f2, d, b)
    return c["c1"] + (1 - c["c2"]) * r


def sparse_gap(r: Column, f1: Column, f2: Column, d, b: int) -> Column:
    return F.abs(match_probability(r, f1, f2, d, b) - match_probability(r, f1, f2, d, b, "sparse"))


def estimate_bbit(p_hat: Column, f1: Column, f2: Column, d, b: int, mode: str = "general", clamp: bool = False) -> Column:
    """(p - c1) / (1 - c2); unclamped it is unbiased and may leave 0..1."""
    if mode == "sparse":
        out = (p_hat - 1.0 / (1 << b)) / (1 - 1.0 / (1 << b))
    else:
        c = constants(f1, f2, d, b)
        out = (p_hat - c["c1"]) / (1 - c["c2"])
    return F.least(F.greatest(out, F.lit(0.0)), F.lit(1.0)) if clamp else out


def var_bbit(r: Column, f1: Column, f2: Column, d, b: int, k: int, mode: str = "general") -> Column:
    p = match_probability(r, f1, f2, d, b, mode)
    c2 = F.lit(1.0 / (1 << b)) if mode == "sparse" else constants(f1, f2, d, b)["c2"]
    return p * (1 - p) / (k * (1 - c2) * (1 - c2))
