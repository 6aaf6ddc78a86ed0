"""Random projections, plain and signed bucket sketches, their estimators and variances, and buckets over expanded codes.

Entries are made from md5 of seed, coordinate and column wherever they are
needed: nothing of the size of the matrix is stored or shipped. Each sketch has
two forms with the same values: over long rows (id, i, v), for vectors that are
spread over rows, with partial sums before one shuffle; and over arrays in a
row, map-only, where a task remembers the entries of the coordinates it met.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.sets import md5_number

UNIT = 1 << 40


def uniform(seed: int, role: str, *parts: Column) -> Column:
    """In (0, 1), from md5."""
    return (md5_number(F.concat_ws("|", F.lit(f"{seed}|{role}"), *(p.cast("string") for p in parts)), UNIT) + 0.5) / UNIT


def entry(kind: str, s: float, seed: int, *parts: Column) -> Column:
    """E r = 0, E r^2 = 1, E r^3 = 0, E r^4 = s: "normal" (s = 3), "sign" (s = 1), "sparse" (+-root of s with probability 1 / 2s each)."""
    u = uniform(seed, "r", *parts)
    if kind == "sign":
        return F.when(u < 0.5, F.lit(-1.0)).otherwise(F.lit(1.0))
    if kind == "sparse":
        edge, root = 1.0 / (2 * s), math.sqrt(s)
        return F.when(u < edge, F.lit(-root)).when(u >= 1 - edge, F.lit(root)).otherwise(F.lit(0.0))
    return F.sqrt(-2 * F.log(u)) * F.cos(2 * math.pi * uniform(seed, "q", *parts))


def project(long: DataFrame, k: int, kind: str = "sign", s: float = 1.0, seed: int = 7) -> DataFrame:
    """(id, j, v): v_j = sum of u_i r_ij. Partial sums before the one shuffle of n k values."""
    spread = long.select("id", "i", "v", F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("j"))
    return spread.groupBy("id", "j").agg(F.sum(F.col("v") * entry(kind, s, seed, F.col("i"), F.col("j"))).alias("v"))


def bucket_of(i: Column, k: int, seed: int = 7) -> Column:
    return md5_number(F.concat_ws("|", F.lit(f"{seed}|h"), i.cast("string")), k).cast("int")


def bucket_sum(long: DataFrame, k: int, signed: bool = True, s: float = 1.0, seed: int = 7) -> DataFrame:
    """(id, bucket, val): sums of the coordinates of each bucket, with the sign of each coordinate if signed."""
    value = F.col("v") * entry("sign" if s == 1.0 else "sparse", s, seed, F.col("i")) if signed else F.col("v")
    return long.groupBy("id", bucket_of(F.col("i"), k, seed).alias("bucket")).agg(F.sum(value).alias("val"))


def stack(active: DataFrame, m: int, seed: int = 7) -> DataFrame:
    """(id, bucket, val): signed buckets over the k ones of expanded codes, to shrink 2^b k places to m."""
    return bucket_sum(active.select("id", F.explode("active").alias("i"), F.lit(1.0).alias("v")), m, True, 1.0, seed)


# ---------------------------------------------------------------- vectors in a row

#: Coordinates that are worked on at a time, and slots of a task's memory of entries.
AT_ONCE, SLOTS = 1 << 18, 1 << 20


def md5_array(label: str, coordinates: np.ndarray, tail: str = "") -> np.ndarray:
    """The first 13 hex digits of md5("label|i tail") for each coordinate i, as numbers of 52 bits."""
    head, end, md5 = f"{label}|".encode(), tail.encode(), hashlib.md5
    digests = b"".join([md5(b"%b%d%b" % (head, i, end)).digest() for i in coordinates.tolist()])
    return (np.frombuffer(digests, ">u8")[::2] >> np.uint64(12)).astype(np.int64)


def entry_array(kind: str, s: float, seed: int, coordinates: np.ndarray, tail: str = "") -> np.ndarray:
    """entry() in numpy; tail names a column as "|j"."""
    u = (md5_array(f"{seed}|r", coordinates, tail) % UNIT + 0.5) / UNIT
    if kind == "sign":
        return np.where(u < 0.5, -1.0, 1.0)
    if kind == "sparse":
        edge, root = 1.0 / (2 * s), math.sqrt(s)
        return np.where(u < edge, -root, np.where(u >= 1 - edge, root, 0.0))
    q = (md5_array(f"{seed}|q", coordinates, tail) % UNIT + 0.5) / UNIT
    return np.sqrt(-2 * np.log(u)) * np.cos(2 * math.pi * q)


def bucket_array(coordinates: np.ndarray, k: int, seed: int = 7) -> np.ndarray:
    return md5_array(f"{seed}|h", coordinates) % k


class Remembered:
    """What make() gives for coordinates: a row of numbers each. A table of fixed size holds those met last in each slot."""

    def __init__(self, make, width: int, slots: int = SLOTS):
        self.make, self.slots = make, min(slots, max(1024, (1 << 23) // width))
        self.keys = np.full(self.slots, -1, np.int64)
        self.rows = np.zeros((self.slots, width))

    def __call__(self, coordinates: np.ndarray) -> np.ndarray:
        """coordinates: distinct and not negative."""
        slot = (coordinates * np.int64(0x9E3779B1) >> 7) % self.slots
        new = np.nonzero(self.keys[slot] != coordinates)[0]
        out = self.rows[slot]
        if len(new):
            made = self.make(coordinates[new])
            out[new] = made
            # Of two new ones in a slot only the last is kept.
            kept = np.unique(slot[new][::-1], return_index=True)[1]
            kept = len(new) - 1 - kept
            self.keys[slot[new[kept]]], self.rows[slot[new[kept]]] = coordinates[new[kept]], made[kept]
        return out


def _pieces(idx: pa.Array, val: pa.Array | None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(row, coordinate, value) of a batch of arrays, about AT_ONCE at a time, a longer row by itself."""
    sizes = np.nan_to_num(idx.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64)
    flat = idx.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    value = np.ones(len(flat)) if val is None else val.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    row = np.repeat(np.arange(len(sizes)), sizes)
    ends = np.cumsum(sizes)
    at = 0
    while at < len(flat):
        last = int(np.searchsorted(ends, at + AT_ONCE, "right"))  # rows that end within reach
        to = int(ends[last - 1]) if last and ends[last - 1] > at else int(ends[np.searchsorted(ends, at, "right")])
        yield row[at:to], flat[at:to], value[at:to]
        at = to


def bucket_sketch(df: DataFrame, idx: str, k: int, val: str | None = None, signed: bool = True, s: float = 1.0, seed: int = 7) -> DataFrame:
    """bucket_sum() of the vectors in a row (id, idx array<bigint>, val array<double> or all ones): (id, bucket, val), without a shuffle."""

    def make(i: np.ndarray) -> np.ndarray:
        sign = entry_array("sign" if s == 1.0 else "sparse", s, seed, i) if signed else np.ones(len(i))
        return np.stack([bucket_array(i, k, seed).astype(np.float64), sign], axis=1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        entries = Remembered(make, 2)
        for b in batches:
            for row, i, v in _pieces(b.column(1), b.column(2) if val else None):
                names, place = np.unique(i, return_inverse=True)
                e = entries(names)[place]
                key, where = np.unique(row * k + e[:, 0].astype(np.int64), return_inverse=True)
                total = np.bincount(where, v * e[:, 1], len(key))
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(key // k)), pa.array((key % k).astype(np.int32)), pa.array(total)], names=["id", "bucket", "val"])

    columns = [F.col("id"), F.col(idx).cast("array<bigint>").alias("idx")] + ([F.col(val).cast("array<double>").alias("val")] if val else [])
    return df.select(*columns).mapInArrow(run, T.StructType([df.schema["id"], T.StructField("bucket", T.IntegerType()), T.StructField("val", T.DoubleType())]))


def projection_sketch(df: DataFrame, idx: str, val: str, k: int, kind: str = "sign", s: float = 1.0, seed: int = 7) -> DataFrame:
    """project() of the vectors in a row, as (id, v array<double>) of length k; nothing is shuffled."""

    def make(i: np.ndarray) -> np.ndarray:
        return np.stack([entry_array(kind, s, seed, i, f"|{j}") for j in range(k)], axis=1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        entries = Remembered(make, k)
        for b in batches:
            out = np.zeros((b.num_rows, k))
            for row, i, v in _pieces(b.column(1), b.column(2)):
                names, place = np.unique(i, return_inverse=True)
                r = entries(names)
                starts = np.nonzero(np.concatenate([[True], row[1:] != row[:-1]]))[0]
                for lo in range(0, k, 16):  # a tile of columns at a time
                    out[row[starts], lo : lo + 16] += np.add.reduceat(v[:, None] * r[place, lo : lo + 16], starts)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * k), pa.array(out.ravel()))], names=["id", "v"])

    rows = df.select("id", F.col(idx).cast("array<bigint>").alias("idx"), F.col(val).cast("array<double>").alias("val"))
    return rows.mapInArrow(run, T.StructType([df.schema["id"], T.StructField("v", T.ArrayType(T.DoubleType()))]))


def seeded_estimates(pairs: DataFrame, v1: str, v2: str, dims: int, seeds: list[int], methods: list[tuple]) -> DataFrame:
    """(id1, id2, method, s, k, mean, variance) of the inner product's estimates over several seeds. methods: (name, s, k), name rp, signed or plain. The entries of all seeds for dims coordinates are made once a task."""
    coordinates = np.arange(dims, dtype=np.int64)

    def matrix(name: str, s: float, k: int, seed: int) -> np.ndarray:
        kind = "sign" if s == 1.0 else "sparse"
        if name == "rp":
            return np.stack([entry_array(kind, s, seed, coordinates, f"|{j}") for j in range(k)], axis=1) / math.sqrt(k)
        out = np.zeros((dims, k))
        out[coordinates, bucket_array(coordinates, k, seed)] = entry_array(kind, s, seed, coordinates) if name == "signed" else 1.0
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = [(m, [matrix(*m, seed) for seed in seeds]) for m in methods]
        for b in batches:
            x, y = (b.column(i).flatten().to_numpy(zero_copy_only=False).reshape(-1, dims) for i in (2, 3))
            for (name, s, k), matrices in made:
                est = np.stack([((x @ r) * (y @ r)).sum(1) for r in matrices])
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([name] * len(x)), pa.array(np.full(len(x), s)), pa.array(np.full(len(x), k, np.int32)), pa.array(est.mean(0)), pa.array(est.var(0, ddof=1))], names=["id1", "id2", "method", "s", "k", "mean", "variance"])

    wide = pairs.select(F.col("id1").cast("long"), F.col("id2").cast("long"), F.col(v1).cast("array<double>").alias("x"), F.col(v2).cast("array<double>").alias("y"))
    return wide.where((F.size("x") == dims) & (F.size("y") == dims)).mapInArrow(run, "id1 long, id2 long, method string, s double, k int, mean double, variance double")


def array_products(a: DataFrame, pairs: DataFrame, value: str = "v") -> DataFrame:
    """(id1, id2, dot) of vectors that stand in a row."""
    side = lambda n: a.select(F.col("id").alias(f"id{n}"), F.col(value).alias(f"v{n}"))
    dot = F.aggregate(F.zip_with("v1", "v2", lambda x, y: x * y), F.lit(0.0), lambda t, x: t + x)
    return pairs.join(side(1), "id1").join(side(2), "id2").select("id1", "id2", dot.alias("dot"))


# ---------------------------------------------------------------- pairs


def inner_products(a: DataFrame, pairs: DataFrame, key: str, value: str) -> DataFrame:
    """(id1, id2, dot) over a common coordinate; absent coordinates are zero. Each side is joined by id, then by coordinate."""
    left = pairs.join(a.select(F.col("id").alias("id1"), F.col(key).alias("c1"), F.col(value).alias("v1")), "id1")
    right = a.select(F.col("id").alias("id2"), F.col(key).alias("c1"), F.col(value).alias("v2"))
    dot = left.join(right, ["id2", "c1"]).groupBy("id1", "id2").agg(F.sum(F.col("v1") * F.col("v2")).alias("dot"))
    return pairs.join(dot, ["id1", "id2"], "left").select("id1", "id2", F.coalesce("dot", F.lit(0.0)).alias("dot"))


def moments(long: DataFrame, pairs: DataFrame) -> DataFrame:
    """(id1, id2, s1, s2, m1, m2, a, q): sums, squared norms, inner product, and sum of u1^2 u2^2."""
    norm = long.groupBy("id").agg(F.sum("v").alias("s"), F.sum(F.col("v") * F.col("v")).alias("m"))
    left = pairs.join(long.select(F.col("id").alias("id1"), "i", F.col("v").alias("v1")), "id1")
    x = F.col("v1") * F.col("v2")
    both = left.join(long.select(F.col("id").alias("id2"), "i", F.col("v").alias("v2")), ["id2", "i"]).groupBy("id1", "id2").agg(F.sum(x).alias("a"), F.sum(x * x).alias("q"))
    out = pairs.join(both, ["id1", "id2"], "left").select("id1", "id2", F.coalesce("a", F.lit(0.0)).alias("a"), F.coalesce("q", F.lit(0.0)).alias("q"))
    out = out.join(norm.select(F.col("id").alias("id1"), F.col("s").alias("s1"), F.col("m").alias("m1")), "id1")
    return out.join(norm.select(F.col("id").alias("id2"), F.col("s").alias("s2"), F.col("m").alias("m2")), "id2")


def var_rp(m1: Column, m2: Column, a: Column, q: Column, s: float, k: int) -> Column:
    return (m1 * m2 + a * a + (s - 3) * q) / k


def var_signed(m1: Column, m2: Column, a: Column, q: Column, s: float, k: int) -> Column:
    return (s - 1) * q + (m1 * m2 + a * a - 2 * q) / k


def var_signed_sets(f1: Column, f2: Column, a: Column, k: int) -> Column:
    """Binary vectors at s = 1."""
    return (f1 * f2 + a * a - 2 * a) / k


def expected_bucket(s1: Column, s2: Column, a: Column, k: int) -> Column:
    """Mean of the plain bucket estimate: far above a."""
    return a + (s1 * s2 - a) / k
