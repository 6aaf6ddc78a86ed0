"""Hash families over item numbers. A family is k pairs of numbers; stored permutations are the exact but heavy alternative."""

from __future__ import annotations

import hashlib
import warnings
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: The default prime 2^31 - 1 and range 2^30: c1 + c2 * t stays below 2^62.
PRIME, RANGE = (1 << 31) - 1, 1 << 30
#: Items of a stored permutation at most.
MOST_STORED = 100_000_000


def seeded(seed: int, role: str, j: int) -> int:
    """A number from md5 of seed, role and index: SQL makes the same."""
    return int(hashlib.md5(f"{seed}|{role}|{j}".encode()).hexdigest()[:13], 16)


def mersenne_values(t: np.ndarray, c1: np.ndarray, c2: np.ndarray, width: int) -> np.ndarray:
    """(c1 + c2 t) mod 2^31 - 1, then mod a power of two, without a division. Folding a positive number gives 1..p; one added before and taken off after gives 0..p - 1."""
    x = c2 * t
    x += c1 + 1
    high = x >> 31
    x &= PRIME
    x += high  # below 2^32
    x = x.astype(np.uint32)
    high = x >> np.uint32(31)
    x &= np.uint32(PRIME)
    x += high
    x -= np.uint32(1)
    x &= np.uint32(width - 1)
    return x


@dataclass(frozen=True)
class Affine:
    """h_j(t) = (c1_j + c2_j t) mod p, then mod the range."""

    k: int
    range: int = RANGE
    p: int = PRIME
    seed: int = 7

    def __post_init__(self):
        if not self.p > self.range - 1:
            raise ValueError("the prime must not be below the range")

    def numbers(self) -> list[tuple[int, int]]:
        return [(seeded(self.seed, "c1", j) % self.p, 1 + seeded(self.seed, "c2", j) % (self.p - 1)) for j in range(self.k)]

    def params(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(j, a, b) for j, (a, b) in enumerate(self.numbers())], "j int, c1 bigint, c2 bigint")

    def params_of(self, numbers: DataFrame) -> DataFrame:
        """(j, c1, c2) of the functions with the given numbers j, however many: made where the numbers lie."""
        drawn = lambda role, below: F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(self.seed)), F.lit(role), F.col("j").cast("string"))), 1, 13), 16, 10).cast("long") % below
        return numbers.select("j", drawn("c1", self.p).alias("c1"), (1 + drawn("c2", self.p - 1)).alias("c2"))

    def literal(self) -> Column:
        """The parameters as one constant array of (c1, c2): 16 bytes a hash function, inside the plan."""
        return F.array(*(F.struct(F.lit(a).cast("long").alias("c1"), F.lit(b).cast("long").alias("c2")) for a, b in self.numbers()))

    def value(self, c1: Column, c2: Column, t: Column) -> Column:
        return (c1 + c2 * t) % self.p % self.range

    def column(self, t: Column, j: int) -> Column:
        a, b = self.numbers()[j]
        return self.value(F.lit(a).cast("long"), F.lit(b).cast("long"), t)

    def numpy(self, t: np.ndarray, c1: np.ndarray, c2: np.ndarray) -> np.ndarray:
        if self.p == PRIME and self.range & (self.range - 1) == 0:
            return mersenne_values(t, c1, c2, self.range)
        return (c1 + c2 * t) % self.p % self.range

    def check(self, largest_set: int) -> None:
        if largest_set > 0.001 * self.range:
            warnings.warn(f"sets of {largest_set} items folded into a range of {self.range}: ties near the minimum bias the estimate", stacklevel=2)


class TwoUniversal(Affine):
    """The two-universal family: 2k numbers replace k stored permutations."""


class MersenneTwoUniversal(Affine):
    """The same values for p = 2^31 - 1 by shifts and additions instead of a division."""

    def value(self, c1: Column, c2: Column, t: Column) -> Column:
        if self.p != PRIME:
            raise ValueError("shift reduction needs p = 2^31 - 1")
        x = c1 + c2 * t
        for _ in range(2):
            x = x.bitwiseAND(F.lit(PRIME)) + F.shiftright(x, 31)
        return F.when(x == PRIME, F.lit(0).cast("long")).otherwise(x) % self.range

    def numpy(self, t, c1, c2):
        if self.range & (self.range - 1) == 0:
            return mersenne_values(t, c1, c2, self.range)
        x = c1 + c2 * t
        x = (x & PRIME) + (x >> 31)
        x = (x & PRIME) + (x >> 31)
        x[x == PRIME] = 0
        return x % self.range


class AffinePrime(Affine):
    """No second modulus: a bijection of 0..p-1, so different items never tie."""

    def __init__(self, k: int, p: int = PRIME, seed: int = 7):
        super().__init__(k, p, p, seed)


def fixed_point(family) -> tuple[list[int], list[int], int] | None:
    """(factors, shifts, turn) of a family modulo 2^31 - 1 whose range is a power of two or the prime itself, else None: as unsigned 64-bit
    numbers, shift + factor t is the fraction (v + 1/2) / p in units of 2^-64, v = 2^turn (c1 + c2 t) mod p. Times 2^turn turns the 31 bits
    around, so that those that the range keeps stand uppermost: the least fraction is that of the least value, and nothing is divided.
    For 0 <= t <= p rounding is below 2^31, half of a step of v above 2^32."""
    if not isinstance(family, Affine) or family.p != PRIME or (family.range & (family.range - 1) and family.range != PRIME):
        return None
    turn = 0 if family.range == PRIME else 32 - family.range.bit_length()
    turned = [((a << turn) % PRIME, (b << turn) % PRIME) for a, b in family.numbers()]
    return [((b << 65) + PRIME) // (2 * PRIME) for _, b in turned], [((2 * a + 1) << 63) // PRIME for a, _ in turned], turn


def from_fixed_point(x: np.ndarray, turn: int) -> np.ndarray:
    """The values (in the range) of the fractions of fixed_point()."""
    p, low = np.uint64(PRIME), np.uint64((1 << 32) - 1)
    v = ((x >> np.uint64(32)) * p + (((x & low) * p) >> np.uint64(32))) >> np.uint64(32)
    return (v >> np.uint64(turn)).astype(np.int64)


@dataclass(frozen=True)
class MultiplyShift:
    """h_j(t): the upper bits of a_j t + b_j modulo 2^64; no division at all. numpy only (unsigned 64-bit)."""

    k: int
    bits: int = 30
    seed: int = 7

    def numbers(self) -> list[tuple[int, int]]:
        wide = lambda role, j: (seeded(self.seed, role, j) << 32 ^ seeded(self.seed, role + "'", j)) % (1 << 64)
        return [(wide("b", j), wide("a", j) | 1) for j in range(self.k)]

    def numpy(self, t: np.ndarray, c1: np.ndarray, c2: np.ndarray) -> np.ndarray:
        return ((c1.astype(np.uint64) + c2.astype(np.uint64) * t.astype(np.uint64)) >> np.uint64(64 - self.bits)).astype(np.int64)


class WideTwoUniversal(Affine):
    """A 64-bit universe: p = 2^61 - 1, products taken in two limbs. numpy only."""

    WIDE = (1 << 61) - 1

    def __init__(self, k: int, range: int = 1 << 60, seed: int = 7):
        super().__init__(k, range, self.WIDE, seed)

    def numbers(self) -> list[tuple[int, int]]:
        wide = lambda role, j: seeded(self.seed, role, j) << 20 ^ seeded(self.seed, role + "'", j)
        return [(wide("c1", j) % self.p, 1 + wide("c2", j) % (self.p - 1)) for j in __import__("builtins").range(self.k)]

    def numpy(self, t, c1, c2):
        p, low = np.uint64(self.WIDE), np.uint64((1 << 31) - 1)
        t, c1, c2 = (np.asarray(x).astype(np.uint64) for x in (t, c1, c2))
        t = t % p
        fold = lambda x: (x & p) + (x >> np.uint64(61))
        a1, a0, b1, b0 = c2 >> np.uint64(31), c2 & low, t >> np.uint64(31), t & low
        mid = a1 * b0 + a0 * b1  # below 2^62
        high = fold((a1 * b1) << np.uint64(1))  # 2^62 = 2 modulo p
        # mid * 2^31: its upper bits wrap around at 2^61.
        mid = ((mid & np.uint64((1 << 30) - 1)) << np.uint64(31)) + (mid >> np.uint64(30))
        x = fold(fold(high + fold(mid)) + fold(a0 * b0))
        x = fold(x + c1)
        return (np.where(x >= p, x - p, x) % np.uint64(self.range)).astype(np.int64)


@dataclass(frozen=True)
class StoredPermutations:
    """k permutations of 0..d-1, each the rank of its members by md5: exact, and k * d rows. A permutation is ranked in one task, so d has a bound: beyond it permutations are not a method but an obstacle."""

    k: int
    d: int
    seed: int = 7

    def __post_init__(self):
        if self.d > MOST_STORED:
            raise ValueError(f"permutations of {self.d} items are not stored: {MOST_STORED} at most")

    def image(self, j: int) -> np.ndarray:
        """The images of 0..d-1 under permutation j, as in table()."""
        high, low, step = np.empty(self.d, np.uint64), np.empty(self.d, np.uint64), 100_000
        for i in range(0, self.d, step):
            digests = np.frombuffer(b"".join([hashlib.md5(b"%d|%d|%d" % (self.seed, j, t)).digest() for t in range(i, min(self.d, i + step))]), ">u8")
            high[i : i + step], low[i : i + step] = digests[::2], digests[1::2]
        out = np.empty(self.d, np.int32)
        out[np.lexsort((low, high))] = np.arange(self.d, dtype=np.int32)
        return out

    def table(self, spark: SparkSession) -> DataFrame:
        """(j, t, image). Each j is a window of its own: d rows."""
        pairs = spark.range(self.k * self.d).select((F.col("id") / self.d).cast("long").alias("j0"), (F.col("id") % self.d).alias("t")).select(F.col("j0").cast("int").alias("j"), "t")
        order = Window.partitionBy("j").orderBy(F.md5(F.concat_ws("|", F.lit(str(self.seed)), F.col("j").cast("string"), F.col("t").cast("string"))), "t")
        return pairs.select("j", "t", (F.row_number().over(order) - 1).cast("long").alias("image"))
