"""Equi-joins of which a few keys may hold a large share of the rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Keys that are told apart as heavy at most (they go to every task), and rows below which no key is heavy.
MOST_HEAVY, LEAST_HEAVY = 100_000, 100


def heavy_keys(left: DataFrame, key: str, n: int | None = None) -> DataFrame:
    """(key) of keys with more than n / MOST_HEAVY rows: fewer than MOST_HEAVY, whatever the data. Counts are summed before the shuffle."""
    n = left.count() if n is None else n
    least = max(LEAST_HEAVY, -(-n // MOST_HEAVY))
    return left.groupBy(key).agg(F.count(F.lit(1)).alias("_n")).where((F.col("_n") > least) & F.col(key).isNotNull()).select(key)


def spread_join(left: DataFrame, right: DataFrame, key: str, how: str = "left", n: int | None = None, heavy: DataFrame | None = None) -> DataFrame:
    """left joined to right, whose keys are unique, by a column of the same name; how: inner or left.

    Rows of heavy keys meet their few partners where they stand; the others are
    shuffled, and none of their keys has more than a hundred-thousandth of the
    rows; rows without a key have no partner. left is read several times: give a
    written table.
    """
    heavy = heavy_keys(left, key, n) if heavy is None else heavy
    partners = right.join(F.broadcast(heavy), key, "left_semi")
    few = left.join(F.broadcast(heavy), key, "left_semi").join(F.broadcast(partners), key, how)
    most = left.where(F.col(key).isNotNull()).join(F.broadcast(heavy), key, "left_anti").join(right, key, how)
    out = most.unionByName(few)
    return out if how == "inner" else out.unionByName(left.where(F.col(key).isNull()), allowMissingColumns=True)
