"""Storage, parameters and times."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession

from ..sources.tables import drain, read_libsvm


def bits_minwise(n: int, k: int, width: int = 64) -> int:
    return n * k * width


def bits_bbit(n: int, b: int, k: int) -> int:
    return n * b * k


def bits_buckets(n: int, k: int, width: int = 32, nnz: float | None = None) -> int:
    """Dense entries; with nnz the sparse form (an index and a value each) if that is smaller."""
    dense = n * k * width
    return dense if nnz is None else min(dense, int(n * min(nnz, k) * (32 + width)))


def train_bytes(n_train: int, k: int, width: int = 32) -> int:
    return n_train * k * width // 8


def params_two_universal(k: int) -> int:
    return 2 * k


def params_permutations(k: int, d: int) -> int:
    return k * d


def storage_ratio_at_variance(var_signed_times_k: Column, var_bbit_times_k: Column, slope: Column, b: int, width: int = 32) -> Column:
    """Bits of signed buckets over bits of codes when both estimate the inner product with one variance.

    Both variances fall as 1/k, so the needed k are as the numerators; slope =
    da/dR carries the resemblance's variance over to the inner product.
    """
    return var_signed_times_k / (var_bbit_times_k * slope * slope) * width / b


def timed(fn: Callable[[], object]) -> tuple[object, float]:
    began = time.perf_counter()
    out = fn()
    return out, time.perf_counter() - began


def time_plan(df: DataFrame) -> float:
    """Seconds to run a plan into the noop sink."""
    return timed(lambda: drain(df))[1]


def time_load(spark: SparkSession, path: str, dims: int) -> float:
    """Seconds to read interchange text into labelled sparse rows."""
    return time_plan(read_libsvm(spark, path, dims))


def time_preprocess(items: DataFrame, k: int, shape: str = "arrow") -> float:
    """Seconds to make k minima of each set, vectorised ("arrow") or by row expressions ("compiled"; "array" with lambdas)."""
    from ..functions.hashing import TwoUniversal
    from ..functions.minwise import signature

    return time_plan(signature(items, TwoUniversal(k), shape=shape).select("id", "sig"))
