"""SQL functions and table functions registered on a session, and pipeline stages."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import keyword_only
from pyspark.ml import Transformer
from pyspark.ml.functions import array_to_vector
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.param.shared import HasInputCol, HasOutputCol
from pyspark.ml.util import DefaultParamsReadable, DefaultParamsWritable
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import projections
from . import bbit, minwise
from .hashing import TwoUniversal


def register(spark: SparkSession, k: int = 16, seed: int = 7) -> None:
    """minwise(items): an Arrow function; bbit(sig, b), match_fraction(a, b), resemblance(a, b): SQL bodies that the optimizer sees through; explode_code(code, b) and stored_permutation(j, d, seed): table functions."""
    spark.udf.register("minwise", minwise.arrow_udf(TwoUniversal(k, seed=seed)))
    spark.sql("create or replace temporary function bbit(sig array<bigint>, b int) returns array<int> return transform(sig, z -> cast(z & (shiftleft(1L, b) - 1) as int))")
    spark.sql("create or replace temporary function match_fraction(a array<bigint>, b array<bigint>) returns double return aggregate(zip_with(a, b, (x, y) -> if(x = y, 1, 0)), 0, (n, x) -> n + x) / size(a)")
    spark.sql("create or replace temporary function resemblance(a array<bigint>, b array<bigint>) returns double return size(array_intersect(a, b)) / nullif(size(array_union(a, b)), 0)")
    spark.sql("create or replace temporary function bbit_estimate(p double, b int) returns double return (p - 1.0D / shiftleft(1, b)) / (1 - 1.0D / shiftleft(1, b))")

    @F.udtf(returnType="j int, v int, idx bigint")
    class ExplodeCode:
        def eval(self, code: list, b: int):
            for j, v in enumerate(code or []):
                yield j, v, j * (1 << b) + (1 << b) - 1 - v

    spark.udtf.register("explode_code", ExplodeCode)

    @F.udtf(returnType="j int, t bigint, image bigint")
    class StoredPermutation:
        def eval(self, j: int, d: int, seed: int):
            order = np.random.default_rng([seed, j]).permutation(d)
            for t, image in enumerate(order.tolist()):
                yield j, t, image

    spark.udtf.register("stored_permutation", StoredPermutation)


class BBitEncoder(Transformer, HasInputCol, HasOutputCol, DefaultParamsReadable, DefaultParamsWritable):
    """Pipeline stage: item arrays to sparse vectors of b-bit codes, 2^b k wide."""

    k = Param(Params._dummy(), "k", "hash functions", TypeConverters.toInt)
    b = Param(Params._dummy(), "b", "bits kept", TypeConverters.toInt)
    seed = Param(Params._dummy(), "seed", "seed of the family", TypeConverters.toInt)

    @keyword_only
    def __init__(self, *, inputCol="items", outputCol="features", k=64, b=8, seed=7):
        super().__init__()
        self._setDefault(inputCol="items", outputCol="features", k=64, b=8, seed=7)
        self._set(**self._input_kwargs)

    def _transform(self, df: DataFrame) -> DataFrame:
        k, b = self.getOrDefault(self.k), self.getOrDefault(self.b)
        signed = minwise.signature(df, TwoUniversal(k, seed=self.getOrDefault(self.seed)), items=self.getInputCol())
        code = bbit.expand(bbit.truncate(F.col("sig"), b), b)
        return signed.withColumn(self.getOutputCol(), bbit.to_vector(code, k << b)).drop("sig")


class _Sketcher(Transformer, HasInputCol, HasOutputCol, DefaultParamsReadable, DefaultParamsWritable):
    """Item arrays to a dense array of k numbers; rows without an id column get one for the pass."""

    k = Param(Params._dummy(), "k", "width", TypeConverters.toInt)
    seed = Param(Params._dummy(), "seed", "seed of the entries", TypeConverters.toInt)

    @keyword_only
    def __init__(self, *, inputCol="items", outputCol="features", k=64, seed=7):
        super().__init__()
        self._setDefault(inputCol="items", outputCol="features", k=64, seed=7)
        self._set(**self._input_kwargs)

    def entries(self, items: np.ndarray, k: int, seed: int) -> np.ndarray:
        raise NotImplementedError

    def _transform(self, df: DataFrame) -> DataFrame:
        k, seed, entries = self.getOrDefault(self.k), self.getOrDefault(self.seed), self.entries

        @F.pandas_udf("array<double>")
        def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for items in batches:
                sizes = np.array([0 if x is None else len(x) for x in items])
                flat = np.concatenate([np.zeros(0, np.int64), *(x for x in items if x is not None)]).astype(np.int64)
                out = np.zeros((len(items), k))
                if len(flat):
                    names, place = np.unique(flat, return_inverse=True)
                    full = np.nonzero(sizes)[0]
                    out[full] = np.add.reduceat(entries(names, k, seed)[place], (np.cumsum(sizes) - sizes)[full])
                yield pd.Series(list(out))

        return df.withColumn(self.getOutputCol(), array_to_vector(run(F.col(self.getInputCol()).cast("array<bigint>"))))


class SignedBucketEncoder(_Sketcher):
    """Pipeline stage: item arrays to dense vectors of k signed bucket sums."""

    def entries(self, items: np.ndarray, k: int, seed: int) -> np.ndarray:
        out = np.zeros((len(items), k))
        out[np.arange(len(items)), projections.bucket_array(items, k, seed)] = projections.entry_array("sign", 1.0, seed, items)
        return out


class ProjectionEncoder(_Sketcher):
    """Pipeline stage: item arrays to dense random projections with sign entries."""

    def entries(self, items: np.ndarray, k: int, seed: int) -> np.ndarray:
        return np.stack([projections.entry_array("sign", 1.0, seed, items, f"|{j}") for j in range(k)], axis=1)
