"""b-bit codes: the low bits of each minimum, packed, sliced and expanded."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.shared import shared_dir

WIDTHS = (1, 2, 4, 8, 12, 16)


def check_width(b: int, expansion: bool = True) -> None:
    if b < 1 or (expansion and b > 16):
        raise ValueError("expansion needs 1 to 16 bits: 2^b slots a hash function")


def truncate(sig: Column, b: int) -> Column:
    return F.transform(sig, lambda z: z.bitwiseAND(F.lit((1 << b) - 1)).cast("int"))


def sliced(sig: Column, k: int, b: int) -> Column:
    """The code of a smaller configuration out of a wider one: first k values, low b bits."""
    return truncate(F.slice(sig, 1, k), b)


def expand(code: Column, b: int, orientation: str = "example") -> Column:
    """Places of the k ones of the 2^b k long vector. "example": value v lights place 2^b - 1 - v of its block; "natural": place v."""
    check_width(b)
    width = 1 << b
    place = (lambda v: width - 1 - v) if orientation == "example" else (lambda v: v)
    return F.transform(code, lambda v, j: (j * width + place(v)).cast("long"))


def onehot_full(sig: Column, d: int) -> Column:
    """Places of the ones of full-width minima: j d + z."""
    if d > 1 << 30:
        raise ValueError("full expansion is for ranges up to 2^30")
    return F.transform(sig, lambda z, j: j.cast("long") * d + z)


def pack_words(code: Column, b: int, per_word: int | None = None) -> Column:
    """Words of up to 60 bits, 60 // b codes each, the first in the lowest bits: JVM expressions only."""
    n = per_word or 60 // b
    words = F.sequence(F.lit(0), F.ceil(F.size(code) / n).cast("int") - 1)
    return F.transform(words, lambda w: F.aggregate(F.reverse(F.slice(code, w * n + 1, F.lit(n))), F.lit(0).cast("long"), lambda acc, v: F.shiftleft(acc, b) + v.cast("long")))


def pack(code: Column, b: int) -> Column:
    """ceil(b k / 8) bytes a row."""

    @F.pandas_udf("binary")
    def run(codes: pd.Series) -> pd.Series:
        return pd.Series(by_length(codes, lambda m: pack_rows(m.astype(np.int64), b)))

    return run(code)


def unpack(packed: Column, b: int, k: int) -> Column:
    @F.pandas_udf("array<int>")
    def run(raw: pd.Series) -> pd.Series:
        as_bytes = pd.Series([None if x is None else np.frombuffer(x, np.uint8) for x in raw])
        return pd.Series(by_length(as_bytes, lambda m: list(unpack_rows(m, b, k))))

    return run(packed)


def by_length(rows: pd.Series, fn) -> list:
    """fn of the matrix of all rows of one length at a time; nulls stay."""
    out, sizes = [None] * len(rows), np.array([-1 if x is None else len(x) for x in rows])
    for n in np.unique(sizes[sizes >= 0]).tolist():
        at = np.nonzero(sizes == n)[0].tolist()
        for i, x in zip(at, fn(np.stack([np.asarray(rows.iloc[i]) for i in at])), strict=True):
            out[i] = x
    return out


def pack_rows(codes: np.ndarray, b: int) -> list[bytes]:
    bits = ((codes[:, :, None] >> np.arange(b)) & 1).astype(np.uint8).reshape(len(codes), -1)
    return [x.tobytes() for x in np.packbits(bits, axis=1, bitorder="little")]


def unpack_rows(raw: np.ndarray, b: int, k: int) -> np.ndarray:
    bits = np.unpackbits(raw, axis=1, bitorder="little")[:, : b * k].reshape(len(raw), k, b)
    return (bits.astype(np.int64) << np.arange(b)).sum(2).astype(np.int32)


def pack_numpy(code: np.ndarray, b: int) -> bytes:
    bits = (code[:, None] >> np.arange(b)) & 1
    return np.packbits(bits.astype(np.uint8).ravel(), bitorder="little").tobytes()


def unpack_numpy(raw: bytes, b: int, k: int) -> np.ndarray:
    bits = np.unpackbits(np.frombuffer(raw, np.uint8), bitorder="little")[: b * k].reshape(k, b)
    return (bits.astype(np.int64) << np.arange(b)).sum(1).astype(np.int32)


def vector_table(df: DataFrame, active: Column, dims: int, out: str = "features") -> DataFrame:
    """df with sparse 0/1 vectors for a solver that reads them many times: made by JVM expressions as the vectors' own fields, written once, and read back as vectors."""
    from pyspark.ml.linalg import VectorUDT

    places = F.array_sort(F.array_distinct(active.cast("array<int>")))
    fields = F.struct(F.lit(0).cast("byte").alias("type"), F.lit(dims).alias("size"), places.alias("indices"), F.transform(places, lambda _: F.lit(1.0)).alias("values"))
    path = shared_dir(df.sparkSession)
    df.withColumn(out, fields).write.parquet(path)
    schema = T.StructType([*(f for f in df.schema.fields if f.name != out), T.StructField(out, VectorUDT())])
    return df.sparkSession.read.schema(schema).parquet(path)


def to_vector(active: Column, dims: int) -> Column:
    """Sparse 0/1 vectors as a column, a row at a time, for lazy pipelines; see vector_table() for training."""
    from pyspark.ml.linalg import Vectors, VectorUDT

    return F.udf(lambda a: Vectors.sparse(dims, sorted(set(a)), [1.0] * len(set(a))), VectorUDT())(active)
