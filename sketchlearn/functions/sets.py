"""Sets of items from the tables: word n-grams, baskets, tokens of pages, events and conversations."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import load_table, spread
from .digests import md5_slices

#: Range of item numbers and of the default hash family: 2^30.
RANGE = 1 << 30
#: Words of a text that are cut into n-grams at a time: a long text takes bounded memory.
WORDS_AT_ONCE = 100_000
#: Texts in a batch of sets: a set is several times as large as its text.
ROWS_AT_ONCE = 500


def md5_number(text: Column, modulus: int) -> Column:
    """The first 13 hex digits of md5 as a number, modulo: the same in Spark and DuckDB."""
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long") % modulus


def tokens(text: Column) -> Column:
    """Lower-case runs of letters and digits."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def let(col: Column, fn) -> Column:
    """fn of a value computed once: inside a lambda an expression would be computed anew for each element."""
    return F.transform(F.array(col), fn)[0]


def ngrams(words: Column, n: int) -> Column:
    """Runs of n words, joined by a blank; none if there are fewer words. words: a column or a bound value, see let()."""
    if n == 1:
        return words
    runs = F.transform(F.sequence(F.lit(1), F.size(words) - (n - 1)), lambda i: F.array_join(F.slice(words, i, n), " "))
    return F.when(F.size(words) >= n, runs).otherwise(F.array().cast("array<string>"))


def shingles(text: Column, sizes: tuple[int, ...] = (1, 2, 3)) -> Column:
    """Distinct n-grams of the given sizes."""
    return let(tokens(text), lambda words: F.array_distinct(F.concat(*(ngrams(words, n) for n in sizes))))


def hash_items(items: Column, modulus: int = RANGE) -> Column:
    """Distinct numbers below modulus."""
    return F.array_distinct(F.transform(items, lambda g: md5_number(g, modulus)))


def words_text(text: Column) -> Column:
    """The words of tokens(), with one blank between them."""
    return F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+", " ")


def gram_numbers(text: bytes, sizes: tuple[int, ...] = (1, 2, 3), modulus: int = RANGE) -> np.ndarray:
    """Sorted distinct numbers of the n-grams of a text of words_text(): those of hash_items(shingles(text))."""
    words, parts, md5 = text.split(), [], hashlib.md5
    for at in range(0, len(words), WORDS_AT_ONCE):
        some, grams = words[at : at + WORDS_AT_ONCE + max(sizes) - 1], set()
        for n in sizes:
            own = some[: WORDS_AT_ONCE + n - 1]
            grams.update(own if n == 1 else map(b" ".join, zip(*(own[i:] for i in range(n)), strict=False)))
        # 13 hex digits are the upper 52 bits of a digest.
        digests = np.frombuffer(b"".join([md5(g).digest() for g in grams]), ">u8")[::2]
        parts.append(np.unique((digests >> np.uint64(12)).astype(np.int64) % modulus))
    if len(parts) == 1:
        return parts[0]
    return np.unique(np.concatenate(parts)) if parts else np.zeros(0, np.int64)


def many_gram_numbers(texts: list[bytes], sizes: tuple[int, ...] = (1, 2, 3), modulus: int = RANGE) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of gram_numbers() of each text one after the other, and how many each has: short texts are hashed together."""
    found, counts, words, lengths, own = {}, np.zeros(len(texts), np.int64), [], [], 0

    def flush() -> None:
        """Hashes the texts that were gathered."""
        nonlocal words, lengths, own
        size = np.fromiter(map(len, words), np.int64, len(words)) + 1
        begin, owner = np.cumsum(size) - size, np.repeat(np.arange(len(lengths)), [n for _, n in lengths])
        end, data, keys = begin + size - 1, np.frombuffer(b" ".join(words), np.uint8), [np.zeros(0, np.int64)]
        for n in sizes:
            if len(words) >= n:
                at = np.nonzero(owner[: len(owner) - n + 1] == owner[n - 1 :])[0]
                keys.append(owner[at] * modulus + md5_slices(data, begin[at], end[at + n - 1] - begin[at]) % modulus)
        key = np.sort(np.concatenate(keys))  # np.unique would go by a hash table, at several times the cost
        key = key[np.concatenate([[True], key[1:] != key[:-1]])] if len(key) else key
        cuts = np.searchsorted(key, np.arange(len(lengths) + 1) * modulus)
        for i, (number, _) in enumerate(lengths):
            found[number] = key[cuts[i] : cuts[i + 1]] - i * modulus
        words, lengths, own = [], [], 0

    for number, text in enumerate(texts):
        parts = text.split()
        if len(parts) > WORDS_AT_ONCE:
            found[number] = gram_numbers(text, sizes, modulus)
            continue
        if own + len(parts) > WORDS_AT_ONCE:
            flush()
        words += parts
        lengths.append((number, len(parts)))
        own += len(parts)
    flush()
    counts[:] = [len(found[i]) for i in range(len(texts))]
    return np.concatenate([np.zeros(0, np.int64), *(found[i] for i in range(len(texts)))]), counts


def text_items(df: DataFrame, text: str, sizes: tuple[int, ...] = (1, 2, 3), modulus: int = RANGE) -> DataFrame:
    """df with the column text replaced by items array<bigint>, the numbers of its n-grams: one Arrow pass, no shuffle."""
    others = [c for c in df.columns if c != text]
    schema = df.select(*others, F.array().cast("array<bigint>").alias("items")).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (whole.slice(i, ROWS_AT_ONCE) for whole in batches for i in range(0, whole.num_rows, ROWS_AT_ONCE)):
            flat, counts = many_gram_numbers(b.column(b.num_columns - 1).cast(pa.binary()).to_pylist(), sizes, modulus)
            ends = np.concatenate([[0], np.cumsum(counts)])
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat))], names=[*b.schema.names[:-1], "items"])

    return spread(df).select(*others, words_text(F.col(text)).alias(text)).mapInArrow(run, schema)


def signed_label(col: Column) -> Column:
    return 2 * col - 1


def binarise(df: DataFrame, value: str = "v", threshold: float = 0.0) -> DataFrame:
    return df.where(F.col(value) > threshold)


# ---------------------------------------------------------------- sets on the tables


def documents(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """DOC: (id, items) of hashed n-grams; empty sets are kept with no items."""
    return text_items(load_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text"), "text", sizes)


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """PAGE: tokens of the html without script, style, comments and tags."""
    html = F.regexp_replace("html", r"(?is)<script.*?</script>|<style.*?</style>|<!--.*?-->|<[^>]*>", " ")
    return load_table(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), hash_items(F.array_distinct(tokens(html))).alias("items"))


def basket_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, t, quantity) of customers, parts and summed quantities."""
    orders, lines = load_table(spark, sf_dir, "orders"), load_table(spark, sf_dir, "lineitem")
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey).groupBy(F.col("o_custkey").alias("id"), F.col("l_partkey").alias("t")).agg(F.sum("l_quantity").alias("v"))


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """CUST: parts that a customer ordered."""
    return basket_lines(spark, sf_dir).groupBy("id").agg(F.array_sort(F.collect_set("t")).alias("items"))


def suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """SUPP: parts that a supplier shipped."""
    return load_table(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("id")).agg(F.array_sort(F.collect_set("l_partkey")).alias("items"))


def event_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """EVT in long form: (id, token, ts)."""
    e = load_table(spark, sf_dir, "events")
    ts = F.col("ts").cast("timestamp")
    return e.select(F.col("user_id").alias("id"), F.concat_ws("|", "event_type", F.hour(ts)).alias("token"), ts.alias("ts"))


def vectors_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    """EMB in long form: (id, i, v)."""
    e = load_table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("id"), F.posexplode("embedding").alias("i", "x")).select("id", F.col("i").cast("long").alias("i"), F.col("x").cast("double").alias("v"))


def profile(sets: DataFrame, items: str = "items") -> DataFrame:
    """n, d (largest item number + 1), median and mean of the set sizes."""
    size = F.size(items)
    return sets.agg(F.count(F.lit(1)).alias("n"), (F.max(F.array_max(items)) + 1).alias("d"), F.round(F.percentile(size, 0.5), 6).alias("nnz_median"), F.round(F.avg(size), 6).alias("nnz_mean"))
