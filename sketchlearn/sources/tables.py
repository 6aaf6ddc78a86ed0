"""Tables, interchange files and stores of codes and models."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The declared schemas of the tables.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table with its declared schema: no inference, and scans read the columns asked for."""
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame, task_bytes: int = 32 << 20) -> DataFrame:
    """df over all cores where its files are too few or small to give each core a task's worth (one row group is one task); larger inputs stay as they are scanned, without a shuffle. Rows are the same."""
    if df.isStreaming:
        return df
    cores = df.sparkSession.sparkContext.defaultParallelism
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return df.repartition(cores) if size < cores * task_bytes else df


def read_any(spark: SparkSession, path: str, kind: str, schema: str | None = None, **options) -> DataFrame:
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_any(df: DataFrame, path: str, kind: str, mode: str = "overwrite", **options) -> None:
    df.write.format(kind).mode(mode).options(**options).save(path)


def read_libsvm(spark: SparkSession, path: str, dims: int) -> DataFrame:
    """Label and sparse vector; with dims given no pass is spent on inferring them."""
    return spark.read.format("libsvm").option("numFeatures", str(dims)).load(path)


def write_libsvm(df: DataFrame, path: str, label: str = "y", active: str = "active") -> None:
    """Lines "label index:1 ..." of 1-based, ascending indices, which may pass 2^31."""
    line = F.concat_ws(" ", F.col(label).cast("string"), F.transform(F.array_sort(active), lambda i: F.concat((i + 1).cast("string"), F.lit(":1"))))
    df.select(line.alias("value")).write.mode("overwrite").text(path)


def write_codes(df: DataFrame, path: str) -> None:
    """Packed codes (id, b, k, code), sorted by id inside files: ranges of ids skip row groups."""
    df.sortWithinPartitions("id").write.mode("overwrite").parquet(path)


def read_codes(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("id bigint, b int, k int, code binary").parquet(path)


def save_model(df: DataFrame, path: str) -> None:
    df.select("cell", "idx", "w").write.mode("overwrite").parquet(path)


def load_model(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("cell string, idx bigint, w double").parquet(path)


def drain(df: DataFrame) -> None:
    """Runs a plan to its end without keeping the rows."""
    df.write.format("noop").mode("overwrite").save()
