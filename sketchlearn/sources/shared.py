"""Tables in the folder that all executors share (spark.checkpoint.dir)."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Folders made by this process.
_made: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """A new folder below spark.checkpoint.dir. Only where that is unset and Spark runs on one machine (tests) a local one is set."""
    top = spark.conf.get("spark.checkpoint.dir", None)
    if not top:
        jvm = spark.sparkContext._jsc.sc().getCheckpointDir()
        if jvm.isEmpty():
            if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
                raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
            spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="checkpoints-"))
            jvm = spark.sparkContext._jsc.sc().getCheckpointDir()
        top = jvm.get()
    path = f"{top.rstrip('/')}/tables-{uuid.uuid4().hex[:12]}"
    _made.append(path)
    return path


def remove_written(spark: SparkSession) -> int:
    """Deletes the folders that this process made. For the end of a job: results that were not written elsewhere read from them."""
    gone = 0
    while _made:
        path = spark._jvm.org.apache.hadoop.fs.Path(_made.pop())
        gone += path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    return gone


def written(df: DataFrame, spark: SparkSession | None = None, **options) -> DataFrame:
    """The rows of df, written once to the shared folder and read from there: lineage ends here, and a lost executor costs nothing that was written."""
    spark = spark or df.sparkSession
    path = shared_dir(spark)
    df.write.options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)
