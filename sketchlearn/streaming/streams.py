"""Streams: signatures as items arrive, with the same plans as their batch twins."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import minwise, sets
from ..functions.hashing import TwoUniversal
from ..operators import learn, projections
from ..plans import relational
from ..sources.tables import SCHEMAS


def read_table_stream(spark: SparkSession, path: str, name: str, files_per_trigger: int | None = None) -> DataFrame:
    """A folder of Parquet files of a table as a stream, with the declared schema."""
    reader = spark.readStream.schema(SCHEMAS[name])
    return (reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader).parquet(path)


def signature_stream(documents: DataFrame, k: int = 16) -> DataFrame:
    """Map only: each document's signature as it arrives."""
    items = sets.text_items(documents.select(F.col("doc_id").alias("id"), "text"), "text").where(F.size("items") > 0)
    return minwise.signature(items, TwoUniversal(k)).select("id", "sig")


def event_items(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """(id, ts, t) with a watermark. The tables' timestamps have no zone and are cast first, or the watermark is refused."""
    ts = F.col("ts").cast("timestamp")
    token = F.concat_ws("|", "event_type", F.hour("ts"))
    return events.withColumn("ts", ts).withWatermark("ts", late).select(F.col("user_id").alias("id"), "ts", sets.md5_number(token, sets.RANGE).alias("t"))


def tumbling_signature(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return relational.tumbling(event_items(events, late))


def sliding_signature(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return relational.sliding(event_items(events, late))


def session_signature(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return relational.sessions(event_items(events, late))


def deduplicated(signed: DataFrame, arrived: str = "arrived", within: str = "1 hour") -> DataFrame:
    """Documents whose whole signature was not seen within a time; state is one hash a document, dropped behind the watermark."""
    keyed = signed.withColumn("sig_hash", F.md5(F.array_join(F.transform("sig", lambda z: z.cast("string")), ",")))
    return keyed.withWatermark(arrived, within).dropDuplicatesWithinWatermark(["sig_hash"])


def running_buckets(long: DataFrame, k: int = 64) -> DataFrame:
    """Signed bucket sums of a stream of (id, i, v); linear, so a negative v takes an item back."""
    return projections.bucket_sum(long, k)


def with_labels(signed: DataFrame, labels: DataFrame) -> DataFrame:
    """Stream joined to the static labels."""
    return signed.join(labels.select(F.col("doc_id").alias("id"), "quality", "toxic"), "id")


def equal_codes_within(left: DataFrame, right: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join: (id, at, code) of both sides with one code, at most a time apart; both sides need watermarks."""
    a, b = left.selectExpr("id as id1", "at as at1", "code as code1"), right.selectExpr("id as id2", "at as at2", "code as code2")
    return a.join(b, F.expr(f"code1 = code2 and at2 >= at1 and at2 <= at1 + interval {within}"))


def growing_signature(items: DataFrame, k: int = 8, ttl_ms: int | None = None) -> DataFrame:
    """Own state: a user's signature over all items so far, sent whenever it changes, dropped after ttl_ms (processing time) without items; None keeps it. items: (id, t)."""
    family = TwoUniversal(k)
    c1, c2 = (np.array(x, np.int64) for x in zip(*family.numbers(), strict=True))

    def grow(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        old = np.array(state.get[0]) if state.exists else None
        new = old
        for pdf in frames:
            low = minwise.numpy_signature(pdf["t"].to_numpy(np.int64), c1, c2, family)
            new = low if new is None else np.minimum(new, low)
        if new is not None and (old is None or (new != old).any()):
            state.update((new.tolist(),))
            yield pd.DataFrame({"id": [key[0]], "sig": [new.tolist()]})
        if ttl_ms:
            state.setTimeoutDuration(ttl_ms)

    return items.groupBy("id").applyInPandasWithState(grow, "id long, sig array<long>", "sig array<long>", "append", GroupStateTimeout.ProcessingTimeTimeout if ttl_ms else GroupStateTimeout.NoTimeout)


class OnlineLearner:
    """SGD over a stream of (y, active): each batch continues from the weights that the batch before left.

    With a folder, the weights after each batch are a written table named by the
    batch's number; a learner made anew on the folder goes on from the last one,
    and a batch that is run again after a failure starts from the one before it.
    """

    def __init__(self, dims: int, c: float, loss: str = "hinge", parts: int = 4, folder: str | None = None, spark: SparkSession | None = None):
        self.dims, self.c, self.loss, self.parts, self.folder, self.w, self.seen = dims, c, loss, parts, folder, np.zeros(dims), 0
        self.batch = -1
        if folder is not None:
            self.restore(spark or SparkSession.active())

    def restore(self, spark: SparkSession, before: int | None = None) -> None:
        """The newest stored weights, or the newest of a batch before the given one."""
        try:
            stored = spark.read.schema("seen long, w binary, batch long").parquet(self.folder)
            rows = stored if before is None else stored.where(F.col("batch") < before)
            last = rows.orderBy(F.desc("batch")).limit(1).collect()
        except AnalysisException:  # nothing was written yet
            last = []
        self.w, self.seen, self.batch = (np.frombuffer(last[0].w).copy(), last[0].seen, last[0].batch) if last else (np.zeros(self.dims), 0, -1)

    def __call__(self, batch: DataFrame, number: int) -> None:
        if self.folder is not None and number <= self.batch:
            self.restore(batch.sparkSession, number)
        w = self.w

        def local(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            own, n = w, 0
            for held in frames:  # an Arrow batch at a time: a task's rows need not fit it together
                own = learn.sgd(learn.SparseRows(held["active"].tolist(), None, self.dims), held["y"].to_numpy(float), self.c, self.loss, 1, seed=number, w=own)
                n += len(held)
            if n:
                yield pd.DataFrame({"n": [n], "w": [own.tobytes()]})

        got = batch.select("y", "active").repartition(self.parts).mapInPandas(local, "n long, w binary").collect()  # one row of a fixed size a part
        if total := sum(r.n for r in got):
            self.w = sum(np.frombuffer(r.w) * (r.n / total) for r in got)
            self.seen += total
        self.batch = number
        if self.folder is not None:
            row = batch.sparkSession.createDataFrame([(self.seen, bytearray(self.w.tobytes()))], "seen long, w binary")
            row.write.mode("overwrite").parquet(f"{self.folder}/batch={number}")


def late_rows(query: StreamingQuery) -> int:
    """Rows that came behind the watermark and were left out, summed over the batches that the query reports."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])


def to_memory(df: DataFrame, name: str, mode: str = "append") -> StreamingQuery:
    """Runs a stream over all files that are there into a memory table."""
    query = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    query.awaitTermination()
    return query
