import pytest
from pyspark.sql import functions as F

from sketchlearn.plans import relational
from sketchlearn.streaming import streams

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("events"))
    spark.read.parquet(f"{SF}/events.parquet").repartitionByRange(3, "ts").write.mode("overwrite").parquet(path)
    return path


@pytest.mark.parametrize(("stream", "batch"), [(streams.tumbling_signature, relational.events_tumbling_signature), (streams.sliding_signature, relational.events_sliding_signature)])
def test_closed_windows_equal_the_batch_twin(spark, folder, stream, batch):
    events = streams.read_table_stream(spark, folder, "events")
    streams.to_memory(stream(events), f"out_{batch.__name__}")
    got = {tuple(r) for r in spark.table(f"out_{batch.__name__}").collect()}
    want = {tuple(r) for r in batch(spark, SF).collect()}
    assert got and got <= want


def test_complete_mode_equals_the_batch_twin(spark, folder):
    streams.to_memory(streams.tumbling_signature(streams.read_table_stream(spark, folder, "events")), "complete_out", "complete")
    assert {tuple(r) for r in spark.table("complete_out").collect()} == {tuple(r) for r in relational.events_tumbling_signature(spark, SF).collect()}


def test_document_stream_and_own_state(spark, folder, tmp_path):
    spark.read.parquet(f"{SF}/documents.parquet").write.parquet(f"{tmp_path}/docs")
    docs = streams.read_table_stream(spark, f"{tmp_path}/docs", "documents")
    streams.to_memory(streams.signature_stream(docs), "sigs")
    assert spark.table("sigs").count() > 150
    items = streams.event_items(streams.read_table_stream(spark, folder, "events")).select("id", "t")
    streams.to_memory(streams.growing_signature(items), "grown")
    assert spark.table("grown").select("id").distinct().count() == 15


def test_online_learner(spark, tmp_path):
    rows = [(1 if i % 2 else -1, [i % 2, 2 + i % 3]) for i in range(200)]
    spark.createDataFrame(rows, "y int, active array<bigint>").repartition(4).write.parquet(f"{tmp_path}/codes")
    learner = streams.OnlineLearner(5, 1.0)
    q = spark.readStream.schema("y int, active array<bigint>").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/codes").writeStream.foreachBatch(learner).trigger(availableNow=True).start()
    q.awaitTermination()
    assert learner.seen == 200 and learner.w[1] > 0 > learner.w[0]


def test_deduplication_and_joins(spark, tmp_path):
    rows = [(1, [1, 2], "2024-01-01 00:00:00"), (2, [1, 2], "2024-01-01 00:10:00"), (3, [5], "2024-01-01 00:20:00")]
    spark.createDataFrame(rows, "id long, sig array<bigint>, at string").selectExpr("id", "sig", "cast(at as timestamp) as arrived").coalesce(1).write.parquet(f"{tmp_path}/s")
    source = lambda: spark.readStream.schema("id long, sig array<bigint>, arrived timestamp").parquet(f"{tmp_path}/s")
    streams.to_memory(streams.deduplicated(source()).select("id"), "dedup")
    assert sorted(r.id for r in spark.table("dedup").collect()) == [1, 3]
    labels = spark.createDataFrame([(1, 1, 0)], "doc_id long, quality int, toxic int")
    streams.to_memory(streams.with_labels(source(), labels).select("id"), "labelled")
    assert [r.id for r in spark.table("labelled").collect()] == [1]
    side = lambda: source().withWatermark("arrived", "1 hour").select("id", F.col("arrived").alias("at"), F.md5(F.col("sig").cast("string")).alias("code"))
    streams.to_memory(streams.equal_codes_within(side(), side()).where("id1 < id2").select("id1", "id2"), "met")
    assert [tuple(r) for r in spark.table("met").collect()] == [(1, 2)]
