"""Sources, stores, encoders, streams and experiments that have no SQL beside them."""

import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from sketchlearn.functions import bbit, minwise, sets, surface
from sketchlearn.functions.hashing import PRIME, Affine, StoredPermutations, TwoUniversal, mersenne_values
from sketchlearn.operators import learn, neighbors, projections, skew
from sketchlearn.plans import experiments, relational, workloads
from sketchlearn.sources import params, shared, tables
from sketchlearn.streaming import streams

SF = "/root/testdata/sf0.001"


def test_arrow_items_are_those_of_the_expressions(spark, monkeypatch):
    texts = ["The quick, brown fox", "", None, "a a a", "É ñandú ß 日本 x1", "one", "w " * 30 + "z y x"]
    df = spark.createDataFrame(list(enumerate(texts)), "id long, text string")
    want = {r.id: sorted(r.items) for r in df.select("id", sets.hash_items(sets.shingles(F.col("text"))).alias("items")).collect()}
    assert {r.id: list(r.items) for r in sets.text_items(df, "text").collect()} == want
    monkeypatch.setattr(sets, "WORDS_AT_ONCE", 4)
    assert all(sets.gram_numbers(t.lower().replace(",", "").encode()).tolist() == want[i] for i, t in enumerate(texts) if t)


def test_shifted_values_are_those_of_the_division():
    rng = np.random.default_rng(1)
    t, c1, c2 = rng.integers(0, 1 << 30, 5000), rng.integers(0, PRIME, 40), rng.integers(1, PRIME, 40)
    t[:3], c1[:2], c2[:2] = [0, 1, (1 << 30) - 1], [PRIME - 1, 0], [PRIME - 1, 1]
    want = (c1[:, None] + c2[:, None] * t) % PRIME % (1 << 30)
    assert (mersenne_values(t[None], c1[:, None], c2[:, None], 1 << 30) == want).all()
    assert Affine(3).numpy(np.array([5]), np.array([PRIME - 5]), np.array([1]))[0] == 0


@pytest.mark.parametrize("at_once", [1 << 18, 7])
def test_row_sketches_equal_the_long_ones(spark, monkeypatch, at_once):
    monkeypatch.setattr(projections, "AT_ONCE", at_once)
    rows = [(1, [3, 9, 100], [1.0, 2.0, -1.5]), (2, [], []), (3, list(range(40)), [0.5] * 40), (4, None, None)]
    df = spark.createDataFrame(rows, "id long, i array<long>, v array<double>")
    long = df.select("id", F.explode(F.arrays_zip("i", "v")).alias("x")).select("id", "x.i", "x.v")
    for signed, s in ((True, 1.0), (True, 3.0), (False, 1.0)):
        want = {(r.id, r.bucket): round(r.val, 9) for r in projections.bucket_sum(long, 16, signed, s).collect()}
        assert {(r.id, r.bucket): round(r.val, 9) for r in projections.bucket_sketch(df, "i", 16, "v", signed, s).collect()} == want
    for kind, s in (("sign", 1.0), ("sparse", 3.0), ("normal", 3.0)):
        want = {(r.id, r.j): r.v for r in projections.project(long, 5, kind, s).collect()}
        for r in projections.projection_sketch(df, "i", "v", 5, kind, s).collect():
            assert r.v == pytest.approx([want.get((r.id, j), 0.0) for j in range(5)])


def test_remembered_entries_survive_clashes():
    asked = []

    def make(i):
        asked.append(len(i))
        return np.stack([i * 2.0], axis=1)

    m = projections.Remembered(make, 1, 8)
    x = np.arange(1000)
    assert (m(x)[:, 0] == 2 * x).all() and (m(x)[:, 0] == 2 * x).all() and (m(x[:3])[:, 0] == 2 * x[:3]).all()


def test_solver_for_all_penalties_equals_the_single_ones():
    rng = np.random.default_rng(3)
    idx, y = [np.sort(rng.choice(40, 6, replace=False)) for _ in range(120)], rng.choice([-1.0, 1.0], 120)
    x, cs = learn.SparseRows(idx, None, 40), np.array([0.1, 1.0])
    for loss in ("hinge", "logistic"):
        w = learn.dual_coordinate_all(x, y, cs, loss, epochs=400, tol=1e-7)
        for j, c in enumerate(cs):
            one = learn.dual_coordinate(x, y, c, loss, epochs=400, tol=1e-7)
            objective = lambda v, c=c, loss=loss: v @ v / 2 + c * sum(max(0, 1 - m) if loss == "hinge" else np.log1p(np.exp(-m)) for m in y * x.margins(v))
            assert objective(w[:, j]) == pytest.approx(objective(one), rel=1e-3)


def test_stores_and_files(spark, tmp_path):
    codes = spark.createDataFrame([(2, 8, 2, bytearray(b"\x01\x02")), (1, 8, 2, bytearray(b"\x03\x04"))], "id bigint, b int, k int, code binary")
    tables.write_codes(codes.coalesce(1), f"{tmp_path}/codes")
    assert [r.id for r in tables.read_codes(spark, f"{tmp_path}/codes").collect()] == [1, 2]
    model = spark.createDataFrame([("svm", 3, 0.5)], "cell string, idx bigint, w double")
    tables.save_model(model, f"{tmp_path}/model")
    assert tables.load_model(spark, f"{tmp_path}/model").collect() == model.collect()
    df = spark.createDataFrame([(1, "a"), (2, "b")], "id long, name string")
    for kind in ("csv", "json", "orc", "parquet"):
        tables.write_any(df, f"{tmp_path}/{kind}", kind)
        assert sorted(map(tuple, tables.read_any(spark, f"{tmp_path}/{kind}", kind, "id long, name string").collect())) == [(1, "a"), (2, "b")]


def test_parameter_source(spark):
    rows = {r.j: (r.c1, r.c2) for r in params.read(spark, 5, seed=9).collect()}
    assert [rows[j] for j in range(5)] == TwoUniversal(5, seed=9).numbers()


def test_small_tables_only(spark):
    with pytest.raises(ValueError):
        relational.all_pairs(spark.range(11), "id", 10)
    assert relational.all_pairs(spark.range(10), "id", 10).count() == 45


def test_spread_join_equals_the_plain_one(spark, monkeypatch):
    monkeypatch.setattr(skew, "LEAST_HEAVY", 3)
    left = spark.createDataFrame([(i, 1 if i < 30 else i % 7) for i in range(60)] + [(99, None)], "id long, k long")
    right = spark.createDataFrame([(1, "a"), (2, "b"), (9, "c")], "k long, v string")
    for how in ("left", "inner"):
        want = sorted((r.id, r.v) for r in left.join(right, "k", how).collect())
        assert sorted((r.id, r.v) for r in skew.spread_join(left, right, "k", how).select("id", "v").collect()) == want


def test_exact_pairs_equal_brute_force(spark):
    rng = np.random.default_rng(6)
    base = [set(rng.choice(300, 30).tolist()) for _ in range(8)]
    rows = {10 * i + j: sorted(b - set(rng.choice(sorted(b), j).tolist())) for i, b in enumerate(base) for j in range(5)}
    r = lambda a, b: len({*a} & {*b}) / len({*a} | {*b})
    want = sorted((a, b) for a in rows for b in rows if a < b and r(rows[a], rows[b]) >= 0.8)
    got = neighbors.exact_pairs(spark.createDataFrame(list(rows.items()), "id long, items array<long>"), 0.8).collect()
    assert sorted((x.id1, x.id2) for x in got) == want and want


@pytest.mark.parametrize("groups", [1, 3, 50])
def test_meetings_lose_no_pair_and_drop_chance_ones(groups, monkeypatch):
    monkeypatch.setattr(neighbors, "MEETINGS", 50)
    rng = np.random.default_rng(groups)
    base = [rng.choice(100_000, n, replace=False) for n in (5, 12, 40, 150, 400)]
    base = [np.concatenate([b, [200_000, 200_001]]) for b in base]  # two items that all sets hold first
    rows = [np.unique(np.concatenate([rng.permutation(b)[: len(b) - int(rng.integers(0, 1 + len(b) // 6))], [200_000, 200_001]])) for b in base for _ in range(12)]
    order = lambda x: np.concatenate([x[x >= 200_000], x[x < 200_000]])
    heads = [order(x)[: len(x) - int(np.ceil(0.8 * len(x) - 1e-9)) + 1] for x in rows]
    r = lambda a, b: len(np.intersect1d(a, b)) / len(np.union1d(a, b))
    want = {(i, j) for i in range(60) for j in range(i + 1, 60) if r(rows[i], rows[j]) >= 0.8}
    got = set()
    for g in range(groups):
        some = [i for i in range(60) if (heads[i] % groups == g).any()]
        l, r2 = neighbors.meeting(np.array(some, np.int64), np.array([len(rows[i]) for i in some], np.int64), [heads[i][heads[i] % groups == g].astype(np.uint32).tobytes() for i in some], 0.8, groups)
        got |= set(zip(l.tolist(), r2.tolist(), strict=True))
    assert want <= got
    if groups == 1:  # 150 and 400 items: pairs that have only the two first items in common do not leave
        assert not any(i // 12 != j // 12 for i, j in got if min(i, j) >= 36)


def test_near_pairs_recall_does_not_join_chance_meetings(spark, monkeypatch):
    joined = []
    plain = neighbors.verified
    monkeypatch.setattr(neighbors, "verified", lambda pairs, *more: joined.append(pairs.count()) or plain(pairs, *more))
    rng = np.random.default_rng(5)
    rows = [(i, sorted([*range(3), *(1000 + rng.choice(10**6, 9000, replace=False)).tolist()])) for i in range(12)]  # larger than 4,096 bits tell apart
    monkeypatch.setattr(neighbors, "bucket_counts", lambda sets: np.zeros(neighbors.BUCKETS, np.uint16))
    assert neighbors.exact_pairs(spark.createDataFrame(rows, "id long, items array<long>"), 0.8).count() == 0 and joined == [0]


def test_bucket_counts_count_all_sets(spark):
    df = spark.createDataFrame([(i, [7, i + 100]) for i in range(300)], "id long, items array<long>")
    n = neighbors.bucket_counts(df.repartition(3))
    assert n.sum() == 600 and n[neighbors._buckets(np.array([7], np.int64))[0]] >= 300


def test_library_join_agrees_with_exact_pairs(spark):
    rows = [(1, [1, 2, 3, 4]), (2, [1, 2, 3, 4, 5]), (3, [9, 10])]
    df = spark.createDataFrame(rows, "id long, active array<long>").withColumn("features", bbit.to_vector(F.col("active"), 20))
    got = neighbors.library_join(df, 0.7, 10).selectExpr("datasetA.id a", "datasetB.id b", "distance").collect()
    assert [(x.a, x.b, round(x.distance, 6)) for x in got] == [(1, 2, 0.2)]


def test_encoders_and_table_functions(spark, tmp_path):
    surface.register(spark)
    images = [r.image for r in spark.sql("select * from stored_permutation(0, 50, 7)").collect()]
    assert sorted(images) == list(range(50))
    df = spark.createDataFrame([(1, [3, 4, 900]), (2, []), (3, None)], "id long, items array<bigint>")
    buckets = {r.id: r.features.toArray() for r in surface.SignedBucketEncoder(k=8).transform(df).collect()}
    want = np.zeros(8)
    for r in projections.bucket_sum(df.select("id", F.explode("items").alias("i"), F.lit(1.0).alias("v")), 8).collect():
        want[r.bucket] = r.val
    assert (buckets[1] == want).all() and not buckets[2].any() and not buckets[3].any()
    stage = surface.ProjectionEncoder(k=4)
    stage.write().overwrite().save(f"{tmp_path}/stage")
    out = surface.ProjectionEncoder.load(f"{tmp_path}/stage").transform(df).first()
    assert out.features.toArray() == pytest.approx(projections.projection_sketch(df.limit(1).withColumn("v", F.array(*[F.lit(1.0)] * 3)), "items", "v", 4).first().v)


def test_learner_goes_on_from_its_folder(spark, tmp_path):
    batch = lambda a: spark.createDataFrame([(1 if i % 2 else -1, [i % 2, 2 + i % 3]) for i in range(a)], "y int, active array<bigint>")
    one = streams.OnlineLearner(5, 1.0, folder=f"{tmp_path}/w", spark=spark)
    one(batch(40), 0)
    one(batch(60), 1)
    again = streams.OnlineLearner(5, 1.0, folder=f"{tmp_path}/w", spark=spark)
    assert again.seen == 100 and (again.w == one.w).all()
    again(batch(60), 1)  # a batch run twice counts once
    assert again.seen == 100


def test_late_rows_sessions_and_running_sums(spark, tmp_path):
    # A row is late by the watermark of the batch before last, so a batch on time stands between.
    rows = [(1, "2024-01-01 00:00:00"), (1, "2024-01-05 00:00:00")], [(2, "2024-01-06 00:00:00")], [(1, "2024-01-01 01:00:00"), (2, "2024-01-08 00:00:00")]
    for part in rows:
        time.sleep(1.1)  # files are read in the order of their times
        spark.createDataFrame([(u, t, u) for u, t in part], "id long, ts string, t long").selectExpr("id", "cast(ts as timestamp) ts", "t").coalesce(1).write.mode("append").parquet(f"{tmp_path}/e")
    source = spark.readStream.schema("id long, ts timestamp, t long").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/e").withWatermark("ts", "1 hour")
    q = streams.to_memory(relational.tumbling(source), "late_out")
    assert streams.late_rows(q) == 1
    streams.to_memory(relational.sessions(source), "sessions_out")
    assert spark.table("sessions_out").count() >= 2
    long = spark.readStream.schema("id long, ts timestamp, t long").parquet(f"{tmp_path}/e").select("id", F.col("t").alias("i"), F.lit(1.0).alias("v"))
    streams.to_memory(streams.running_buckets(long, 4), "sums", "complete")
    assert {r.id: abs(r.val) for r in spark.table("sums").collect()} == {1: 3.0, 2: 2.0}


def test_experiments_score_all_test_rows(spark, monkeypatch):
    rows = experiments.labelled_rows(spark, SF)
    tests = rows.where("part = 'test'").count()
    monkeypatch.setattr(experiments, "MAX_TRAIN", 40)
    cells = [experiments.Cell("bbit", 30, 8), experiments.Cell("signed_bucket", 256), experiments.Cell("raw"), experiments.Cell("minwise", 30, 64), experiments.Cell("stacked", 30, 16, 64)]
    out = experiments.run_cells(spark, rows, cells, (0.1, 1.0), "hinge").collect()
    assert len(out) == 10 and all(r.n_test == tests and r.n_train == 40 and 0 <= r.auc <= 1 for r in out)


def test_families_learn_alike(spark):
    got = {(r.family, r.loss, r.k): r for r in experiments.permutation_vs_universal_accuracy(spark, SF, runs=6).collect()}
    assert len(got) == 8 and all(r.runs == 6 for r in got.values())
    assert all(abs(got["permutation", loss, 50].accuracy - got["two_universal", loss, 50].accuracy) < 0.1 for loss in ("hinge", "logistic"))


def test_families_learn_from_all_training_rows(spark, monkeypatch):
    result = lambda: sorted(map(tuple, experiments.permutation_vs_universal_accuracy(spark, SF, runs=2).collect()))
    want, seen = result(), []
    monkeypatch.setattr(experiments, "MAX_TRAIN", 10)
    for name, v in (("RUNS_AT_ONCE", 1), ("HELD_ROWS", 20)):
        monkeypatch.setattr(experiments, name, v, raising=False)
        seen.append(result())
    assert all([x[:4] for x in got] == [x[:4] for x in want] and np.allclose([x[4] for x in got], [x[4] for x in want], atol=0.02) for got in seen)


@pytest.mark.parametrize("loss", ["hinge", "logistic"])
def test_runs_learned_together_equal_those_learned_alone(loss):
    rng = np.random.default_rng(3)
    y = np.where(rng.random(200) < 0.5, 1.0, -1.0)
    codes = np.where(rng.random((200, 3, 8)) < 0.3, (y[:, None, None] > 0) * 3, rng.integers(0, 16, (200, 3, 8))).astype(np.uint8)
    w = learn.dual_coordinate_runs(codes, y, 16, 1.0, loss)
    for r in range(3):
        rows = learn.SparseRows(list(np.arange(8) * 16 + 15 - codes[:, r].astype(int)), None, 8 * 16)
        assert np.abs(w[r] - learn.dual_coordinate(rows, y, 1.0, loss, epochs=200, tol=1e-6)).max() < 0.05


def test_bands_find_nearly_all_near_pairs(spark):
    r = workloads.near_pairs_recall(spark, SF).first()
    assert r.found >= 0.9 * r.pairs and r.pairs > 0


def test_empty_and_long_sets():
    assert len(sets.gram_numbers(b"")) == 0
    one = minwise.numpy_signature(np.arange(200_000), *(np.array(x) for x in zip(*TwoUniversal(4).numbers(), strict=True)), TwoUniversal(4))
    assert (one >= 0).all() and one.dtype == np.int64


def test_vector_table_equals_the_column(spark):
    df = spark.createDataFrame([(1, [5, 3, 5]), (2, [])], "id long, active array<long>")
    want = {r.id: r.v for r in df.select("id", bbit.to_vector(F.col("active"), 9).alias("v")).collect()}
    assert {r.id: r.features for r in bbit.vector_table(df, F.col("active"), 9).collect()} == want


def test_written_folders_can_be_removed(spark, monkeypatch):
    monkeypatch.setattr(shared, "_made", [])
    df = shared.written(spark.range(3).toDF("x"))
    assert df.count() == 3 and shared.remove_written(spark) == 1 and shared.remove_written(spark) == 0
    with pytest.raises(Exception):
        spark.read.parquet(df.inputFiles()[0])


def test_stored_permutations_have_a_bound():
    with pytest.raises(ValueError):
        StoredPermutations(1, 1 << 40)
