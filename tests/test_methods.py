import hashlib
import itertools
import math
from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from sketchlearn.functions import bbit, digests, minwise, sets, similarity, surface
from sketchlearn.functions.hashing import Affine, MersenneTwoUniversal, MultiplyShift, StoredPermutations, TwoUniversal, WideTwoUniversal
from sketchlearn.operators import cost, evaluate, expand, graph, learn, neighbors, projections
from sketchlearn.sources import tables

SF = "/root/testdata/sf0.001"


def value(spark, col):
    return spark.range(1).select(col.alias("x")).first().x


def test_md5_rule(spark):
    got = [value(spark, sets.md5_number(F.lit(g), sets.RANGE)) for g in ("a", "the", "the of")]
    assert got == [463212315, 115210646, 294683844]


def test_two_universal_values():
    t = np.array([1, 10, 100, 1000])
    assert TwoUniversal(1).numpy(t, np.int64(1000000007), np.int64(123456789)).tolist() == [49714972, 87084250, 460777025, 976479304]


def test_worked_example(spark):
    sig = F.array(*(F.lit(x).cast("long") for x in (12013, 25964, 20191)))
    assert value(spark, bbit.truncate(sig, 2)) == [1, 0, 3]
    assert value(spark, bbit.expand(bbit.truncate(sig, 2), 2)) == [2, 7, 8]


@given(st.lists(st.integers(0, (1 << 30) - 1), min_size=1, max_size=50))
@settings(max_examples=30, deadline=None)
def test_mersenne_equals_plain(items):
    t, f, g = np.array(items, np.int64), TwoUniversal(8), MersenneTwoUniversal(8)
    c1, c2 = (np.array(x, np.int64)[:, None] for x in zip(*f.numbers(), strict=True))
    assert (f.numpy(t[None], c1, c2) == g.numpy(t[None], c1, c2)).all()


def test_wide_family_equals_big_integers():
    f = WideTwoUniversal(5)
    t = np.array([0, 1, 2**60 + 12345, 2**61 - 2, 987654321987654321], np.int64)
    for a, b in f.numbers():
        assert f.numpy(t, a, b).tolist() == [(a + b * int(x)) % f.p % f.range for x in t]


def test_multiply_shift_range():
    f = MultiplyShift(3)
    c1, c2 = (np.array(x, np.uint64)[:, None] for x in zip(*f.numbers(), strict=True))
    z = f.numpy(np.arange(1000)[None], c1, c2)
    assert z.min() >= 0 and z.max() < 1 << 30 and len(np.unique(z[0])) > 990


def test_shapes_agree_and_empty_set_is_null(spark):
    df = spark.createDataFrame([(1, [5, 9, 70]), (2, [7]), (3, []), (4, list(range(3000)))], "id long, items array<bigint>")
    f = TwoUniversal(20)
    out = {s: {r.id: r.sig for r in minwise.signature(df, f, shape=s).collect()} for s in ("array", "arrow", "grouped")}
    assert out["array"] == out["arrow"] and out["array"][3] is None
    assert out["grouped"] == {k: v for k, v in out["array"].items() if v is not None}


def test_collision_probability_over_all_permutations():
    s1, s2 = {0, 1, 2}, {2, 3}
    hit = sum(min(p[t] for t in s1) == min(p[t] for t in s2) for p in itertools.permutations(range(6)))
    assert Fraction(hit, math.factorial(6)) == Fraction(1, 4)


def test_stored_permutation_is_a_bijection(spark):
    rows = StoredPermutations(3, 50).table(spark).collect()
    for j in range(3):
        assert sorted(r.image for r in rows if r.j == j) == list(range(50))


def test_merged_signature_is_that_of_the_union(spark):
    f, a, b = TwoUniversal(16), [1, 5, 9], [5, 1000, 7]
    df = spark.createDataFrame([(a, b, sorted({*a, *b}))], "a array<bigint>, b array<bigint>, u array<bigint>")
    r = df.select(minwise.merged(minwise.signature_column(F.col("a"), f), minwise.signature_column(F.col("b"), f)).alias("m"), minwise.signature_column(F.col("u"), f).alias("u")).first()
    assert r.m == r.u


@pytest.mark.parametrize(("r1", "r2", "b", "want"), [(0.25, 0.5, 1, (0.428571, 0.333333, 0.396825, 0.365079)), (0.25, 0.5, 2, (0.154286, 0.066667, 0.125079, 0.095873)), (0.1, 0.1, 4, (0.025272,) * 4)])
def test_constants(spark, r1, r2, b, want):
    c = similarity.constants(F.lit(r1 * 1000), F.lit(r2 * 1000), 1000, b)
    assert [round(value(spark, c[n]), 6) for n in ("a1", "a2", "c1", "c2")] == pytest.approx(want, abs=2e-6)


def test_full_set_and_tiny_sets(spark):
    assert value(spark, similarity.constants(F.lit(10.0), F.lit(10.0), 10, 1)["a1"]) == 0
    tiny = value(spark, similarity.constants(F.lit(1.0), F.lit(1.0), 2.0**64, 8)["a1"])
    assert tiny == pytest.approx(1 / 256)


def test_variances(spark):
    r, f = F.lit(1 / 3), F.lit(1.0)
    assert value(spark, similarity.var_minwise(r, 100)) == pytest.approx(0.00222222, abs=1e-8)
    for b, want in ((1, 0.00888889), (2, 0.00444444), (8, 0.00224837)):
        assert value(spark, similarity.var_bbit(r, f, f, 1, b, 100, "sparse")) == pytest.approx(want, abs=1e-8)


def test_projection_variances(spark):
    u1, u2, k = [1, 2, 0, 3], [2, 0, 1, 1], 4
    m1, m2, a, q = (F.lit(float(x)) for x in (sum(x * x for x in u1), sum(x * x for x in u2), 5, sum(x * x * y * y for x, y in zip(u1, u2))))
    assert value(spark, projections.var_rp(m1, m2, a, q, 1, k)) == 20.75 == value(spark, projections.var_signed(m1, m2, a, q, 1, k))
    assert value(spark, projections.var_rp(m1, m2, a, q, 3, k)) == 27.25
    assert value(spark, projections.var_signed(m1, m2, a, q, 3, k)) == 46.75
    assert value(spark, projections.expected_bucket(F.lit(6.0), F.lit(4.0), a, k)) == 9.75


def test_signed_bucket_mean_and_variance_by_enumeration():
    u1, u2, est = (1, 2, 0, 3), (2, 0, 1, 1), []
    for h in itertools.product(range(4), repeat=4):
        for s in itertools.product((-1, 1), repeat=4):
            g1, g2 = np.zeros(4), np.zeros(4)
            for i in range(4):
                g1[h[i]] += s[i] * u1[i]
                g2[h[i]] += s[i] * u2[i]
            est.append(g1 @ g2)
    assert np.mean(est) == 5 and np.var(est) == 20.75


@given(st.sampled_from(bbit.WIDTHS), st.integers(1, 40), st.integers(0, 2**32))
@settings(max_examples=40, deadline=None)
def test_pack_round_trip(b, k, seed):
    code = np.random.default_rng(seed).integers(0, 1 << b, k)
    raw = bbit.pack_numpy(code, b)
    assert len(raw) == -(-b * k // 8) and (bbit.unpack_numpy(raw, b, k) == code).all()


def test_expansion_is_limited_to_16_bits():
    with pytest.raises(ValueError):
        bbit.check_width(17)
    with pytest.warns(UserWarning):
        Affine(1, range=1000).check(518)


def test_inner_product_of_expanded_codes_counts_matches(spark):
    df = spark.createDataFrame([([1, 2, 3, 0], [1, 3, 3, 1])], "a array<int>, b array<int>")
    r = df.select(F.size(F.array_intersect(bbit.expand(F.col("a"), 2), bbit.expand(F.col("b"), 2))).alias("dot"), similarity.matches(F.col("a"), F.col("b")).alias("m")).first()
    assert r.dot == r.m == 2


def toy(n=400, dims=60, seed=1):
    rng = np.random.default_rng(seed)
    true = rng.standard_normal(dims)
    idx = [np.sort(rng.choice(dims, 8, replace=False)) for _ in range(n)]
    y = np.array([1.0 if true[i].sum() >= 0 else -1.0 for i in idx])
    return learn.SparseRows(idx, None, dims), y


@pytest.mark.parametrize("loss", ["hinge", "logistic"])
def test_dual_solver_reaches_the_minimum(loss):
    x, y = toy()
    w = learn.dual_coordinate(x, y, 1.0, loss, epochs=300, tol=1e-6)

    def objective(w):
        m = y * x.margins(w)
        return w @ w / 2 + (np.maximum(1 - m, 0) if loss == "hinge" else np.logaddexp(0, -m)).sum()

    rng = np.random.default_rng(0)
    best = objective(w)
    assert all(objective(w + 1e-2 * rng.standard_normal(len(w))) > best - 1e-6 for _ in range(20))
    assert (np.sign(x.margins(w)) == y).mean() > 0.95


def test_solvers_agree_with_the_library(spark):
    x, y = toy(200, 30)
    rows = spark.createDataFrame([(i, int(v), a.tolist()) for i, (v, a) in enumerate(zip(y, x.idx))], "id long, y int, active array<bigint>")
    vectors = rows.select(((F.col("y") + 1) / 2).alias("label"), bbit.to_vector(F.col("active"), 30).alias("features"))
    lib = learn.fit_mllib(vectors, 1.0, "logistic", max_iter=200).coefficients.toArray()
    assert np.abs(lib - learn.dual_coordinate(x, y, 1.0, "logistic", epochs=300, tol=1e-7)).max() < 0.02
    w = learn.averaged_sgd(rows, 30, 1.0, "hinge", epochs=5, parts=2)
    assert (np.sign(x.margins(w)) == y).mean() > 0.85
    scored = learn.score_codes(rows, w).collect()
    assert np.allclose([r.score for r in scored], [w[r.active].sum() for r in scored])


def test_one_class_and_zero_score(spark):
    x, _ = toy(20)
    w = learn.dual_coordinate(x, np.ones(20), 1.0)
    assert (x.margins(w) > 0).all()
    long = spark.createDataFrame([(1, 1, 0, 1.0)], "id long, y int, idx long, v double")
    assert learn.predict(long, spark.createDataFrame([(0, 0.0)], "idx long, w double")).first().pred == 1


def test_auc_and_report(spark):
    y, s = np.array([1, -1, 1, -1, 1]), np.array([0.9, 0.1, 0.4, 0.4, 0.8])
    assert evaluate.auc(s, y) == pytest.approx(5.5 / 6)
    df = spark.createDataFrame([(int(a), float(b), 1 if b >= 0.5 else -1) for a, b in zip(y, s)], "y int, score double, pred int")
    r = evaluate.binary_report(df).first()
    assert (r.tp, r.fp, r.fn, r.tn) == (2, 0, 1, 2) and r.auc == pytest.approx(5.5 / 6)


@pytest.mark.parametrize(("nodes", "pairs"), [(1_000_000, 200_000), (1, 0), (5, 10)])
def test_components(spark, monkeypatch, nodes, pairs):
    monkeypatch.setattr(graph, "TASK_NODES", nodes)
    monkeypatch.setattr(graph, "LOCAL_PAIRS", pairs)
    edges = [(i, i + 1) for i in range(40)] + [(100, 101), (102, 101), (200, 200)]
    got = {r.node: r.root for r in graph.connected_components(spark.createDataFrame(edges, "src long, dst long")).collect()}
    assert {got[i] for i in range(41)} == {0} and got[102] == 100 and got[200] == 200


def test_storage():
    assert cost.bits_bbit(677_399, 16, 500) // 8 == pytest.approx(677e6, rel=0.01)
    assert cost.train_bytes(338_700, 1 << 15) == pytest.approx(44e9, rel=0.02)
    assert cost.params_permutations(500, 10**9) * 8 == 4 * 10**12


def test_expansion_counts(spark):
    df = spark.createDataFrame([(1, list(range(10))), (2, [])], "id long, items array<bigint>")
    assert expand.feature_products(df).count() == 10 + 45
    assert expand.feature_products(df, triple_rate=1).count() == 10 + 45 + 120


def test_files_round_trip(spark, tmp_path):
    df = spark.createDataFrame([(1, [0, 5]), (-1, [2])], "y int, active array<bigint>")
    tables.write_libsvm(df, f"{tmp_path}/svm")
    back = sorted((r.label, r.features.indices.tolist()) for r in tables.read_libsvm(spark, f"{tmp_path}/svm", 8).collect())
    assert back == [(-1.0, [2]), (1.0, [0, 5])]
    wide = spark.createDataFrame([(1, [1 << 33])], "y int, active array<bigint>")
    tables.write_libsvm(wide, f"{tmp_path}/wide")
    assert spark.read.text(f"{tmp_path}/wide").first().value == f"1 {(1 << 33) + 1}:1"


def test_map_only_signature_has_no_exchange(spark):
    docs = tables.load_table(spark, SF, "documents").select(F.col("doc_id").alias("id"), sets.hash_items(sets.shingles(F.col("text"))).alias("items"))
    plan = minwise.signature(docs, TwoUniversal(16), shape="array")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Python" not in plan


def test_sql_surface(spark):
    surface.register(spark)
    r = spark.sql("select minwise(array(1L, 2L, 3L)) as s, bbit(array(12013L, 25964L, 20191L), 2) as c, resemblance(array(1L, 2L), array(2L, 3L)) as r").first()
    assert len(r.s) == 16 and r.c == [1, 0, 3] and r.r == pytest.approx(1 / 3)
    assert [x.idx for x in spark.sql("select * from explode_code(array(1, 0, 3), 2)").collect()] == [2, 7, 8]
    out = surface.BBitEncoder(k=4, b=2).transform(spark.createDataFrame([(1, [3, 4])], "id long, items array<bigint>")).first()
    assert out.features.size == 16 and out.features.values.sum() == 4


@pytest.mark.parametrize("block", [1024, 3])
def test_near_pairs_are_all_pairs_of_a_bucket(spark, block, monkeypatch):
    monkeypatch.setattr(neighbors, "BLOCK", block)
    rng = np.random.default_rng(5)
    base = [sorted(rng.choice(5000, 40, replace=False).tolist()) for _ in range(6)]
    sets_ = {1: sorted(rng.choice(5000, 30, replace=False).tolist())}  # like none
    for i, b in enumerate(base):
        for c in range(5):
            sets_[10 * i + c + 2] = sorted({*b[c % 3 :], 6000 + c % 3})
    # A signature is a function of the set; of few values, so that unlike sets share bands and the smallest id of a bucket is no copy.
    sig = {i: [(sum(x) >> j) % 2 for j in range(16)] for i, x in sets_.items()}
    df = spark.createDataFrame([(i, x, sig[i]) for i, x in sets_.items()] + [(99, [], None)], "id long, items array<long>, sig array<long>")
    shares = lambda a, b: any(sig[a][2 * k : 2 * k + 2] == sig[b][2 * k : 2 * k + 2] for k in range(8))
    r = lambda a, b: len({*sets_[a]} & {*sets_[b]}) / len({*sets_[a]} | {*sets_[b]})
    want = sorted((a, b, sum(x == y for x, y in zip(sig[a], sig[b], strict=True)), round(r(a, b), 9)) for a, b in itertools.combinations(sorted(sets_), 2) if r(a, b) >= 0.8 and shares(a, b))
    got = sorted((x.id1, x.id2, x.matches, round(x.r, 9)) for x in neighbors.near_pairs(df, 8, 2, 0.8).collect())
    assert got == want and len(want) > 10
    root = {}
    for x in neighbors.clusters(neighbors.near_links(df, 8, 2, 0.8)).collect():
        root[x.id] = x.cluster_id
    assert root == {x.node: x.root for x in graph.connected_components(spark.createDataFrame([w[:2] for w in want], "src long, dst long")).collect()}


def test_sizes_of_products_equal_the_products(spark):
    rng = np.random.default_rng(3)
    wide = [sorted({int(10 ** rng.uniform(0, 7)) - 1 for _ in range(12)}) for _ in range(20)]
    rows = [(i, x) for i, x in enumerate([*wide, [], [5], [1, 2], [-7, 3, 4, 9_999_999], [1, 10**12, 5, 77], list(range(70))])]
    df = spark.createDataFrame(rows, "id long, items array<long>")
    for rate in (1, 3):
        want = {r.id: r["count"] for r in expand.feature_products(df, triple_rate=rate).groupBy("id").count().collect()}
        assert {r.id: r.f for r in expand.product_sizes(df, rate).collect()} == want


def test_digests_of_many_texts():
    texts = [bytes(range(1, n + 1)) for n in range(digests.ONE_BLOCK + 1)]
    block = np.zeros((len(texts), 64), np.uint8)
    for i, t in enumerate(texts):
        block[i, : len(t)] = np.frombuffer(t, np.uint8)
    want = [int(hashlib.md5(t).hexdigest()[:13], 16) for t in texts]
    assert digests.md5_upper(block, np.array([len(t) for t in texts])).tolist() == want


def test_texts_hashed_together_equal_each_by_itself(monkeypatch):
    monkeypatch.setattr(sets, "WORDS_AT_ONCE", 50)
    rng = np.random.default_rng(5)
    texts = [b" ".join(b"w%d" % (10 ** rng.integers(0, 9)) for _ in range(n)) for n in (0, 1, 2, 3, 20, 45, 0, 30, 60, 130)] + [b"x" * 60 + b" y \xc3\xa9 " + b"z" * 54, b"  a  a a ", b""]
    for n, modulus in (((1, 2, 3), sets.RANGE), ((2,), 97)):
        flat, counts = sets.many_gram_numbers(texts, n, modulus)
        want = [sorted({int(hashlib.md5(b" ".join(w[i : i + k])).hexdigest()[:13], 16) % modulus for k in n for i in range(len(w) - k + 1)}) for w in (t.split() for t in texts)]
        assert np.split(flat, np.cumsum(counts)[:-1])[3].tolist() == want[3]
        assert [x.tolist() for x in np.split(flat, np.cumsum(counts)[:-1])] == want
    assert sets.many_gram_numbers([])[0].tolist() == []
