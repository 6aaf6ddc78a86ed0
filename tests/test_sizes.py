"""Queries as they run over larger tables: what they read, ties of rounding, and shapes that stay small."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from sketchlearn.functions import hashing, minwise, sets, similarity
from sketchlearn.functions.hashing import PRIME, AffinePrime, MersenneTwoUniversal, StoredPermutations, TwoUniversal
from sketchlearn.operators import neighbors
from sketchlearn.plans import experiments, workloads
from sketchlearn.sources import shared

from .oracle import SF


@pytest.mark.parametrize("name", ["worked_example", "hash_parameters", "hash_parameters_source", "entry_moments"])
def test_queries_read_a_table(spark, name):
    assert workloads.QUERIES[name](spark, SF).inputFiles()


def test_ties_round_as_in_sql(spark):
    got = [r.x for r in spark.range(2, 3000).select(workloads.near6(F.col("id") / 1_200_000, "x")).collect()]
    want = duckdb.sql("select round(n::DOUBLE / 1200000, 6) as x from range(2, 3000) t(n) order by n").fetchall()
    assert got == [x for (x,) in want]


def test_quick_rounding_equals_the_decimal_one(spark):
    x = [*np.random.default_rng(2).normal(0, 3, 500).tolist(), -1e-9, 0.0, 2.5e7, -3e12, float("nan"), None]
    rows = spark.createDataFrame([(v,) for v in x], "x double").select(workloads.quick6(F.col("x")).alias("a"), F.round("x", 6).alias("b")).collect()
    assert [str(r.a) for r in rows] == [str(r.b) for r in rows]


@pytest.mark.parametrize("block", [512, 2])
def test_common_items_are_counted_in_blocks_without_a_join_of_items(spark, block, monkeypatch):
    for name, v in {"PAIR_BLOCK": block, "PAIRS_COUNTED": 40, "DEALT": 16}.items():
        monkeypatch.setattr(similarity, name, v, raising=False)
    rng = np.random.default_rng(9)
    items = {i: set(rng.choice(40, int(rng.integers(1, 12)), replace=False).tolist()) for i in range(-5, 30)}
    df = shared.written(spark.createDataFrame([(i, t) for i, x in items.items() for t in x] + [(None, 3), (4, None)], "id long, t long"))
    found = similarity.resemblance_pairs(df.where("t is not null"))
    got = {(r.id1, r.id2): (r.f1, r.f2, r.a, r.r) for r in found.collect()}
    want = {(i, j): (len(x), len(y), len(x & y), len(x & y) / len(x | y)) for i, x in items.items() for j, y in items.items() if i < j and x & y}
    assert got == want
    plan = similarity.resemblance_pairs(df)._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapGroupsInArrow" in plan and "SortMergeJoin [t#" not in plan and "(id1#" not in plan.split("FlatMapGroupsInArrow")[-1]


@pytest.mark.parametrize("block", [512, 2])
def test_matches_of_pairs_and_permuted_signatures(spark, block, monkeypatch):
    monkeypatch.setattr(similarity, "PAIR_BLOCK", block)
    rng = np.random.default_rng(4)
    items = {i: sorted(rng.choice(60, 12, replace=False).tolist()) for i in range(-3, 9)} | {20: [70], 21: []}  # 70 has no image
    perms = StoredPermutations(7, 60)
    held = shared.written(spark.createDataFrame(list(items.items()), "id long, items array<long>"))
    want = {i: {} for i in items}
    for r in minwise.signature_by_lookup(held.select("id", F.explode("items").alias("t")), perms).collect():
        want[r.id][r.j] = r.z
    want = {i: [z[j] for j in range(7)] for i, z in want.items() if z}
    monkeypatch.setattr(minwise, "IMAGE_BYTES", 3 * 4 * 60)  # three permutations at a time
    signed = minwise.permuted_signature(held, perms)
    assert {r.id: r.sig for r in signed.collect()} == want
    pairs = shared.written(spark.createDataFrame([(a, b, a * b) for a in items for b in items if a < b], "id1 long, id2 long, x long"))
    found = similarity.pair_matches(pairs, signed, (0, 2))
    got = {(r.id1, r.id2): (r.x, *r.matches) for r in found.collect()}
    same = lambda a, b, m: sum(x & m == y & m for x, y in zip(want[a], want[b], strict=True))
    assert got == {(a, b): (a * b, same(a, b, -1), same(a, b, 3)) for a in want for b in want if a < b}


def test_large_unlike_sets_of_a_bucket_are_told_apart_by_parity(spark):
    rng = np.random.default_rng(8)
    sets_of = [sorted(rng.choice(1 << 30, n, replace=False).tolist()) for n in (700, 1500, 1600, 3000, 3100, 9000)]
    sets_of += [x[: -len(x) // 20] for x in sets_of]  # each has a near copy; widths of parity differ in some
    df = spark.createDataFrame([(i, x, [5] * 16) for i, x in enumerate(sets_of)], "id long, items array<long>, sig array<long>")
    pairs = neighbors.band_candidates(neighbors.described(df, 8, 2), 8, 2, 0.8).collect()
    assert sorted((r.id1, r.id2) for r in pairs) == [(i, i + 6) for i in range(6)]


@pytest.mark.parametrize("family", [512, 2])
def test_near_copies_are_verified_by_family_without_stored_items(spark, family, monkeypatch):
    monkeypatch.setattr(neighbors, "FAMILY", family)
    rng = np.random.default_rng(6)
    base = [sorted(rng.choice(5000, 40, replace=False).tolist()) for _ in range(3)]
    rows = {20 * i + c: sorted({*b[c % 4 :], 6000 + c % 4}) for i, b in enumerate(base) for c in range(12)}
    df = spark.createDataFrame([(i, x, [sum(base[i // 20][:3])] * 16) for i, x in rows.items()], "id long, items array<long>, sig array<long>")
    assert "items" not in neighbors.described(df, 8, 2).columns
    r = lambda a, b: len({*rows[a]} & {*rows[b]}) / len({*rows[a]} | {*rows[b]})
    rep = {i: min(j for j in rows if rows[j] == x) for i, x in rows.items()}
    want = sorted([(a, b, round(r(a, b), 9)) for a in rows for b in rows if a < b and rep[a] == a and rep[b] == b and a // 20 == b // 20 and r(a, b) >= 0.8] + [(rep[i], i, 1.0) for i in rows if rep[i] != i])
    got = neighbors.near_classes(df, 8, 2, 0.8).collect()
    assert sorted((x.id1, x.id2, round(x.r, 9)) for x in got) == want and len(want) > 30
    assert {x.matches for x in got} == {16}


def test_images_of_a_large_dictionary_come_one_at_a_time():
    assert experiments.MOST_WORDS > 1_000_000
    for family in ("permutation", "two_universal"):
        images = experiments.family_images(family, 3, 50, 2_000_000)
        assert iter(images) is images and len(next(images)) == 2_000_000
    a, b = experiments.family_images("permutation", 3, 2, 9)
    rng = np.random.default_rng([7, 3])
    assert a.tolist() == rng.permutation(9).tolist() and b.tolist() == rng.permutation(9).tolist()


@pytest.mark.parametrize("family", [TwoUniversal(7), TwoUniversal(3, 1 << 4), TwoUniversal(3, 1), AffinePrime(5), MersenneTwoUniversal(4, 1 << 20)])
@pytest.mark.parametrize("tile", [1 << 16, 100])
def test_minima_of_many_sets_by_fixed_point(family, tile, monkeypatch):
    monkeypatch.setattr(minwise, "TILE", tile)
    rng = np.random.default_rng(5)
    sizes = np.array([1, 2, 1, 350, 99, 1, 100, 7, 3000])
    flat = rng.integers(0, PRIME + 1, sizes.sum())
    flat[:6] = [0, PRIME, PRIME - 1, 1, 1 << 30, (1 << 30) - 1]
    points = hashing.fixed_point(family)
    want = [[min((a + b * t) % PRIME % family.range for t in s.tolist()) for a, b in family.numbers()] for s in np.split(flat, np.cumsum(sizes)[:-1])]
    assert minwise.many_minima(flat, sizes, points).tolist() == want
    # Every value of a few functions, nearest to and farthest from a wrap: items that give it are found by inversion.
    for j, (a, b) in enumerate(family.numbers()):
        t = np.array([(r - a) * pow(b, -1, PRIME) % PRIME for r in (0, 1, 2, PRIME // 2, PRIME // 2 + 1, PRIME - 2, PRIME - 1)])
        assert minwise.many_minima(t, np.ones(len(t), np.int64), points)[:, j].tolist() == [int((a + b * int(x)) % PRIME % family.range) for x in t]
    assert hashing.fixed_point(hashing.WideTwoUniversal(2)) is None and hashing.fixed_point(TwoUniversal(2, 1000)) is None


@pytest.mark.parametrize("family", [TwoUniversal(7), TwoUniversal(23, 1 << 20), TwoUniversal(3, 1000)])
def test_compiled_minima_equal_those_of_the_other_shapes(spark, family):
    """Each row is a set by itself, also of equal or null ids; no lambda runs over items, and arithmetic stays checked outside."""
    rng = np.random.default_rng(8)
    rows = [(i // 2 if i else None, sorted(rng.choice(1 << 30, n, replace=False).tolist())) for i, n in enumerate([1, 7, 8, 9, 16, 0, 700, 3])]
    df = shared.written(spark.createDataFrame(rows, "id long, items array<long>"))
    key = lambda r: (r.id is None, r.id, r.sig)
    want = sorted((r for r in minwise.signature(df, family, shape="array").select("id", "sig").collect() if r.sig), key=key)
    got = minwise.signature(df, family, shape="compiled")
    assert sorted(got.collect(), key=key) == want and len(want) == 7
    assert sorted((r for r in minwise.signature(df, family).select("id", "sig").collect() if r.sig), key=key) == want
    plan = minwise.signature(df, family, shape="compiled")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and spark.conf.get("spark.sql.ansi.enabled") == "true"


def test_loading_and_preprocessing_hashes_every_item(spark):
    rows = {r.step: r for r in experiments.loading_and_preprocessing(spark, SF, 20).collect()}
    n = sets.documents(spark, SF).select(F.sum(F.size("items"))).first()[0]
    assert [rows[s].hashes for s in ("preprocess_vectorised", "preprocess_row_expression")] == [20 * n, 20 * n] and len(rows) == 5
