"""Variances seen over many seeds beside the theory's, the errors of the hash families, and what large norms do to buckets. Each query has its SQL beside it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import bbit, minwise, sets, similarity
from ..functions.hashing import TwoUniversal
from ..operators import projections
from ..sources.tables import load_table
from .oracles import CPAIRS, EMB, MOM, SUPP, num, sig, union
from .workloads import customer_pairs, id_pairs, r6

#: Seeds of the minwise variances, functions a seed; seeds of the projections; functions and runs of the family error.
SEEDS, SEED_K, PROJECTION_SEEDS, ERROR_K, ERROR_RUNS = 50, 16, range(100, 120), 64, 20
BITS = (0, 1, 2, 4, 8)
#: (method, s, k) of the projections whose variances are measured.
MEASURED = [("rp", 1.0, 8), ("rp", 3.0, 8), ("signed", 1.0, 32), ("signed", 3.0, 32), ("plain", 1.0, 32)]


def _supplier_pairs(spark, d, k: int) -> DataFrame:
    """(id1, id2, i1, i2, s1, s2, r) of suppliers next to each other in id."""
    sup = sets.suppliers(spark, d)
    signed = minwise.signature(sup, TwoUniversal(k))
    side = lambda n: signed.select(F.col("id").alias(f"id{n}"), F.col("items").alias(f"i{n}"), F.col("sig").alias(f"s{n}"))
    return id_pairs(sup).join(side(1), "id1").join(side(2), "id2").withColumn("r", similarity.resemblance(F.col("i1"), F.col("i2")))


def minwise_variance(spark, d):
    """Mean and variance over SEEDS draws of SEED_K functions, of the full-width (b = 0) and the b-bit estimates, and the theory's variance."""
    part = lambda c, run: F.slice(c, run * SEED_K + 1, F.lit(SEED_K))
    cells = []

    def estimate(b: int, low: float):
        cut = lambda c: bbit.truncate(c, b) if b else c
        return lambda run: (similarity.matches(cut(part("s1", run)), cut(part("s2", run))) / SEED_K - low) / (1 - low)

    for b in BITS:
        low = 0.0 if b == 0 else 1.0 / (1 << b)
        theory = similarity.var_minwise(F.col("r"), SEED_K) if b == 0 else similarity.var_bbit(F.col("r"), F.lit(1.0), F.lit(1.0), 1, b, SEED_K, "sparse")
        cells.append(F.struct(F.lit(b).alias("b"), F.transform(F.sequence(F.lit(0), F.lit(SEEDS - 1)), estimate(b, low)).alias("hats"), theory.alias("theory")))
    long = _supplier_pairs(spark, d, SEED_K * SEEDS).select("id1", "id2", "r", F.explode(F.array(*cells)).alias("x")).select("id1", "id2", "r", "x.b", "x.theory", F.explode("x.hats").alias("hat"))
    out = long.groupBy("id1", "id2", "b").agg(F.first("r").alias("r"), F.avg("hat").alias("mean_hat"), F.var_samp("hat").alias("var_seen"), F.first("theory").alias("theory"))
    return out.select("id1", "id2", "b", r6(F.col("r"), "r"), r6(F.col("mean_hat"), "mean_hat"), r6(F.col("var_seen"), "var_seen"), r6(F.col("theory"), "var_theory"))


def projection_variance(spark, d):
    """Mean and variance over seeds of projections and of plain and signed buckets, and the theory's, for vectors next to each other in id."""
    e = load_table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), "embedding")
    dims = e.agg(F.max(F.size("embedding"))).first()[0] or 0
    pairs, long = id_pairs(e), sets.vectors_long(spark, d)
    side = lambda n: e.select(F.col("id").alias(f"id{n}"), F.col("embedding").alias(f"v{n}"))
    seen = projections.seeded_estimates(pairs.join(side(1), "id1").join(side(2), "id2"), "v1", "v2", dims, list(PROJECTION_SEEDS), MEASURED)
    both, m1, m2, a, q, s, k = seen.join(projections.moments(long, pairs), ["id1", "id2"]), *(F.col(x) for x in ("m1", "m2", "a", "q", "s", "k"))
    theory = F.when(F.col("method") == "rp", projections.var_rp(m1, m2, a, q, s, k)).when(F.col("method") == "signed", projections.var_signed(m1, m2, a, q, s, k))
    return both.select("id1", "id2", "method", "s", "k", F.round("a", 3).alias("a_true"), F.round("mean", 3).alias("mean_hat"), F.round("variance", 2).alias("var_seen"), F.round(theory, 2).alias("var_theory"))


def norm_domination(spark, d, k: int = 64, b: int = 8):
    """Customers without a common part: the variance of signed buckets is the product of the sizes over k, however little they share; that of b-bit codes, carried over to the inner product, beside it."""
    pairs = customer_pairs(spark, d).where("a = 0")
    slope = F.col("f1") + F.col("f2")
    codes = similarity.var_bbit(F.col("r"), F.col("f1"), F.col("f2"), 1, b, k, "sparse") * slope * slope
    return pairs.select("id1", "id2", F.round(projections.var_signed_sets(F.col("f1"), F.col("f2"), F.col("a"), k), 6).alias("var_signed"), F.round(codes, 6).alias("var_bbit"))


def family_error(spark, d):
    """Over runs with new functions: the mean bias, its deviation and the mean squared error of two-universal estimates."""
    part = lambda c, run: F.slice(c, run * ERROR_K + 1, F.lit(ERROR_K))
    hats = F.transform(F.sequence(F.lit(0), F.lit(ERROR_RUNS - 1)), lambda run: similarity.matches(part("s1", run), part("s2", run)) / ERROR_K)
    each = _supplier_pairs(spark, d, ERROR_K * ERROR_RUNS).select("id1", "r", F.posexplode(hats).alias("run", "hat")).withColumn("e", F.col("hat") - F.col("r"))
    runs = each.groupBy("run").agg(F.avg("e").alias("bias"), F.avg(F.col("e") * F.col("e")).alias("mse"))
    return runs.agg(F.count(F.lit(1)).alias("runs"), r6(F.avg("bias"), "bias"), r6(F.stddev_samp("bias"), "bias_deviation"), r6(F.avg("mse"), "mse"))


# ---------------------------------------------------------------- SQL

_SPAIRS = f"""{SUPP}, sf as (select id, count(*) as f from supp group by id),
sa as (select x.id as id1, y.id as id2, count(*) as a from supp x join supp y on x.t = y.t and y.id = x.id + 1 group by all),
spairs as (select x.id as id1, y.id as id2, coalesce(a, 0) / (x.f + y.f - coalesce(a, 0)) as r from sf x join sf y on y.id = x.id + 1 left join sa on sa.id1 = x.id)"""


def _match(b: int) -> str:
    return f"(1.0 / {1 << b} + (1 - 1.0 / {1 << b}) * r)"


def _minwise_sql() -> str:
    parts = []
    for b in BITS:
        low = 0.0 if b == 0 else 1.0 / (1 << b)
        same = "x.z = y.z" if b == 0 else f"(x.z & {(1 << b) - 1}) = (y.z & {(1 << b) - 1})"
        theory = f"r * (1 - r) / {SEED_K}" if b == 0 else f"{_match(b)} * (1 - {_match(b)}) / ({SEED_K} * (1 - 1.0 / {1 << b}) * (1 - 1.0 / {1 << b}))"
        hats = f"select id1, id2, x.j // {SEED_K} as run, any_value(r) as r, (count_if({same}) / {SEED_K} - {low}) / (1 - {low}) as hat from spairs join sig x on x.id = id1 join sig y on y.id = id2 and y.j = x.j group by all"
        parts.append(f"select id1, id2, {b}::INT as b, round(any_value(r), 6) as r, round(avg(hat), 6) as mean_hat, round(var_samp(hat), 6) as var_seen, round(any_value({theory}), 6) as var_theory from ({hats}) group by id1, id2")
    return f"with {_SPAIRS}, {sig('supp', SEED_K * SEEDS)} " + union(parts)


def _entry_sql(s: float, text: str) -> str:
    u = f"(({num(text, 1 << 40)} + 0.5::DOUBLE) / {1 << 40})"
    if s == 1.0:
        return f"(case when {u} < 0.5 then -1.0::DOUBLE else 1.0::DOUBLE end)"
    return f"(case when {u} < {1 / (2 * s)!r} then -sqrt({s}) when {u} >= {1 - 1 / (2 * s)!r} then sqrt({s}) else 0.0::DOUBLE end)"


def _projection_sql() -> str:
    ctes = [f"seeds as (select unnest(range({PROJECTION_SEEDS.start}, {PROJECTION_SEEDS.stop})) as seed)", "coords as (select distinct i from u)"]
    parts = []
    for n, (method, s, k) in enumerate(MEASURED):
        if method == "rp":
            entry = _entry_sql(s, "(seed || '|r|' || i || '|' || j)")
            ctes.append(f"m{n} as (select seed, i, j as slot, {entry} as e from seeds, coords, range({k}) r(j))")
            theory = f"(m1 * m2 + a * a + ({s} - 3) * q) / {k}"
        else:
            entry = _entry_sql(s, "(seed || '|r|' || i)") if method == "signed" else "1.0::DOUBLE"
            slot = num("(seed || '|h|' || i)", k)
            ctes.append(f"m{n} as (select seed, i, {slot} as slot, {entry} as e from seeds, coords)")
            theory = f"({s} - 1) * q + (m1 * m2 + a * a - 2 * q) / {k}" if method == "signed" else "null::DOUBLE"
        ctes.append(f"k{n} as (select seed, id, slot, sum(v * e) as w from u join m{n} using (i) group by all)")
        ctes.append(f"h{n} as (select id1, id2, x.seed, sum(x.w * y.w){f' / {k}' if method == 'rp' else ''} as hat from idp join k{n} x on x.id = id1 join k{n} y on y.id = id2 and y.seed = x.seed and y.slot = x.slot group by all)")
        parts.append(f"select id1, id2, '{method}' as method, {s}::DOUBLE as s, {k}::INT as k, round(any_value(a), 3) as a_true, round(avg(hat), 3) as mean_hat, round(var_samp(hat), 2) as var_seen, round(any_value({theory}), 2) as var_theory from h{n} join mom using (id1, id2) group by id1, id2")
    return f"with {EMB}, {MOM}, {', '.join(ctes)} " + union(parts)


_HATS = f"h as (select id1, id2, x.j // {ERROR_K} as run, any_value(r) as r, count_if(x.z = y.z) / {ERROR_K} as hat from spairs join sig x on x.id = id1 join sig y on y.id = id2 and y.j = x.j group by id1, id2, x.j // {ERROR_K})"
ORACLES = {
    "minwise_variance": _minwise_sql(),
    "projection_variance": _projection_sql(),
    "norm_domination": f"with {CPAIRS} select id1, id2, round((f1 * f2 + a * a - 2 * a) / 64, 6) as var_signed, round({_match(8)} * (1 - {_match(8)}) / (64 * (1 - 1.0 / 256) * (1 - 1.0 / 256)) * (f1 + f2) * (f1 + f2), 6) as var_bbit from cpairs where a = 0",
    "family_error": f"with {_SPAIRS}, {sig('supp', ERROR_K * ERROR_RUNS)}, {_HATS}, e as (select run, avg(hat - r) as bias, avg((hat - r) * (hat - r)) as mse from h group by run) select count(*) as runs, round(avg(bias), 6) as bias, round(stddev_samp(bias), 6) as bias_deviation, round(avg(mse), 6) as mse from e",
}
QUERIES = {name: globals()[name] for name in ORACLES}
