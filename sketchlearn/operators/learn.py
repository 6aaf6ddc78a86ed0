"""L2-regularised linear SVM and logistic regression over sparse rows (id, y in -1/+1, active places, optional values).

Objective: |w|^2 / 2 + C times the summed hinge or logistic loss, no intercept.
Solvers: MLlib (distributed), dual coordinate descent and SGD (numpy, one model
a task, on codes that fit it), local-epoch SGD with averaged weights
(distributed), and a fixed number of full gradient steps (DataFrame only, so
that SQL can check it). Hashing is done before and is the same for all.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Penalties of the sweep: 1e-3 to 1e2, finer in 0.1 to 10.
PENALTIES = (0.001, 0.01, 0.1, 0.2, 0.5, 1.0, 2.0, 5.0, 10.0, 100.0)


# ---------------------------------------------------------------- MLlib


def fit_mllib(vectors: DataFrame, c: float, loss: str, n: int | None = None, max_iter: int = 50):
    """MLlib minimises the mean loss plus lambda |w|^2 / 2: lambda = 1 / (C n) has the same minimiser. vectors: label 0/1, features."""
    from pyspark.ml.classification import LinearSVC, LogisticRegression

    lam = 1.0 / (c * (n or vectors.count()))
    kind = LinearSVC if loss == "hinge" else LogisticRegression
    return kind(regParam=lam, fitIntercept=False, standardization=False, maxIter=max_iter).fit(vectors)


def one_vs_rest(vectors: DataFrame, c: float, max_iter: int = 20):
    from pyspark.ml.classification import LinearSVC, OneVsRest

    return OneVsRest(classifier=LinearSVC(regParam=1.0 / (c * vectors.count()), fitIntercept=False, standardization=False, maxIter=max_iter)).fit(vectors)


# ---------------------------------------------------------------- numpy, in one task


class SparseRows:
    def __init__(self, idx: list[np.ndarray], val: list[np.ndarray] | None, dims: int):
        self.idx = [np.asarray(i, np.int64) for i in idx]
        self.val = [np.ones(len(i)) for i in self.idx] if val is None else [np.asarray(v, float) for v in val]
        self.dims = dims

    def margins(self, w: np.ndarray) -> np.ndarray:
        return np.array([w[i] @ v for i, v in zip(self.idx, self.val, strict=True)])


def dual_coordinate(x: SparseRows, y: np.ndarray, c: float, loss: str = "hinge", epochs: int = 20, seed: int = 0, tol: float = 1e-3) -> np.ndarray:
    """Coordinate descent on the dual. Hinge: the closed-form clipped step. Logistic: a few guarded Newton steps on the one-variable problem."""
    rng, n = np.random.default_rng(seed), len(y)
    w, q = np.zeros(x.dims), np.array([v @ v for v in x.val])
    alpha = np.zeros(n) if loss == "hinge" else np.full(n, min(1e-3 * c, 0.5 * c))
    if loss != "hinge":
        for i in range(n):
            w[x.idx[i]] += alpha[i] * y[i] * x.val[i]
    for _ in range(epochs):
        most = 0.0
        for i in rng.permutation(n):
            if q[i] == 0:
                continue
            at, v = x.idx[i], x.val[i]
            m = y[i] * (w[at] @ v)
            old = alpha[i]
            if loss == "hinge":
                new = min(max(old - (m - 1) / q[i], 0.0), c)
            else:
                new = old
                for _ in range(8):
                    g = np.log(new / (c - new)) + m + q[i] * (new - old)
                    step = g / (c / (new * (c - new)) + q[i])
                    nxt = new - step
                    nxt = new / 2 if nxt <= 0 else (new + c) / 2 if nxt >= c else nxt
                    if abs(nxt - new) < 1e-9 * c:
                        new = nxt
                        break
                    new = nxt
            if new != old:
                w[at] += (new - old) * y[i] * v
                alpha[i] = new
                most = max(most, abs(new - old))
        if most < tol * c:
            break
    return w


def dual_coordinate_all(x: SparseRows, y: np.ndarray, cs: np.ndarray, loss: str = "hinge", epochs: int = 20, seed: int = 0, tol: float = 1e-3) -> np.ndarray:
    """dual_coordinate() for several penalties over the same rows: dims x penalties.

    The passes over the rows are shared. A penalty whose dual variables have come
    to rest leaves; rows that did not move in a pass are looked at again in every
    fourth only.
    """
    rng, n, dims = np.random.default_rng(seed), len(y), x.dims
    out, open_ = np.zeros((dims, len(cs))), np.arange(len(cs))
    w, q, c = np.zeros((dims, len(cs))), np.array([v @ v for v in x.val]), np.asarray(cs, float)
    ones = all((v == 1).all() for v in x.val)
    alpha = np.zeros((n, len(c)))
    if loss != "hinge":
        alpha += np.minimum(1e-3 * c, 0.5 * c)
        for i in range(n):
            w[x.idx[i]] += alpha[i] * y[i] * (1.0 if ones else x.val[i][:, None])
    every = np.nonzero(q > 0)[0]
    moved = every
    for epoch in range(epochs):
        before, whole = alpha.copy(), epoch % 4 == 0 or not len(moved)
        for i in rng.permutation(every if whole else moved).tolist():
            at, old = x.idx[i], alpha[i]
            rows = w[at]
            m = np.add.reduce(rows, 0) if ones else x.val[i] @ rows
            if y[i] < 0:
                m = -m
            new = np.minimum(np.maximum(old - (m - 1) / q[i], 0.0), c) if loss == "hinge" else _logistic_step(old, m, q[i], c)
            step = (new - old) * y[i]
            if step.any():
                rows += step if ones else np.outer(x.val[i], step)
                w[at] = rows
                alpha[i] = new
        change = np.abs(alpha - before)
        moved = np.nonzero((change > 0.1 * tol * c).any(1))[0]
        rest = (change.max(0, initial=0) < tol * c) if whole else np.zeros(len(c), bool)
        if rest.any():
            out[:, open_[rest]] = w[:, rest]
            w, alpha, c, open_ = w[:, ~rest].copy(), alpha[:, ~rest].copy(), c[~rest], open_[~rest]
            if not len(c):
                return out
    out[:, open_] = w
    return out


def dual_coordinate_runs(codes: np.ndarray, y: np.ndarray, width: int, c: float, loss: str = "hinge", epochs: int = 20, seed: int = 0, tol: float = 1e-3) -> np.ndarray:
    """Models of several runs over the same rows at one penalty: codes rows x runs x k, of which value v at j lights place j * width + width - 1 - v; runs x (k * width).

    The passes over the rows are shared, and each run takes the steps that it
    would take alone (up to digits that a Newton step leaves open). A run whose dual variables have come to rest leaves; rows
    that did not move in a pass are looked at again in every fourth only.
    """
    rng, (n, runs, k) = np.random.default_rng(seed), codes.shape
    dims, open_ = k * width, np.arange(runs)
    out, w = np.zeros((runs, dims)), np.zeros((runs, dims))
    base = open_[:, None] * dims + np.arange(k) * width + width - 1
    alpha = np.full((n, runs), 0.0 if loss == "hinge" else min(1e-3 * c, 0.5 * c))
    if loss != "hinge":
        for i in range(n):
            w.reshape(-1)[base - codes[i]] += alpha[i, 0] * y[i]
    moved = np.ones((n, runs), bool)
    for epoch in range(epochs):
        order, before = rng.permutation(n), alpha.copy()
        whole = np.full(len(open_), epoch % 4 == 0) | ~moved.any(0)
        looked = moved | whole
        flat, every = w.reshape(-1), len(open_) == runs
        for i in (order if whole.any() else order[looked[order].any(1)]).tolist():
            at, old = base - (codes[i] if every else codes[i, open_]), alpha[i]
            m = flat[at].sum(1) * y[i]
            new = np.minimum(np.maximum(old - (m - 1) / k, 0.0), c) if loss == "hinge" else _logistic_step(old, m, k, c)
            step = np.where(looked[i], new - old, 0.0)
            own = np.nonzero(step)[0]
            if len(own):
                flat[at[own]] += step[own, None] * y[i]
                alpha[i] += step
        change = np.abs(alpha - before)
        moved = change > 0.1 * tol * c
        rest = whole & (change.max(0, initial=0) < tol * c)
        if rest.any():
            out[open_[rest]] = w[rest]
            w, alpha, moved, open_ = w[~rest], alpha[:, ~rest], moved[:, ~rest], open_[~rest]
            base = base[: len(open_)]
            if not len(open_):
                return out
    out[open_] = w
    return out


def _logistic_step(old: np.ndarray, m: np.ndarray, q: float, cs: np.ndarray | float) -> np.ndarray:
    """Guarded Newton steps on the one-variable dual problem of each penalty."""
    new = old
    for _ in range(6):
        g = np.log(new / (cs - new)) + m + q * (new - old)
        nxt = new - g / (cs / (new * (cs - new)) + q)
        nxt = np.where(nxt <= 0, new / 2, np.where(nxt >= cs, (new + cs) / 2, nxt))
        done = (np.abs(nxt - new) < 1e-4 * cs).all()
        new = nxt
        if done:
            break
    return new


def sgd(x: SparseRows, y: np.ndarray, c: float, loss: str = "hinge", epochs: int = 5, step: float = 0.5, seed: int = 0, w: np.ndarray | None = None, total: int | None = None) -> np.ndarray:
    """Plain stochastic subgradient over several epochs; the shrinkage is kept as a scale. total: rows of the whole part, where x is a piece of it."""
    rng, n = np.random.default_rng(seed), len(y)
    w, scale, t, lam = np.zeros(x.dims) if w is None else w.copy(), 1.0, 0, 1.0 / (c * (total or n))
    for _ in range(epochs):
        for i in rng.permutation(n):
            t += 1
            eta = step / (1 + step * lam * t)
            at, v = x.idx[i], x.val[i]
            m = y[i] * scale * (w[at] @ v)
            pull = float(m < 1) if loss == "hinge" else 1 / (1 + np.exp(np.clip(m, -30, 30)))
            scale *= 1 - eta * lam
            if pull:
                w[at] += eta * pull * y[i] / scale * v
    return w * scale


# ---------------------------------------------------------------- distributed


def averaged_sgd(rows: DataFrame, dims: int, c: float, loss: str = "hinge", epochs: int = 3, parts: int = 8) -> np.ndarray:
    """Epochs of local SGD in each partition, weights averaged after each; one pass and one small reduce an epoch. rows: id, y, active."""
    dealt = rows.select("y", "active").repartition(parts)
    total, w = max(1, rows.count() // parts), np.zeros(dims)
    for e in range(epochs):

        def local(frames: Iterator[pd.DataFrame], w=w, e=e) -> Iterator[pd.DataFrame]:
            own, n = w, 0
            for held in frames:  # an Arrow batch at a time: a part of the corpus need not fit a task
                own = sgd(SparseRows(held["active"].tolist(), None, dims), held["y"].to_numpy(float), c, loss, 1, seed=e, w=own, total=total)
                n += len(held)
            if n:
                yield pd.DataFrame({"n": [n], "w": [own.tobytes()]})

        got = dealt.mapInPandas(local, "n long, w binary").collect()  # one row of the model's fixed size a partition
        met = sum(r.n for r in got)
        w = sum((np.frombuffer(r.w) * (r.n / met) for r in got), np.zeros(dims))
    return w


def margins(long: DataFrame, weights: DataFrame) -> DataFrame:
    """(id, y, score) from rows (id, y, idx, v) and weights (idx, w)."""
    return long.join(weights, "idx", "left").groupBy("id", "y").agg(F.sum(F.col("v") * F.coalesce("w", F.lit(0.0))).alias("score"))


def objective(long: DataFrame, weights: DataFrame, c: float, loss: str) -> DataFrame:
    """One row: the objective. The logistic loss in its stable form."""
    m = F.col("y") * F.col("score")
    one = F.greatest(1 - m, F.lit(0.0)) if loss == "hinge" else F.log1p(F.exp(-F.abs(m))) + F.greatest(-m, F.lit(0.0))
    total = margins(long, weights).agg(F.sum(one).alias("l"))
    norm = weights.agg((F.sum(F.col("w") * F.col("w")) / 2).alias("h"))
    return total.crossJoin(norm).select(F.lit(loss).alias("loss"), F.lit(c).alias("c"), (F.col("h") + c * F.col("l")).alias("objective"))


def fixed_gd(long: DataFrame, c: float, loss: str, steps: int = 2, eta: float = 1e-3) -> DataFrame:
    """(idx, w) after full gradient steps from zero: joins and sums only. long: id, y, idx, v."""
    weights = long.groupBy("idx").agg(F.lit(0.0).alias("w"))
    for _ in range(steps):
        m = F.col("y") * F.col("score")
        pull = F.when(m < 1, -F.col("y")).otherwise(0) if loss == "hinge" else -F.col("y") / (1 + F.exp(m))
        g = margins(long, weights).select("id", pull.alias("g"))
        slope = long.join(g, "id").groupBy("idx").agg(F.sum(F.col("g") * F.col("v")).alias("slope"))
        weights = weights.join(slope, "idx").select("idx", (F.col("w") - eta * (F.col("w") + c * F.col("slope"))).alias("w"))
    return weights


def predict(long: DataFrame, weights: DataFrame) -> DataFrame:
    """(id, y, score, pred): a score of 0 predicts +1."""
    return margins(long, weights).withColumn("pred", F.when(F.col("score") >= 0, 1).otherwise(-1))


def score_codes(rows: DataFrame, w: np.ndarray, active: str = "active") -> DataFrame:
    """Adds score: the sum of the weights at a code's places, without building the expanded vector. The weights are of a fixed size, 2^b k."""
    held = rows.sparkSession.sparkContext.broadcast(w)

    @F.pandas_udf("double")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        own = held.value
        for a in batches:
            sizes = np.array([0 if x is None else len(x) for x in a])
            flat = np.concatenate([np.zeros(0, np.int64), *(x for x in a if x is not None)]).astype(np.int64)
            full, total = np.nonzero(sizes)[0], np.zeros(len(a))
            if len(full):
                total[full] = np.add.reduceat(own[flat], (np.cumsum(sizes) - sizes)[full])
            yield pd.Series(total, dtype=float).where(pd.Series([x is not None for x in a]))

    return rows.withColumn("score", run(active))
