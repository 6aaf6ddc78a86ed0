"""Exact top-k by integer inner product: a Voronoi join.

Vectors are assigned to the nearest of a bounded number of pivots. Summaries of
the cells (counts, radii, the distances of the vectors nearest to the pivot)
give each query a score that k other vectors are sure to reach. As
q.x <= q.p + |q| dist(x, p), a cell is needed by a block of queries only if it
can pass that score, and of the cell only the vectors from some distance on.
Cells are laid into parts of the data; a block of queries goes once to each part
that holds a cell it needs, is multiplied there, and the best k of each meeting
go to one ranking by query. What is sent is the vectors once, in 16 bits a
component where they fit, and the queries once a part; nothing is broadcast.

All groups are bounded: full cells are cut by a hash of the id, queries
likewise, so neither a frequent vector nor a full cell gathers in one task. How much the bounds leave out is up
to the data: clustered vectors lose most of their cells (pruned() counts it),
vectors spread evenly over many dimensions lose nearly none.

Defined results: a vector that is null, empty or holds null or non-finite
components takes no part, nor does a row without an id; vectors meet only
vectors of the same length; of repeated ids each row counts as a candidate, and
none is a candidate of its own id; a query row given twice asks once; ties go
to the smaller id; fewer candidates than k give fewer rows; components and
scores beyond 64 bits are the nearest 64-bit number.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import written

#: At most so many pivots (they go to every task), queries in a block; bytes of a part of the data as doubles, its least vectors, bytes of queries that meet it together, scores at a time.
MOST_PIVOTS, QUERY_BLOCK = 256, 256
PART_BYTES, LEAST_PART, ASKED_BYTES, SCORES = 32 << 20, 2048, 64 << 20, 4_000_000
_RANK = 2.0**53


def integer_vector(col: Column, scale: int = 1024) -> Column:
    """floor(scale * x) of each component as long; null where the vector can't take part."""
    bad = F.exists(col, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.when(col.isNotNull() & ~bad, F.transform(col, lambda x: F.floor(x.cast("double") * scale)))


def products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact integer products: in doubles where no sum can pass 2^53, else in Python's integers."""
    x, y = a.astype(np.float64), b.astype(np.float64)
    if np.abs(x).max(initial=0) * np.abs(y).max(initial=0) * max(1, a.shape[1]) < _RANK:
        return (x @ y.T).astype(np.int64)
    return np.clip(a.astype(object) @ b.astype(object).T, -(1 << 63), (1 << 63) - 1).astype(np.int64)


def best(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k highest scores, ties to the smaller id."""
    if len(scores) > 4 * k:
        cut = np.partition(scores, len(scores) - k)[len(scores) - k]
        at = np.nonzero(scores >= cut)[0]
    else:
        at = np.arange(len(scores))
    return at[np.lexsort((ids[at], -scores[at]))[:k]]


def short_ints(m: np.ndarray) -> list[bytes]:
    """Each row in the shortest integers that hold it: equal rows give equal bytes."""
    kinds = [m.astype(np.int16), m.astype(np.int32), m]
    which = np.where((kinds[0] == m).all(1), 0, np.where((kinds[1] == m).all(1), 1, 2)).tolist()
    return [kinds[w][i].tobytes() for i, w in enumerate(which)]


def whole_ints(rows: list[bytes], d: int) -> np.ndarray:
    """rows x d, from short_ints()."""
    sizes = {len(r) // d for r in rows}
    if len(sizes) == 1:
        return np.frombuffer(b"".join(rows), f"<i{sizes.pop()}").reshape(-1, d)
    return np.array([np.frombuffer(r, f"<i{len(r) // d}") for r in rows], np.int64).reshape(-1, d)


def leaders(q: np.ndarray, asking: np.ndarray, m: np.ndarray, ids: np.ndarray, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(query id, places, scores) of the k best of each query among vectors m (doubles or integers) whose ids ascend; none of its own id."""
    n = len(ids)
    low, high = np.searchsorted(ids, asking, "left"), np.searchsorted(ids, asking, "right")
    exact = np.abs(q.astype(np.float64)).max(initial=0) * np.abs(m).max(initial=0) * max(1, q.shape[1]) < _RANK if m.dtype == np.float64 else False
    for at in range(0, len(q), step := max(1, SCORES // n)):
        scores = q[at : at + step].astype(np.float64) @ m.T if exact else products(q[at : at + step], m)
        thin = scores[:, :: max(1, n // 1024)]
        for i in range(len(scores)):
            own, a, z = scores[i], low[at + i], high[at + i]
            # The k-th best of some of the vectors, one's own id not among them, is no more than the k-th best of all.
            some, others = thin[i], n - (z - a)
            least = None
            if others > 8 * k and z - a <= 1 and len(some) > k + 1:
                least = np.partition(some, len(some) - k - 1)[len(some) - k - 1]
            where = np.arange(n) if least is None else np.nonzero(own >= least)[0]
            where = where[(where < a) | (where >= z)]
            top = where[best(own[where], ids[where], k)]
            yield int(asking[at + i]), top, own[top].astype(np.int64)


def pruned(vectors: DataFrame, is_query: Column, k: int = 10, **options) -> DataFrame:
    """(query_blocks, meetings, all_meetings): how many of the meetings of a block of queries with a cell the bounds leave."""
    asked, cells = _join(vectors, is_query, k, **options)[:2]
    spark = vectors.sparkSession
    if not cells:
        return spark.createDataFrame([(0, 0, 0)], "query_blocks long, meetings long, all_meetings long")
    of_length = spark.createDataFrame([(d, sum(1 for x, _ in cells if x == d)) for d in {d for d, _ in cells}], "d int, n long")
    counted = asked.select("d", (F.length("cells") / 4).cast("long").alias("met")).where("met > 0").join(of_length, "d")
    return counted.agg(F.count(F.lit(1)).alias("query_blocks"), F.coalesce(F.sum("met"), F.lit(0)).alias("meetings"), F.coalesce(F.sum("n"), F.lit(0)).alias("all_meetings"))


def top_k(vectors: DataFrame, is_query: Column, k: int = 10, scale: int = 1024, id_col: str = "vec_id", vector_col: str = "embedding", pivots: int = MOST_PIVOTS) -> DataFrame:
    """(query_id, rank, vec_id, score) for every row of which is_query holds, against all other rows."""
    _, cells, found = _join(vectors, is_query, k, scale, id_col, vector_col, pivots)
    if not cells:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return ranked.select("query_id", "rank", "vec_id", "score")


def _join(vectors: DataFrame, is_query: Column, k: int = 10, scale: int = 1024, id_col: str = "vec_id", vector_col: str = "embedding", pivots: int = MOST_PIVOTS) -> tuple[DataFrame | None, dict, DataFrame | None]:
    """What blocks of queries ask of the cells, the cells, and the best of each meeting (query_id, vec_id, score)."""
    spark = vectors.sparkSession
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.coalesce(is_query, F.lit(False)).alias("asks"), integer_vector(F.col(vector_col), scale).alias("v")).where("v is not null and size(v) > 0 and vec_id is not null")
    chosen: dict[int, np.ndarray] = {}
    # A fixed number of pivots, spread by a hash of their components; copies of a vector are one pivot.
    sample = rows.select("v", F.xxhash64("v").alias("h")).groupBy("h").agg(F.first("v").alias("v")).orderBy("h").limit(pivots).collect()
    for d in {len(r.v) for r in sample}:
        chosen[d] = np.array([r.v for r in sample if len(r.v) == d], np.float64).reshape(-1, d)

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, asks, lists = b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False), b.column(2)
            sizes = lists.value_lengths().to_numpy(zero_copy_only=False)
            flat = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
            at = np.concatenate([[0], np.cumsum(sizes)])
            for d in np.unique(sizes).tolist():
                who = np.nonzero(sizes == d)[0]
                m = flat[(at[who][:, None] + np.arange(d)).ravel()].reshape(-1, d)
                p = chosen.get(d, np.zeros((1, d)))
                x = m.astype(np.float64)
                far = (x * x).sum(1)[:, None] - 2 * x @ p.T + (p * p).sum(1)
                cell = far.argmin(1)
                dist = np.sqrt(((x - p[cell]) ** 2).sum(1))
                yield pa.RecordBatch.from_arrays([pa.array(ids[who]), pa.array(asks[who]), pa.array(short_ints(m), pa.binary()), pa.array(np.full(len(who), d), pa.int32()), pa.array(cell, pa.int32()), pa.array(dist)], names=["vec_id", "asks", "v", "d", "cell", "dist"])

    placed = written(rows.mapInArrow(assign, "vec_id long, asks boolean, v binary, d int, cell int, dist double"), spark)
    # The nearest k+1 distances of each cell, its count, radius and number of queries: bounded by pivots * (k + 1).
    # An id gives one distance to one cell only, however many rows it has: of k+1 bounds one at most is the query's own.
    once = placed.groupBy("d", "vec_id").agg(F.min(F.struct("dist", "cell")).alias("x")).select("d", "vec_id", "x.*")
    # The least of a part of a cell, then of the cell: what is gathered is k+1 numbers a part, however full the cell is.
    least = lambda df, *keys: df.withColumn("nth", F.row_number().over(Window.partitionBy(*keys).orderBy("dist"))).where(F.col("nth") <= k + 1)
    near = least(once.withColumn("salt", F.pmod(F.xxhash64("vec_id"), F.lit(64))), "d", "cell", "salt")
    nearest = least(near, "d", "cell").groupBy("d", "cell").agg(F.sort_array(F.collect_list("dist")).alias("near"))
    summary = placed.groupBy("d", "cell").agg(F.count(F.lit(1)).alias("n"), F.max("dist").alias("far"), F.count_if("asks").alias("queries")).join(nearest, ["d", "cell"], "left").collect()
    cells = {(r.d, r.cell): (np.array(r.near or [], np.float64), r.n, r.far, r.queries) for r in summary}
    if not cells:
        return None, cells, None

    def blocks_of(n: dict[tuple[int, int], int], block: int) -> Column:
        """ceil(n / block) of a row's cell."""
        parts = [(key, -(-v // block)) for key, v in n.items() if v > block]
        if not parts:
            return F.lit(1)
        count = F.create_map(*[x for (d, c), v in parts for x in (F.lit(d * MOST_PIVOTS + c), F.lit(v))])
        return F.coalesce(F.try_element_at(count, F.col("d") * MOST_PIVOTS + F.col("cell")), F.lit(1))

    # Cells are laid into parts one after the other; a full one is cut into several by a hash of the id.
    parts: dict[tuple[int, int], tuple[int, int]] = {}
    cores, last = spark.sparkContext.defaultParallelism, -1
    for d in sorted({d for d, _ in cells}):
        own = sorted(c for dd, c in cells if dd == d)
        whole = sum(cells[d, c][1] for c in own)
        most, held = max(LEAST_PART, min(PART_BYTES // (8 * d), -(-whole // (3 * cores)))), None
        for c in own:
            n = cells[d, c][1]
            if n > most:
                parts[d, c] = last + 1, -(-n // most)
                last, held = last + parts[d, c][1], None
                continue
            if held is None or held + n > most:
                last, held = last + 1, 0
            held += n
            parts[d, c] = last, 1
    asked_bytes = sum(8 * d * v[3] for (d, _), v in cells.items())
    turns = -(-asked_bytes // ASKED_BYTES) or 1  # a part meets the queries in so many turns
    in_queries = blocks_of({key: v[3] for key, v in cells.items()}, QUERY_BLOCK)
    own_block = lambda n: F.pmod(F.xxhash64("vec_id"), n).cast("int")
    looked_up = lambda i: F.element_at(F.create_map(*[x for (d, c), v in parts.items() for x in (F.lit(d * MOST_PIVOTS + c), F.lit(v[i]))]), F.col("d") * MOST_PIVOTS + F.col("cell"))
    data = placed.withColumn("part", looked_up(0) + own_block(looked_up(1))).withColumn("turn", F.explode(F.sequence(F.lit(0), F.lit(turns - 1)))).select("part", "turn", "vec_id", "cell", "dist", "v")

    def plan(pdf: pd.DataFrame) -> pd.DataFrame:
        """For a block of queries: the cells it needs, each with the distance from its pivot from which vectors matter."""
        d = int(pdf["d"].iloc[0])
        q = whole_ints(list(pdf["v"]), d).astype(np.float64)
        norm, p = np.sqrt((q * q).sum(1)), chosen.get(d, np.zeros((1, d)))
        own = sorted(c for dd, c in cells if dd == d)
        at_pivot = q @ p[own].T  # queries x cells
        sure = np.concatenate([at_pivot[:, [i]] - norm[:, None] * cells[d, c][0] for i, c in enumerate(own)], axis=1)
        floor = np.sort(sure, axis=1)[:, -(k + 1)] if sure.shape[1] > k else np.full(len(q), -np.inf)
        slack = 1e-6 * (1 + np.abs(at_pivot).max() + norm.max() * max(cells[d, c][2] for c in own))
        with np.errstate(divide="ignore", invalid="ignore"):
            needs = np.where(norm[:, None] > 0, (floor[:, None] - slack - at_pivot) / norm[:, None], np.where(at_pivot >= floor[:, None] - slack, -np.inf, np.inf)).min(0)
        held = [(c, float(t)) for c, t in zip(own, needs.tolist(), strict=True) if t <= cells[d, c][2]]
        needed = sorted({x for c, _ in held for x in range(parts[d, c][0], sum(parts[d, c]))})
        return pd.DataFrame({"d": [d], "cells": [np.array([c for c, _ in held], np.int32).tobytes()], "least": [np.array([t for _, t in held], np.float64).tobytes()], "parts": [needed], "qids": [pdf["vec_id"].to_numpy(np.int64).tobytes()], "q": [whole_ints(list(pdf["v"]), d).astype(np.int64).tobytes() if len({len(v) for v in pdf["v"]}) > 1 else b"".join(pdf["v"])]})

    asked = placed.where("asks").dropDuplicates(["vec_id", "v"]).withColumn("block", own_block(in_queries)).groupBy("d", "cell", "block").applyInPandas(plan, "d int, cells binary, least binary, parts array<int>, qids binary, q binary")

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        """Blocks of queries against a part of the data."""
        out_q, out_v, out_s = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        if left.num_rows and right.num_rows:
            d = left.column("d")[0].as_py()
            right = right.sort_by("vec_id")
            ids, cell, far = (right.column(c).to_numpy() for c in ("vec_id", "cell", "dist"))
            m = whole_ints(right.column("v").to_pylist(), d)
            if m.dtype != np.int64:
                m = m.astype(np.float64)  # exact
            for own_cells, least, qids, q in zip(*(left.column(c).to_pylist() for c in ("cells", "least", "qids", "q")), strict=True):
                from_on = np.full(MOST_PIVOTS, np.inf)
                from_on[np.frombuffer(own_cells, np.int32)] = np.frombuffer(least, np.float64)
                keep = far >= from_on[cell]
                some = np.nonzero(keep)[0]
                if not len(some):
                    continue
                # Vectors that are not needed do no harm where they are few.
                few = len(some) < len(ids) / 2
                asking = np.frombuffer(qids, np.int64)
                rows = np.frombuffer(q, f"<i{len(q) // (len(asking) * d)}").reshape(-1, d).astype(np.int64)
                held_ids = ids[some] if few else ids
                for query, top, score in leaders(rows, asking, m[some] if few else m, held_ids, k):
                    out_q.append(np.full(len(top), query))
                    out_v.append(held_ids[top])
                    out_s.append(score)
        return pa.table({"query_id": np.concatenate(out_q), "vec_id": np.concatenate(out_v), "score": np.concatenate(out_s)})

    dealt = asked.withColumn("part", F.explode("parts")).withColumn("turn", F.pmod(F.xxhash64("qids"), F.lit(turns)).cast("int")).select("part", "turn", "d", "cells", "least", "qids", "q")
    return asked, cells, dealt.groupBy("part", "turn").cogroup(data.groupBy("part", "turn")).applyInArrow(meet, "query_id long, vec_id long, score long")
