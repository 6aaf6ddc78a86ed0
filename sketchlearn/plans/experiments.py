"""Accuracy, training time and family experiments: codes, full-width minima, raw sets, signed buckets and stacked codes under both losses.

Models over the grid are fitted on a bounded sample of the training rows (MAX_TRAIN,
by a hash of the id: a documented bound; permutation_vs_universal_accuracy takes
all of them); the sample is packed once and sent to every
task, and a task fits one feature set for all penalties. The models, of the size
of what the sample lights, are then sent out and score every labelled test row
where it stands: accuracy and AUC are over all test rows, however many. Hashing
runs once, at the widest setting; each cell is a slice of it. Buckets are the
md5 buckets that SQL checks (operators.projections).
"""

from __future__ import annotations

import time
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import minwise, sets
from ..functions.hashing import TwoUniversal
from ..operators import cost, evaluate, learn, projections
from ..sources import tables
from ..sources.shared import shared_dir, written
from ..sources.tables import load_table

MAX_TRAIN, K_MAX, TEST = 6_000, 500, 0.2
#: Bytes of models that go to every task at a time (one model has 12 bytes a place, of which the sample lights MAX_TRAIN k at most), and scores in a bin of the AUC (1 / AUC_BINS wide).
MODEL_BYTES, AUC_BINS = 1 << 27, 1000
RESULT = "method string, solver string, k int, b int, m int, c double, n_train bigint, n_test bigint, accuracy double, auc double, train_s double, bits_per_row bigint"
#: The full grid of the accuracy experiments, and the penalties of the comparison with buckets.
GRID = {"k": (30, 50, 100, 200, 300, 500), "b": (1, 2, 4, 8, 12, 16), "c": learn.PENALTIES}
VERSUS_C = (0.01, 0.1, 1.0, 10.0)


# ---------------------------------------------------------------- rows and features


def labelled_rows(spark, d, target: str = "lang", test: float = TEST) -> DataFrame:
    """(id, y, part, items, sig) of all labelled rows, hashed once and written. target: lang (English or not), quality, toxic."""
    docs = load_table(spark, d, "documents").select("doc_id", "text", "lang")
    rows = docs.join(load_table(spark, d, "labels"), "doc_id")
    y = F.when(F.col("lang") == "en", 1).otherwise(-1) if target == "lang" else sets.signed_label(F.col(target))
    # Copies of a text fall on one side of the split.
    named = rows.select(F.col("doc_id").alias("id"), y.cast("int").alias("y"), evaluate.split(F.md5(F.coalesce("text", F.lit(""))), test).alias("part"), "text")
    return written(minwise.signature(sets.text_items(named, "text").where(F.size("items") > 0), TwoUniversal(K_MAX)))


@dataclass(frozen=True)
class Cell:
    """A feature set: method raw, minwise, bbit, signed_bucket (k buckets) or stacked (b-bit codes of k in m buckets)."""

    method: str
    k: int = 0
    b: int = 0
    m: int = 0

    def bits(self, mean_items: float) -> int:
        return {"raw": int(64 * mean_items), "minwise": 64 * self.k, "signed_bucket": 32 * self.k}.get(self.method, self.b * self.k)


@dataclass
class Rows:
    """Rows in numpy: labels, minima, items one row after the other, and the md5 numbers of the items' buckets and signs."""

    y: np.ndarray
    sig: np.ndarray
    items: np.ndarray
    at: np.ndarray
    bucket: np.ndarray | None = None
    sign: np.ndarray | None = None


def rows_of(table: pa.Table | pa.RecordBatch, hashed: projections.Remembered | None) -> Rows:
    """From columns y, items, sig."""
    y, items, sig = (table.column(n) for n in ("y", "items", "sig"))
    if isinstance(table, pa.Table):
        y, items, sig = (c.combine_chunks() for c in (y, items, sig))
    flat = items.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    at = np.concatenate([[0], np.cumsum(items.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64)
    out = Rows(y.to_numpy(zero_copy_only=False).astype(np.float64), sig.flatten().to_numpy(zero_copy_only=False).reshape(len(at) - 1, -1).astype(np.int32), flat, at)
    if hashed is not None:
        names, place = np.unique(flat, return_inverse=True)
        e = hashed(names)[place]
        out.bucket, out.sign = e[:, 0].astype(np.int64), e[:, 1].astype(np.int8)
    return out


def bucket_entries() -> projections.Remembered:
    """For coordinates the md5 number of their bucket (its low 40 bits: bucket counts are powers of two) and their sign."""
    return projections.Remembered(lambda i: np.stack([projections.bucket_array(i, 1 << 40).astype(np.float64), projections.entry_array("sign", 1.0, 7, i)], axis=1), 2, 1 << 18)


def summed(row: np.ndarray, bucket: np.ndarray, sign: np.ndarray, n: int, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places, values and row ends of signed bucket sums; sums of zero are left out."""
    key, where = np.unique(row * width + bucket, return_inverse=True)
    val = np.bincount(where, sign, len(key))
    key, val = key[val != 0], val[val != 0]
    return key % width, val, np.searchsorted(key // width, np.arange(n + 1))


def features(x: Rows, cell: Cell, stacked: projections.Remembered | None = None) -> tuple[np.ndarray, np.ndarray | None, np.ndarray]:
    """(places, values or all ones, row ends) of a feature set."""
    n = len(x.y)
    if cell.method == "raw":
        return x.items, None, x.at
    if cell.method == "signed_bucket":
        return summed(np.repeat(np.arange(n), np.diff(x.at)), x.bucket % cell.k, x.sign, n, cell.k)
    sig, j = x.sig[:, : cell.k].astype(np.int64), np.arange(cell.k)
    at = np.arange(n + 1) * cell.k
    if cell.method == "minwise":
        return (sig + (j << 31)).ravel(), None, at
    width = 1 << cell.b
    active = (j * width + width - 1 - (sig & (width - 1))).ravel()
    if cell.method != "stacked":
        return active, None, at
    names, place = np.unique(active, return_inverse=True)
    e = (stacked or bucket_entries())(names)[place]
    return summed(np.repeat(np.arange(n), cell.k), e[:, 0].astype(np.int64) % cell.m, e[:, 1], n, cell.m)


def margins(x: Rows, cell: Cell, names: np.ndarray, w: np.ndarray, stacked) -> np.ndarray:
    """rows x penalties: scores under weights w (names x penalties); places that training never lit weigh nothing."""
    idx, val, at = features(x, cell, stacked)
    place = np.searchsorted(names, idx)
    place[place == len(names)] = 0
    known = names[place] == idx if len(names) else np.zeros(len(idx), bool)
    out, sizes = np.zeros((len(x.y), w.shape[1])), np.diff(at)
    full = np.nonzero(sizes)[0]
    for c in range(w.shape[1]):
        part = np.where(known, w[place, c], 0.0) if len(names) else np.zeros(len(idx))
        if len(full):
            out[full, c] = np.add.reduceat(part if val is None else part * val, at[:-1][full])
    return out


# ---------------------------------------------------------------- fitting and scoring


def train_sample(rows: DataFrame) -> pa.Table:
    """At most MAX_TRAIN training rows by a hash of the id, in a fixed order."""
    return rows.where("part = 'train'").orderBy(F.xxhash64("id"), "id").limit(MAX_TRAIN).select("id", "y", "items", "sig").toArrow()


def run_cells(spark, rows: DataFrame, cells: list[Cell], cs: tuple[float, ...], loss: str) -> DataFrame:
    """One row for each feature set and penalty, measured on all test rows."""
    table = train_sample(rows)
    if not table.num_rows:
        return spark.createDataFrame([], RESULT)
    wants_buckets = any(c.method == "signed_bucket" for c in cells)
    train = rows_of(table, bucket_entries() if wants_buckets else None)
    if not any(c.method == "raw" for c in cells):
        train.items = train.items[:0] if not wants_buckets else train.items
    held, n_train = spark.sparkContext.broadcast(train), len(train.y)
    mean_items = float(np.diff(train.at).mean())

    def fit(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        x = held.value
        for i in (i for pdf in frames for i in pdf["cell"].tolist()):
            idx, val, at = features(x, cells[i])
            names, place = np.unique(idx, return_inverse=True)
            data = learn.SparseRows([place[a:z] for a, z in zip(at[:-1], at[1:], strict=True)], None if val is None else [val[a:z] for a, z in zip(at[:-1], at[1:], strict=True)], len(names))
            began = time.perf_counter()
            w = learn.dual_coordinate_all(data, x.y, np.array(cs), loss)
            took = (time.perf_counter() - began) / len(cs)
            lit = (w != 0).any(1)
            yield pd.DataFrame({"cell": [i], "names": [names[lit].tobytes()], "w": [w[lit].astype(np.float32).tobytes()], "train_s": [took]})

    tasks = spark.createDataFrame([(i,) for i in range(len(cells))], "cell int").repartitionByRange(len(cells), "cell")
    fitted = written(tasks.mapInPandas(fit, "cell int, names binary, w binary, train_s double"))

    def score(models, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashed, stacked = bucket_entries() if wants_buckets else None, bucket_entries()
        for b in (whole.slice(i, 500) for whole in batches for i in range(0, whole.num_rows, 500)):
            x = rows_of(b, hashed)
            for i, names, w in models.value:
                m = margins(x, cells[i], names, w, stacked)
                low = np.floor(m * AUC_BINS).astype(np.int64)
                for c in range(len(cs)):
                    key, where = np.unique(low[:, c], return_inverse=True)
                    count = lambda hit, n=len(key), where=where: np.bincount(where, hit, n).astype(np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(key), i, np.int32)), pa.array(np.full(len(key), c, np.int32)), pa.array(key), pa.array(count(x.y > 0)), pa.array(count(x.y < 0)), pa.array(count(np.where(m[:, c] >= 0, 1, -1) == x.y))], names=["cell", "ci", "bin", "p", "n", "good"])

    # Some models at a time go out and score all test rows; what comes back is counts.
    chunks, held_bytes = [[]], 0
    for r in fitted.select("cell", (F.length("names") + F.length("w")).alias("size")).orderBy("cell").collect():
        if chunks[-1] and held_bytes + r["size"] > MODEL_BYTES:
            chunks, held_bytes = [*chunks, []], 0
        chunks[-1].append(r.cell)
        held_bytes += r["size"]
    bins = None
    for chunk in chunks:
        models = spark.sparkContext.broadcast([(r.cell, np.frombuffer(r.names, np.int64), np.frombuffer(r.w, np.float32).reshape(-1, len(cs))) for r in fitted.where(F.col("cell").isin(chunk)).select("cell", "names", "w").toLocalIterator()])
        one = rows.where("part = 'test'").select("y", "items", "sig").mapInArrow(lambda batches, models=models: score(models, batches), "cell int, ci int, bin long, p long, n long, good long")
        bins = one if bins is None else bins.unionByName(one)
    measured = evaluate.binned_report(bins, "cell", "ci")
    # The cells are a constant list; with their times they are joined to what was measured.
    named = spark.createDataFrame([(i, j, c.method, f"dual_{loss}", c.k, c.b, c.m, v, n_train, c.bits(mean_items)) for i, c in enumerate(cells) for j, v in enumerate(cs)], "cell int, ci int, method string, solver string, k int, b int, m int, c double, n_train bigint, bits_per_row bigint")
    out = named.join(fitted.select("cell", "train_s"), "cell").join(measured, ["cell", "ci"], "left")
    return out.select(*(x.split()[0] for x in RESULT.split(", ")))


# ---------------------------------------------------------------- queries


def _grid(method: str = "bbit") -> list[Cell]:
    return [Cell(method, k, b) for k in GRID["k"] for b in GRID["b"]]


def _versus() -> list[Cell]:
    """Every power of two of buckets, and a panel of every b."""
    return [Cell("signed_bucket", 1 << p) for p in range(5, 15)] + _grid()


def svm_accuracy_grid(spark, d):
    """All k, b and C of the grid, 80 % of the rows for training."""
    return run_cells(spark, labelled_rows(spark, d), _grid(), GRID["c"], "hinge")


def logistic_accuracy_grid(spark, d):
    return run_cells(spark, labelled_rows(spark, d), _grid(), GRID["c"], "logistic")


def svm_accuracy_half(spark, d):
    """The same grid with half of the rows for training."""
    return run_cells(spark, labelled_rows(spark, d, test=0.5), _grid(), GRID["c"], "hinge")


def logistic_accuracy_half(spark, d):
    return run_cells(spark, labelled_rows(spark, d, test=0.5), _grid(), GRID["c"], "logistic")


def svm_bucket_vs_bbit(spark, d):
    return run_cells(spark, labelled_rows(spark, d), _versus(), VERSUS_C, "hinge")


def logistic_bucket_vs_bbit(spark, d):
    return run_cells(spark, labelled_rows(spark, d), _versus(), VERSUS_C, "logistic")


def training_times(spark, d):
    """Seconds to fit one model at C = 1: codes over k and b, buckets at the same k, stacked codes; both losses. Column train_s."""
    cells = _grid() + [Cell("signed_bucket", 1 << p) for p in range(5, 15)] + [Cell("signed_bucket", k) for k in (64, 256, 512)] + [Cell("stacked", k, 16, 4096) for k in GRID["k"]]
    rows, out = labelled_rows(spark, d), None
    for loss in ("hinge", "logistic"):
        one = run_cells(spark, rows, list(dict.fromkeys(cells)), (1.0,), loss)
        out = one if out is None else out.unionByName(one)
    return out


def stacked_accuracy(spark, d):
    """b = 16 codes plain and stacked into m buckets, with training times."""
    cells = [Cell("bbit", k, 16) for k in (100, 200, 500)] + [Cell("stacked", k, 16, m) for k in (100, 200, 500) for m in (1 << 8, 1 << 10, 1 << 12, 1 << 14, 1 << 16)]
    return run_cells(spark, labelled_rows(spark, d), cells, (1.0,), "hinge")


def raw_accuracy(spark, d):
    """The raw sets and full-width minima, as references."""
    return run_cells(spark, labelled_rows(spark, d), [Cell("raw"), Cell("minwise", 200, 64), Cell("minwise", 500, 64)], VERSUS_C, "hinge")


def _panels() -> list[Cell]:
    return [Cell("raw")] + [Cell("signed_bucket", 1 << p) for p in (8, 11, 14)] + [Cell("bbit", k, b) for k in (100, 500) for b in GRID["b"]]


def quality_accuracy(spark, d):
    """Accuracy and AUC for the quality label."""
    return run_cells(spark, labelled_rows(spark, d, "quality"), _panels(), VERSUS_C, "hinge")


def toxic_accuracy(spark, d):
    return run_cells(spark, labelled_rows(spark, d, "toxic"), _panels(), VERSUS_C, "hinge")


def equal_accuracy(spark, d):
    """For each method (codes: each b) the least k, and its bits a row, that reaches 95 %."""
    return evaluate.match_accuracy(svm_bucket_vs_bbit(spark, d), 0.95, "method", "b")


def _mllib_rows(spark, d, k: int, b: int) -> DataFrame:
    from ..functions import bbit

    rows = labelled_rows(spark, d)
    coded = rows.select("id", "y", "part", ((F.col("y") + 1) / 2).alias("label"), bbit.expand(bbit.sliced(F.col("sig"), k, b), b).alias("active"))
    return bbit.vector_table(coded, F.col("active"), k << b).drop("active")


def mllib_accuracy(spark, d):
    """MLlib's distributed solvers on 8-bit codes over all labelled rows."""
    vectors, out = _mllib_rows(spark, d, 64, 8), None
    train, test = vectors.where("part = 'train'"), vectors.where("part = 'test'")
    n = train.count()
    for loss in ("hinge", "logistic"):
        model = learn.fit_mllib(train, 0.1, loss, n, 50)
        scored = model.transform(test).select(F.lit(loss).alias("loss"), "y", (2 * F.col("prediction") - 1).cast("int").alias("pred"))
        out = scored if out is None else out.unionByName(scored)
    return evaluate.accuracy(out, "loss")


def language_one_vs_rest(spark, d):
    """All four languages, one model each, on 8-bit codes: (lang, n_test, accuracy)."""
    langs = ["de", "en", "es", "fr"]
    number = F.array_position(F.array(*map(F.lit, langs)), F.col("lang")) - 1
    vectors = _mllib_rows(spark, d, 64, 8).drop("label", "y").join(load_table(spark, d, "documents").select(F.col("doc_id").alias("id"), "lang"), "id").withColumn("label", number.cast("double"))
    model = learn.one_vs_rest(vectors.where("part = 'train' and label >= 0"), 0.1, 50)
    scored = model.transform(vectors.where("part = 'test' and label >= 0")).select("lang", F.col("label").alias("y"), F.col("prediction").alias("pred"))
    return evaluate.accuracy(scored, "lang")


# ---------------------------------------------------------------- stored permutations against two-universal hashing

#: Runs that are averaged, widths, bits and penalty; words of the dictionary up to which permutations are drawn (a task holds one at a time, some 20 bytes a word with the dictionary).
RUNS, FAMILY_K, FAMILY_B, FAMILY_C, MOST_WORDS = 50, (10, 50), 8, 1.0, 20_000_000
#: Runs that a task fits together at most, bytes of codes up to which it does (one run has 50 bytes a row, and is held whole, in fitting twice), rows and items that hash functions go over at a time.
RUNS_AT_ONCE, CODE_BYTES, HELD_ROWS, HELD_ITEMS = 25, 1 << 27, 50_000, 10_000_000


def word_sets(spark, d) -> tuple[DataFrame, int]:
    """(id, y, part, items) with items numbered 0..D-1 over the dictionary of the labelled documents, and D. A task holds the dictionary and one permutation of it, which is what bounds it; larger ones raise."""
    rows = load_table(spark, d, "documents").select("doc_id", "text", "lang").join(load_table(spark, d, "labels").select("doc_id").distinct(), "doc_id")
    y = F.when(F.col("lang") == "en", 1).otherwise(-1)
    named = sets.text_items(rows.select(F.col("doc_id").alias("id"), y.alias("y"), evaluate.split(F.md5(F.coalesce("text", F.lit(""))), TEST).alias("part"), "text"), "text", (1,))
    hashed = written(named.where(F.size("items") > 0))
    words = hashed.select(F.explode("items").alias("t")).distinct()
    if words.limit(MOST_WORDS + 1).count() > MOST_WORDS:
        raise ValueError(f"a dictionary of over {MOST_WORDS} words: permutations are not drawn for it")
    names = np.sort(words.toArrow().column("t").to_numpy())
    held = spark.sparkContext.broadcast(names)

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            items = b.column(3)
            flat = np.searchsorted(held.value, items.flatten().to_numpy(zero_copy_only=False))
            ends = np.concatenate([[0], np.cumsum(items.value_lengths().to_numpy(zero_copy_only=False))])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat, pa.int64()))], names=["id", "y", "part", "items"])

    return written(hashed.select("id", "y", "part", "items").mapInArrow(number, "id long, y int, part string, items array<long>")), len(names)


def family_images(family: str, run: int, k: int, d: int) -> Iterator[np.ndarray]:
    """k images of the dictionary, one at a time: permutations, or two-universal values."""
    if family == "permutation":
        rng = np.random.default_rng([7, run])
        for _ in range(k):
            yield rng.permutation(d).astype(np.int32)
        return
    f, t = TwoUniversal(k, seed=1000 + run), np.arange(d, dtype=np.int64)
    for a, b in f.numbers():
        yield f.numpy(t, np.int64(a), np.int64(b)).astype(np.int32)


def _items(lists: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
    """Items one row after the other, and the rows' ends."""
    return lists.flatten().to_numpy(zero_copy_only=False), np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64)


def _some(batches: Iterable[pa.RecordBatch]) -> Iterator[list[pa.RecordBatch]]:
    """Batches (id, y, part, items) that are held together: up to HELD_ROWS rows and HELD_ITEMS items, and one batch."""
    held, rows, items = [], 0, 0
    for b in (b for b in batches if b.num_rows):
        held.append(b)
        rows, items = rows + b.num_rows, items + len(b.column(3).flatten())
        if rows > HELD_ROWS or items > HELD_ITEMS:
            yield held
            held, rows, items = [], 0, 0
    if held:
        yield held


def permutation_vs_universal_accuracy(spark, d, runs: int = RUNS):
    """(family, loss, k, runs, accuracy, deviation): both families learn the same rows with the same solvers, runs times with new hash functions; models are fitted on all labelled training rows and score all test rows in each run.

    A row goes once as its codes (50 bytes a run) to each task that learns, some runs each; how runs are dealt does not change a run."""
    rows, size = word_sets(spark, d)
    n = {r.part: r["count"] for r in rows.groupBy("part").count().collect()}
    if not n.get("train"):
        return spark.createDataFrame([], "family string, loss string, k int, runs bigint, accuracy double, deviation double")
    losses, k_max = ("hinge", "logistic"), max(FAMILY_K)
    every = [(f, r) for f in ("permutation", "two_universal") for r in range(runs)]
    at_once = max(1, min(RUNS_AT_ONCE, CODE_BYTES // (sum(n.values()) * k_max)))
    groups = [every[i : i + at_once] for i in range(0, len(every), at_once)]

    def code(group: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for held in _some(batches):
            lists = [_items(b.column(3)) for b in held]
            codes = [np.empty((b.num_rows, len(groups[group]), k_max), np.uint8) for b in held]
            for r, (family, run) in enumerate(groups[group]):
                for j, one in enumerate(family_images(family, run, k_max, size)):
                    for own, (items, at) in zip(codes, lists, strict=True):
                        own[:, r, j] = np.minimum.reduceat(one[items], at[:-1]) & ((1 << FAMILY_B) - 1)
            for b, own in zip(held, codes, strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), group, np.int32)), *b.columns[:3], pa.array([x.tobytes() for x in own], pa.binary())], names=["task", "id", "y", "part", "codes"])

    def learned(table: pa.Table) -> pa.Table:
        own, order, at = groups[table.column("task")[0].as_py()], np.argsort(table.column("id").to_numpy()), 0
        place, codes = np.argsort(order), np.empty((len(order), len(own), k_max), np.uint8)
        for some in table.column("codes").chunks:
            codes[place[at : at + len(some)]] = np.frombuffer(b"".join(some.to_pylist()), np.uint8).reshape(-1, len(own), k_max)
            at += len(some)
        y, train = table.column("y").to_numpy().astype(np.float64)[order], pc.equal(table.column("part"), "train").to_numpy()[order]
        fitted, tested, out = codes[train], codes[~train], []
        for k in FAMILY_K:
            for loss in losses:
                w = learn.dual_coordinate_runs(fitted[:, :, :k], y[train], 1 << FAMILY_B, FAMILY_C, loss)
                for r, (family, run) in enumerate(own):
                    places = np.arange(k) * (1 << FAMILY_B) + (1 << FAMILY_B) - 1 - tested[:, r, :k].astype(np.int64)
                    out.append((family, run, loss, k, len(places), int((np.where(w[r][places].sum(1) >= 0, 1, -1) == y[~train]).sum())))
        names = ("family", "run", "loss", "k", "n", "good")
        return pa.Table.from_pylist([dict(zip(names, r, strict=True)) for r in out], pa.schema(list(zip(names, (pa.string(), pa.int32(), pa.string(), pa.int32(), pa.int64(), pa.int64()), strict=True))))

    coded = None
    for group in range(len(groups)):
        one = rows.select("id", "y", "part", "items").mapInArrow(lambda batches, group=group: code(group, batches), "task int, id long, y int, part string, codes binary")
        coded = one if coded is None else coded.unionByName(one)
    counted = coded.repartition(16 * len(groups), "task").groupBy("task").applyInArrow(learned, "family string, run int, loss string, k int, n long, good long").where("n > 0")
    return evaluate.mean_of_runs(counted.select("family", "loss", "k", "run", (F.col("good") / F.col("n")).alias("accuracy")), "family", "loss", "k")


# ---------------------------------------------------------------- loading, preprocessing, growth


def loading_and_preprocessing(spark, d, k: int = 500):
    """(step, seconds, hashes, hashes_per_s, ratio_to_text): reading the sets as interchange text and as Parquet, hashing them from text
    to items, and k minima of each in the vectorised and the row-expression form. Ratios are to the reading of the text."""
    folder = shared_dir(spark)
    items = written(sets.documents(spark, d).where(F.size("items") > 0))  # as many files as cores, for all steps alike
    tables.write_libsvm(items.select(F.lit(1).alias("y"), F.col("items").alias("active")), f"{folder}/text")
    n_items = items.agg(F.sum(F.size("items"))).first()[0] or 0
    steps = [
        ("load_text", 0, lambda: cost.time_load(spark, f"{folder}/text", sets.RANGE)),
        ("load_parquet", 0, lambda: cost.time_plan(items)),
        ("items_from_documents", 0, lambda: cost.time_plan(sets.documents(spark, d))),
        ("preprocess_vectorised", n_items * k, lambda: cost.time_preprocess(items, k)),
        ("preprocess_row_expression", n_items * k, lambda: cost.time_preprocess(items, k, "compiled")),
    ]
    took = [(name, measure(), hashes) for name, hashes, measure in steps]
    text = took[0][1]
    return spark.createDataFrame([(name, t, h, h / t if h else None, t / text) for name, t, h in took], "step string, seconds double, hashes bigint, hashes_per_s double, ratio_to_text double")


def growth_curve(spark, d, copies: tuple[int, ...] = (1, 2, 4, 8)):
    """(copies, rows, seconds, rows_per_s): signatures of the documents repeated with salted texts. Work a row must not grow."""
    out = []
    for n in copies:
        docs = load_table(spark, d, "documents").select("doc_id", "text", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("copy"))
        salted = docs.select((F.col("doc_id") * n + F.col("copy")).alias("id"), F.concat_ws(" ", "text", F.col("copy").cast("string")).alias("text"))
        salted = written(salted.repartition(spark.sparkContext.defaultParallelism))
        rows = salted.count()
        took = cost.time_plan(minwise.signature(sets.text_items(salted, "text"), TwoUniversal(16)).select("id", "sig"))
        out.append((n, rows, took, rows / took))
    return spark.createDataFrame(out, "copies int, rows bigint, seconds double, rows_per_s double")


NAMES = """loading_and_preprocessing growth_curve svm_accuracy_grid logistic_accuracy_grid svm_accuracy_half logistic_accuracy_half svm_bucket_vs_bbit logistic_bucket_vs_bbit
training_times stacked_accuracy raw_accuracy quality_accuracy toxic_accuracy equal_accuracy mllib_accuracy language_one_vs_rest
permutation_vs_universal_accuracy""".split()
QUERIES = {name: globals()[name] for name in NAMES}
