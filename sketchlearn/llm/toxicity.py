"""Toxicity by a classifier chain.

Categories are predicted one after the other: the linear model of a category
gets the hashed words and word beginnings of the text and, as further features,
the log-odds of the categories before it. In training these come from models
that did not see the row (out of fold), so that later models meet earlier
predictions as good or bad as they will be on new texts.

The chain is fitted in one task on a bounded sample of labelled rows
(`max_rows`, chosen by a hash of the id, a documented bound), whose texts become
vectors where they are read; scoring reads every text whole, in one map-only pass.

Defined results: a null or empty text scores as a text without words; labels
that are null, or of documents that are not there, are unused; of repeated
labels of a document the higher counts; with fewer than two classes in a
category its probability is the share of ones; without labels it is 0.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import alnum_words, few_rows_a_batch, frugal, frugal_group, written

#: Order of the chain; each is a column of `labels` turned into 0/1 by LABELS.
CATEGORIES = ("low_quality", "toxic")
BITS, PREFIXES, FOLDS, MAX_ROWS = 18, (4, 5, 6, 7), 3, 6_000
#: A feature tells something if it is in so many rows at least and its chi-square is so high.
MIN_ROWS, MIN_CHI = 4, 18.0
CACHE = 100_000


class Features(dict):
    """Hashed features of a word: itself, and its beginnings of some lengths (in characters)."""

    def __missing__(self, word: bytes) -> tuple[int, ...]:
        text, mask = word.decode("utf-8", "replace"), (1 << BITS) - 1
        keys = [b"=" + word, *(b"^" + text[:n].encode() for n in PREFIXES if len(text) > n)]
        value = tuple(xxhash.xxh3_64_intdigest(k) & mask for k in keys)
        if len(self) < CACHE:
            self[word] = value
        return value


def vector(text: str | None, cache: Features) -> tuple[np.ndarray, np.ndarray]:
    """Feature numbers and values: log(1 + count), scaled by the text's length."""
    words = alnum_words(text)
    flat = [i for w in words for i in cache[w]]
    if not flat:
        return np.zeros(0, np.int32), np.zeros(0, np.float32)
    ids, n = np.unique(np.array(flat, np.int32), return_counts=True)
    return ids, (np.log1p(n) * weight(len(words))).astype(np.float32)


def weight(n_words: int) -> float:
    return 4.0 / np.log2(8 + n_words)


@dataclass
class Linear:
    """w over kept features, one weight for each earlier category, and an intercept."""

    w: np.ndarray
    chain: np.ndarray
    bias: float

    def logit(self, ids: np.ndarray, vals: np.ndarray, earlier: list[float]) -> float:
        return float(self.w[ids] @ vals) + float(self.chain @ np.asarray(earlier)) + self.bias if len(self.chain) else float(self.w[ids] @ vals) + self.bias


class Rows:
    """Sparse rows side by side."""

    def __init__(self, rows: list[tuple[np.ndarray, np.ndarray]]):
        self.sizes = np.array([len(i) for i, _ in rows], np.int64)
        self.ids = np.concatenate([i for i, _ in rows]) if rows else np.zeros(0, np.int32)
        self.vals = np.concatenate([v for _, v in rows]) if rows else np.zeros(0, np.float32)
        self.row = np.repeat(np.arange(len(rows), dtype=np.int32), self.sizes)

    def times(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, self.vals * w[self.ids], len(self.sizes))

    def transposed(self, g: np.ndarray) -> np.ndarray:
        return np.bincount(self.ids, self.vals * g[self.row], 1 << BITS)


def sigmoid(z):
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def telling(rows: Rows, y: np.ndarray) -> np.ndarray:
    """Features whose presence goes with the class beyond chance: chi-square over 2 x 2 counts, for features of at least MIN_ROWS rows."""
    n, ones = len(y), y.sum()
    df = np.bincount(rows.ids, minlength=1 << BITS).astype(float)
    a = np.bincount(rows.ids, y[rows.row], 1 << BITS)
    with np.errstate(divide="ignore", invalid="ignore"):
        chi = n * (a * n - df * ones) ** 2 / (df * (n - df) * ones * (n - ones))
    return (df >= MIN_ROWS) & (np.nan_to_num(chi, posinf=0) >= MIN_CHI)


def fit_linear(rows: Rows, earlier: np.ndarray, y: np.ndarray, steps: int = 150, l2: float = 1e-3, each: np.ndarray | None = None) -> Linear:
    """Logistic regression over the telling features, classes weighted 1 to the root of their ratio, by Nesterov's accelerated gradient with the step that the features' norms allow. each: how many rows of the table a row stands for."""
    n, k = len(y), earlier.shape[1]
    ones = int(y.sum())
    if ones in (0, n):
        share = (ones + 0.5) / (n + 1) if n else 0.0
        return Linear(np.zeros(1 << BITS, np.float32), np.zeros(k), float(np.log(share / (1 - share))) if n else -30.0)
    held = telling(rows, y)
    kept = held[rows.ids]
    slot = np.cumsum(held) - 1
    row, col, val, width = rows.row[kept], slot[rows.ids[kept]], rows.vals[kept].astype(float), int(held.sum())
    side = np.concatenate([earlier / 10, np.ones((n, 1))], axis=1)
    each = np.ones(n) if each is None else each
    c = each * np.where(y == 1, np.sqrt((each @ (1 - y)) / (each @ y)), 1.0) / each.sum()
    # The largest eigenvalue of the weighted Gram matrix, by power iteration, bounds the step.
    a, b = np.ones(width), np.ones(k + 1)
    norm = 1.0
    for _ in range(12):
        z = c * (np.bincount(row, val * a[col], n) + side @ b)
        a, b = np.bincount(col, val * z[row], width), side.T @ z
        norm = np.sqrt(a @ a + b @ b) or 1.0
        a, b = a / norm, b / norm
    step = 1 / (0.3 * norm + l2)
    w, u = np.zeros(width), np.zeros(k + 1)
    w0, u0 = w, u
    for t in range(steps):
        beta = t / (t + 3)
        wy, uy = w + beta * (w - w0), u + beta * (u - u0)
        g = (sigmoid(np.bincount(row, val * wy[col], n) + side @ uy) - y) * c
        w0, u0 = w, u
        w = wy - step * (np.bincount(col, val * g[row], width) + l2 * wy)
        u = uy - step * (side.T @ g + l2 * np.append(uy[:-1], 0))
    full = np.zeros(1 << BITS, np.float32)
    full[held] = w
    return Linear(full, u[:-1] / 10, float(u[-1]))


@dataclass
class Chain:
    categories: tuple[str, ...]
    models: list[Linear]
    thresholds: list[float]

    def logits(self, text: str | None, cache: Features) -> list[float]:
        ids, vals = vector(text, cache)
        out: list[float] = []
        for m in self.models:
            out.append(float(np.clip(m.logit(ids, vals, out), -30, 30)))
        return out


def fit_chain(texts: list[str | None], keys: list[int], y: np.ndarray, categories: tuple[str, ...] = CATEGORIES, each: np.ndarray | None = None) -> Chain:
    """y: rows x categories of 0/1. Rows of the same key (a hash of the text) fall into one fold, so a copy never predicts its twin.

    each: how many labelled rows a row stands for. Thresholds: of the out-of-fold log-odds, the cut with the highest F1 over all rows that the sample stands for.
    """
    cache = Features()
    return fit_vectors([vector(t, cache) for t in texts], keys, y, categories, each)


def fit_vectors(vectors: list[tuple[np.ndarray, np.ndarray]], keys: list[int], y: np.ndarray, categories: tuple[str, ...] = CATEGORIES, each: np.ndarray | None = None) -> Chain:
    """fit_chain() of texts that are vectors already."""
    each = np.ones(len(vectors)) if each is None else each
    fold = np.array([k % FOLDS for k in keys], np.int64)
    everything, earlier = Rows(vectors), np.zeros((len(vectors), 0))
    models, cuts = [], []
    for j in range(len(categories)):
        out = np.zeros(len(vectors))
        for f in range(FOLDS):
            a, b = np.nonzero(fold != f)[0], np.nonzero(fold == f)[0]
            if len(b):
                part = fit_linear(Rows([vectors[i] for i in a]), earlier[a], y[a, j], each=each[a])
                out[b] = np.clip(Rows([vectors[i] for i in b]).times(part.w) + earlier[b] @ part.chain + part.bias, -30, 30)
        models.append(fit_linear(everything, earlier, y[:, j], each=each))
        cuts.append(best_cut(out, y[:, j], each))
        earlier = np.concatenate([earlier, out[:, None]], axis=1)
    return Chain(categories, models, cuts)


def best_cut(score: np.ndarray, y: np.ndarray, each: np.ndarray | None = None) -> float:
    """Midway between the neighbours at which F1 is highest; nothing is positive if there are no ones."""
    if not y.sum():
        return float("inf")
    order = np.argsort(-score, kind="stable")
    each = np.ones(len(y)) if each is None else each
    hit = np.cumsum((each * y)[order])
    f1 = 2 * hit / (np.cumsum(each[order]) + each @ y)
    last = np.append(score[order][1:] != score[order][:-1], True)  # equal scores fall on one side
    at = int(np.argmax(np.where(last, f1, -1)))
    s = score[order]
    return float((s[at] + s[at + 1]) / 2) if at + 1 < len(s) else float(s[at] - 1)


def labelled_sample(docs: DataFrame, labels: DataFrame, max_rows: int) -> DataFrame:
    """At most max_rows labelled rows, by a hash of the id, toxic ones first up to half of them; each: how many labelled rows of its class a row stands for, so that the sample's make-up does not follow the table's size.

    The sample is drawn from the labels alone, so that only its ids (max_rows at
    most, which bounds the broadcast) meet the documents and no text is shuffled.
    """
    said = labels.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(1 - F.col("quality")).alias("low_quality"), F.max("toxic").alias("toxic")).where("doc_id is not null and low_quality is not null and toxic is not null")
    total = {r.toxic: r["count"] for r in said.where("toxic in (0, 1)").groupBy("toxic").count().collect()}
    by_hash = lambda toxic, n: said.where(F.col("toxic") == toxic).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n).withColumn("each", F.lit(max(1.0, total.get(toxic, 0) / max(n, 1))))
    chosen = by_hash(1, max_rows // 2).unionByName(by_hash(0, max_rows - max_rows // 2))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id")
    return rows.withColumn("key", F.xxhash64("text"))


def vectorised(sample: DataFrame) -> DataFrame:
    """(key, doc_id, low_quality, toxic, each, ids, vals): the texts as sparse vectors, made where they are read."""
    names = ["key", "doc_id", *CATEGORIES, "each"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = Features()
        for b in batches:
            made = [vector(t, cache) for t in b.column(len(names)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(names)], pa.array([i.astype(np.int32).tobytes() for i, _ in made], pa.binary()), pa.array([v.tobytes() for _, v in made], pa.binary())], names=[*names, "ids", "vals"])

    wide = sample.select("key", "doc_id", *(F.col(c).cast("double").alias(c) for c in CATEGORIES), F.col("each").cast("double").alias("each"), "text")
    return wide.mapInArrow(frugal(run), "key long, doc_id long, " + "".join(f"{c} double, " for c in CATEGORIES) + "each double, ids binary, vals binary")


def fitted(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS) -> Chain:
    """The chain, fitted in one task on the sample's vectors (max_rows at most); the driver gets the model alone."""
    few_rows_a_batch(docs.sparkSession)
    sample = written(vectorised(labelled_sample(docs, labels, max_rows)).orderBy("key", "doc_id", "ids").limit(max_rows))

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["key", "doc_id"], kind="stable", ignore_index=True)
        vectors = [(np.frombuffer(i, np.int32), np.frombuffer(v, np.float32)) for i, v in zip(pdf["ids"], pdf["vals"], strict=True)]
        chain = fit_vectors(vectors, [int(k) & 0x7FFFFFFF for k in pdf["key"]], pdf[list(CATEGORIES)].to_numpy(np.float64), each=pdf["each"].to_numpy(np.float64))
        return pd.DataFrame({"chain": [pickle.dumps(chain)]})

    made = sample.groupBy().applyInPandas(frugal_group(fit), "chain binary").collect()
    return pickle.loads(bytes(made[0].chain)) if made else fit_vectors([], [], np.zeros((0, len(CATEGORIES))))


def classify(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS, train_docs: DataFrame | None = None) -> DataFrame:
    """One row a document: doc_id, p_<category> for each category, and rejected (the last category's log-odds pass their cut)."""
    return score(docs, fitted(docs if train_docs is None else train_docs, labels, max_rows))


def score(docs: DataFrame, chain: Chain) -> DataFrame:
    held = docs.sparkSession.sparkContext.broadcast(chain)  # 2^BITS weights a category: a fixed size
    names = ["doc_id", *(f"p_{c}" for c in chain.categories), "rejected"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, cache = held.value, Features()
        for b in batches:
            z = np.array([model.logits(t, cache) for t in b.column(1).to_pylist()]).reshape(-1, len(model.categories))
            p = sigmoid(z)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(p[:, j]) for j in range(p.shape[1])), pa.array(z[:, -1] > model.thresholds[-1])], names=names)

    schema = "doc_id long, " + "".join(f"p_{c} double, " for c in chain.categories) + "rejected boolean"
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(frugal(run), schema)


def without_toxic(docs: DataFrame, labels: DataFrame, text_col: str = "text", max_rows: int = MAX_ROWS) -> DataFrame:
    """The rows of docs, all their columns, that the chain does not reject."""
    held, at = docs.sparkSession.sparkContext.broadcast(fitted(docs, labels, max_rows)), docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, cache = held.value, Features()
        for b in batches:
            yield b.filter(pa.array([model.logits(t, cache)[-1] <= model.thresholds[-1] for t in b.column(at).to_pylist()], pa.bool_()))

    return docs.mapInArrow(frugal(run), docs.schema)
