"""Language-model scores of whole documents.

Base score: smoothed word frequencies of the training documents. Model: a gated
recurrent network in numpy over the most frequent tokens, trained by truncated
backpropagation, with an output softmax factored into classes (class given
state, word given class and state). Other words form 64 kinds by their first and
last letters: the network predicts the kind, corpus counts the word within it,
so that every text has a proper probability.

Documents lie in lanes. Windows of some steps pass over all lanes at once, and
the state at a window's end starts the next, until a document ends: the score
is the log-likelihood of the complete document, however long.

Counts: each page sends each distinct token once (common.exchange). Training:
each task passes over all training documents of its pages once, starting from
the parameters of the round before; the parameters are averaged, weighted by
tokens, in groups of 64 until one is left. Each page is trained on in one
round, so all rounds are one pass over the corpus. Vocabulary and network have a
fixed size; what is counted and learned from grows with the corpus.

Defined results: a null or empty text is the end token alone; a null id counts
as held out; repeated rows are learned from and scored each; in an empty corpus
N = V = 0 and nothing is scored.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER_TABLE, REQUEST_ARROW, REQUEST_SCHEMA, Page, answers, buckets_for, exchange_rows, frugal, pages, requests, written

#: Words of the network's vocabulary in CLASSES classes of CLASS_SIZE; one further class holds the KINDS of other words.
CLASSES, CLASS_SIZE, KINDS = 64, 64, 64
HEAD = CLASSES * CLASS_SIZE
START, OUTPUTS = HEAD + KINDS, CLASSES + 1
HIDDEN, STEPS, WINDOW_TOKENS, LANES, ROUNDS, RATE = 16, 16, 8192, 512, 2, 0.05
#: Pages that the pass lays into lanes together.
GROUP = 4


def held_out(doc_id: int | None) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % 10 == 0


# ---------------------------------------------------------------- tokens of a page


class Tokens:
    """The tokens of a page's documents one after the other, each document closed by its end token (hash 0)."""

    def __init__(self, head: bytes, body: bytes):
        page = Page(head, body, LOWER_TABLE)
        self.ids, self.hash = page.ids, page.flat[1:]
        self.sizes = page.sizes + 1
        self.held = np.array([held_out(i) for i in page.ids], bool)
        self.kind = np.zeros(len(self.hash), np.uint8)
        self.kind[~page.end[1:]] = kinds(page.data, page.starts, page.ends)
        self.doc = np.repeat(np.arange(len(self.sizes)), self.sizes)


def kinds(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """32 groups of first letters, and whether the last byte is a letter: 64 kinds."""
    first = data[starts].astype(np.int64)
    a = np.where((first >= 97) & (first <= 122), first - 97, np.where(first >= 128, 26 + (data[np.minimum(starts + 1, len(data) - 1)] & 3), np.where((first >= 48) & (first <= 57), 30, 31)))
    last = data[ends - 1]
    return (2 * a + ~(((last >= 97) & (last <= 122)) | (last >= 128))).astype(np.uint8)


def distinct_tokens(t: Tokens) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct hashes, training counts times 256 plus kind, and where each token went."""
    order = np.argsort(t.hash)  # equal hashes are alike in all that is read of them
    s = t.hash[order]
    new = np.ones(len(s), bool)
    new[1:] = s[1:] != s[:-1]
    at = np.nonzero(new)[0]
    where = np.empty(len(s), np.int64)
    where[order] = np.cumsum(new) - 1
    count = np.bincount(where, weights=~t.held[t.doc], minlength=len(at)).astype(np.int64)
    return s[at], count * 256 + t.kind[order][at], where


# ---------------------------------------------------------------- vocabulary


@dataclass
class Vocabulary:
    """Hashes of the head words by frequency, with their counts; counts of the tail by kind; totals."""

    keys: np.ndarray
    counts: np.ndarray
    tail_tokens: np.ndarray
    tail_words: np.ndarray
    tokens: int
    words: int

    def table(self) -> list[tuple[int, np.ndarray]]:
        """Some tables from 16 bits of the hash to a head word; a word that finds its place taken goes to the next table."""
        out, left, shift = [], np.arange(len(self.keys)), 0
        while len(left) and shift <= 48:
            slot = ((self.keys[left] >> np.uint64(shift)) & np.uint64(0xFFFF)).astype(np.int64)
            t = np.full(65536, -1, np.int32)
            t[slot[::-1]] = left[::-1]
            out.append((shift, t))
            left = left[t[slot] != left]
            shift += 12
        return out

    def numbers(self, hashes: np.ndarray, kind: np.ndarray, table) -> np.ndarray:
        """Numbers of the tokens: head words 0.., kinds HEAD.."""
        out = HEAD + kind.astype(np.int32)
        for shift, t in table:
            at = t[((hashes >> np.uint64(shift)) & np.uint64(0xFFFF)).astype(np.int64)]
            ok = (at >= 0) & (self.keys[at] == hashes) if len(self.keys) else np.zeros(len(hashes), bool)
            out[ok] = at[ok]
        return out


# ---------------------------------------------------------------- network


class Network:
    """Diagonal gated recurrence h' = h + z (c - h), z = sigmoid(A[x] + u h), c = tanh(B[x] + v h); softmax over classes, then over a class."""

    NAMES = ("A", "B", "u", "v", "Wc", "bc", "Ww", "bw")

    def __init__(self, vocab: Vocabulary | None = None, blob: bytes | None = None):
        shapes = {"A": (START + 1, HIDDEN), "B": (START + 1, HIDDEN), "u": (HIDDEN,), "v": (HIDDEN,), "Wc": (HIDDEN, OUTPUTS), "bc": (OUTPUTS,), "Ww": (OUTPUTS, HIDDEN, CLASS_SIZE), "bw": (OUTPUTS, CLASS_SIZE)}
        self.p: dict[str, np.ndarray] = {}
        if blob is not None:
            at = 0
            for k in self.NAMES:
                n = int(np.prod(shapes[k]))
                self.p[k] = np.frombuffer(blob, np.float32, n, at).reshape(shapes[k]).copy()
                at += 4 * n
            return
        rng = np.random.default_rng(7)
        for k in self.NAMES:
            self.p[k] = (rng.standard_normal(shapes[k]) * 0.1).astype(np.float32)
        self.p["A"] -= 1.5  # slow gates at first: the state remembers
        count = np.zeros(OUTPUTS * CLASS_SIZE)
        count[: len(vocab.counts)] = vocab.counts
        count[HEAD:] = vocab.tail_tokens
        count = count.reshape(OUTPUTS, CLASS_SIZE) + 0.1
        self.p["Wc"] *= 0.1
        self.p["Ww"] *= 0.1
        self.p["bc"] = np.log(count.sum(1) / count.sum()).astype(np.float32)
        self.p["bw"] = np.log(count / count.sum(1, keepdims=True)).astype(np.float32)

    def blob(self) -> bytes:
        return b"".join(self.p[k].astype(np.float32).tobytes() for k in self.NAMES)

    # -- forward and backward over one window

    def run(self, x: np.ndarray, keep: np.ndarray, h: np.ndarray):
        """x, keep: steps x lanes. States before (reset where a document starts), gates, candidates, states after."""
        p, steps = self.p, len(x)
        az, bx = p["A"][x], p["B"][x]
        before, z, c, after = (np.empty(az.shape, np.float32) for _ in range(4))
        u, v = p["u"], p["v"]
        for t in range(steps):
            b = before[t]
            np.multiply(h, keep[t][:, None], out=b)
            zt = az[t]
            zt += u * b
            np.negative(zt, out=zt)
            np.exp(zt, out=zt)
            zt += 1
            np.reciprocal(zt, out=z[t])
            ct = bx[t]
            ct += v * b
            np.tanh(ct, out=c[t])
            h = after[t]
            np.subtract(c[t], b, out=h)
            h *= z[t]
            h += b
        return before, z, c, after

    def outputs(self, h: np.ndarray, target: np.ndarray, learn: bool):
        """Log-probabilities of the targets; with learn, gradients of their negative mean for states and output weights."""
        p, n = self.p, len(h)
        cls, word = target >> 6, target & 63
        # Outputs lie in rows and tokens in columns, so that largest values and sums go along whole rows.
        logits = p["Wc"].T @ h.T
        logits += p["bc"][:, None]
        logits -= logits.max(0)
        rows = np.arange(n)
        logp = logits[cls, rows]
        e = np.exp(logits, out=logits)
        total = e.sum(0)
        logp -= np.log(total)
        grads, dh = {}, None
        if learn:
            e /= total
            e[cls, rows] -= 1
            e /= n
            dh = e.T @ p["Wc"].T
            grads = {"Wc": (e @ h).T, "bc": e.sum(1), "Ww": np.zeros_like(p["Ww"]), "bw": np.zeros_like(p["bw"])}
        order = np.argsort(cls.astype(np.uint8), kind="stable")
        cuts = np.searchsorted(cls[order], np.arange(OUTPUTS + 1)).tolist()
        hs, ws = h[order], word[order]
        within, dsorted = np.empty(n, np.float32), np.empty((n, HIDDEN), np.float32) if learn else None
        for k in range(OUTPUTS):
            i, j = cuts[k], cuts[k + 1]
            if i == j:
                continue
            hk, wk, own = hs[i:j], ws[i:j], rows[: j - i]
            g = p["Ww"][k].T @ hk.T
            g += p["bw"][k][:, None]
            g -= g.max(0)
            top = g[wk, own]
            np.exp(g, out=g)
            s = g.sum(0)
            within[i:j] = top - np.log(s)
            if learn:
                s *= n
                g /= s
                g[wk, own] -= 1 / n
                dsorted[i:j] = g.T @ p["Ww"][k].T
                grads["Ww"][k] = (g @ hk).T
                grads["bw"][k] = g.sum(1)
        logp[order] += within
        if learn:
            dh[order] += dsorted
        return logp, dh, grads


@dataclass
class Lanes:
    """Documents laid into lanes, the longest lane first: token places by step and lane (-1: none), and where documents start."""

    place: np.ndarray
    first: np.ndarray
    active: np.ndarray


def lay(sizes: np.ndarray, begins: np.ndarray, width: int) -> Lanes:
    order = np.argsort(-sizes, kind="stable").tolist()
    heap = [(0, i) for i in range(max(1, min(width, len(order))))]
    rows: list[list[int]] = [[] for _ in heap]
    for d in order:
        load, lane = heapq.heappop(heap)
        rows[lane].append(d)
        heapq.heappush(heap, (load + int(sizes[d]), lane))
    loads = np.array([int(sizes[r].sum()) if r else 0 for r in rows])
    by = np.argsort(-loads, kind="stable")
    steps = int(loads.max(initial=0))
    place, first = np.full((steps, len(rows)), -1, np.int32), np.zeros((steps, len(rows)), bool)
    for lane, r in enumerate(by.tolist()):
        t = 0
        for d in rows[r]:
            n = int(sizes[d])
            place[t : t + n, lane] = np.arange(begins[d], begins[d] + n)
            first[t, lane] = True
            t += n
    return Lanes(place, first, (place >= 0).sum(1))


def windows(lanes: Lanes, numbers: np.ndarray):
    """Inputs, resets and places of each window of about WINDOW_TOKENS tokens, STEPS steps at least; lanes that have ended are left out from the next window on."""
    t = 0
    while t < len(lanes.place):
        k = int(lanes.active[t])
        steps = int(np.clip(WINDOW_TOKENS // k, STEPS, 256))
        place, first = lanes.place[t : t + steps, :k], lanes.first[t : t + steps, :k]
        real = place >= 0
        x = np.where(first | ~real, START, numbers[np.maximum(place - 1, 0)])
        yield x, (~first).astype(np.float32), place, real
        t += steps


def forward_scores(net: Network, lanes: Lanes, numbers: np.ndarray) -> np.ndarray:
    """Natural log-probability of each token."""
    out = np.zeros(len(numbers), np.float64)
    h = np.zeros((lanes.place.shape[1] if lanes.place.size else 0, HIDDEN), np.float32)
    held, at, n = [], [], 0

    def flush() -> None:
        where = np.concatenate(at)
        out[where] = net.outputs(np.concatenate(held), numbers[where], False)[0]

    for x, keep, place, real in windows(lanes, numbers):
        *_, after = net.run(x, keep, h[: x.shape[1]])
        h = after[-1]
        held.append(after[real])
        at.append(place[real])
        n += len(at[-1])
        if n >= 32_768:
            flush()
            held, at, n = [], [], 0
    if n:
        flush()
    return out


class Trainer:
    """Adagrad; rows of the input tables only where the window has their tokens."""

    def __init__(self, net: Network):
        self.net = net
        self.sq = {k: np.full(v.shape, 1e-8, np.float32) for k, v in net.p.items()}

    def dense(self, name: str, g: np.ndarray) -> None:
        self.sq[name] += g * g
        self.net.p[name] -= RATE * g / np.sqrt(self.sq[name])

    def rows(self, name: str, at: np.ndarray, g: np.ndarray) -> None:
        s = self.sq[name][at] + g * g
        self.sq[name][at] = s
        self.net.p[name][at] -= RATE * g / np.sqrt(s)

    def learn(self, lanes: Lanes, numbers: np.ndarray) -> None:
        net, p = self.net, self.net.p
        h = np.zeros((lanes.place.shape[1], HIDDEN), np.float32)
        for x, keep, place, real in windows(lanes, numbers):
            before, z, c, after = net.run(x, keep, h[: x.shape[1]])
            h = after[-1].copy()
            _, dout, grads = net.outputs(after[real], numbers[place[real]], True)
            dh = np.zeros(after.shape, np.float32)
            dh[real] = dout
            da, db = np.empty(z.shape, np.float32), np.empty(z.shape, np.float32)
            gate, cand = z * (1 - z) * (c - before), z * (1 - c * c)
            stay = 1 - z
            carry = np.zeros(h.shape, np.float32)
            for t in range(len(x) - 1, -1, -1):
                carry += dh[t]
                np.multiply(carry, gate[t], out=da[t])
                np.multiply(carry, cand[t], out=db[t])
                carry *= stay[t]
                carry += da[t] * p["u"]
                carry += db[t] * p["v"]
                carry *= keep[t][:, None]
            flat = x.ravel().astype(np.uint16)
            order = np.argsort(flat, kind="stable")
            s = flat[order]
            cut = np.nonzero(np.concatenate([[True], s[1:] != s[:-1]]))[0]
            both = np.concatenate([da.reshape(-1, HIDDEN), db.reshape(-1, HIDDEN)], axis=1)[order]
            sums = np.add.reduceat(both, cut, axis=0)
            at = s[cut].astype(np.int64)
            self.rows("A", at, sums[:, :HIDDEN])
            self.rows("B", at, sums[:, HIDDEN:])
            self.dense("u", (da * before).sum((0, 1)))
            self.dense("v", (db * before).sum((0, 1)))
            for k, g in grads.items():
                self.dense(k, g)


# ---------------------------------------------------------------- Spark


def note(keys: np.ndarray, group: np.ndarray, vals: np.ndarray) -> bytes:
    """Of a bucket: its most frequent tokens, and of all its tokens the counts and distinct numbers by kind."""
    total = np.bincount(group, weights=(vals >> 8).astype(float)).astype(np.int64)
    some = np.zeros(len(total), np.int64)
    some[group] = np.arange(len(group))
    key, kind = keys[some, 0], vals[some] & 255
    top = np.lexsort((key, -total))[:HEAD]
    top = top[total[top] > 0]
    by_tokens = np.bincount(kind, weights=total, minlength=KINDS).astype(np.int64)
    by_words = np.bincount(kind[total > 0], minlength=KINDS).astype(np.int64)
    return np.concatenate([by_tokens, by_words, key[top].view(np.int64), total[top], kind[top]]).tobytes()


def unnoted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for said in b.column(0).to_pylist():
            x = np.frombuffer(said, np.int64)
            key, total, kind = x[2 * KINDS :].reshape(3, -1)
            tokens, words = x[:KINDS], x[KINDS : 2 * KINDS]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.zeros(len(key), np.int8), np.ones(KINDS, np.int8)])), pa.array(np.concatenate([key, np.zeros(KINDS, np.int64)])), pa.array(np.concatenate([total, tokens])), pa.array(np.concatenate([kind, np.arange(KINDS)])), pa.array(np.concatenate([np.zeros(len(key), np.int64), words]))], names=["what", "key", "n", "kind", "words"])


def vocabulary(notes: DataFrame) -> Vocabulary:
    rows = written(notes.select("said").mapInArrow(unnoted, "what byte, key long, n long, kind long, words long"))
    # Partial results meet on an executor; the driver gets the head alone.
    head = written(rows.where("what = 0").orderBy(F.desc("n"), "key").limit(HEAD)).collect()
    tail = rows.where("what = 1").groupBy("kind").agg(F.sum("n").alias("n"), F.sum("words").alias("words")).collect()
    tokens, words = np.zeros(KINDS, np.int64), np.zeros(KINDS, np.int64)
    for r in tail:
        tokens[r.kind], words[r.kind] = r.n, r.words
    total, distinct_words = int(tokens.sum()), int(words.sum())
    for r in head:
        tokens[r.kind] -= r.n
        words[r.kind] -= 1
    return Vocabulary(np.array([r.key for r in head], np.int64).view(np.uint64), np.array([r.n for r in head], np.int64), tokens, words, total, distinct_words)


def train(packed: DataFrame, vocab: Vocabulary, rounds: int = ROUNDS) -> Network:
    net = Network(vocab)
    for r in range(rounds):
        start = net.blob()

        def work(batches: Iterator[pa.RecordBatch], start: bytes = start) -> Iterator[pa.RecordBatch]:
            own, table, seen = Trainer(Network(blob=start)), vocab.table(), 0
            for group in in_groups(batches):
                parts = [Tokens(head, body) for head, body in group]
                numbers = np.concatenate([vocab.numbers(t.hash, t.kind, table) for t in parts])
                sizes, held = np.concatenate([t.sizes for t in parts]), np.concatenate([t.held for t in parts])
                begins = np.cumsum(sizes) - sizes
                sizes, begins = sizes[~held], begins[~held]
                n = int(sizes.sum())
                width = int(np.clip(n // (STEPS * 150), 8, LANES))
                if n:
                    own.learn(lay(sizes, begins, width), numbers)
                seen += n
            if seen:
                yield pa.RecordBatch.from_arrays([pa.array([seen], pa.int64()), pa.array([own.net.blob()], pa.binary())], names=["n", "blob"])

        part = packed.where(F.pmod(F.xxhash64("ids"), F.lit(rounds)) == r) if rounds > 1 else packed  # by what a page holds, not by where it was made
        net = averaged(part.select("ids", "body").mapInArrow(frugal(work), "n long, blob binary")) or net
    return net


def in_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[list[tuple]]:
    group: list[tuple] = []
    for b in batches:
        for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
            group.append(row)
            if len(group) == GROUP:
                yield group
                group = []
    if group:
        yield group


def mean_blob(rows: list[tuple[int, bytes]]) -> tuple[int, bytes]:
    total = sum(n for n, _ in rows)
    acc = 0.0
    for n, blob in rows:
        acc = acc + np.frombuffer(blob, np.float32).astype(np.float64) * (n / total)
    return total, np.asarray(acc).astype(np.float32).tobytes()


def averaged(trained: DataFrame) -> Network | None:
    """Weighted mean of parameters, by groups of about 64 on executors until one is left: the driver gets one model, however many tasks trained."""

    def mean(pdf: pd.DataFrame) -> pd.DataFrame:
        n, blob = mean_blob(sorted(zip(pdf["n"].tolist(), map(bytes, pdf["blob"]), strict=True)))  # sums in one order
        return pd.DataFrame({"n": [n], "blob": [blob]})

    rows = written(trained)
    while (count := rows.count()) > 1:
        rows = written(rows.groupBy(F.pmod(F.xxhash64("n", "blob"), F.lit(-(-count // 64))).alias("g")).applyInPandas(mean, "n long, blob binary"))
    last = rows.first()
    return Network(blob=bytes(last.blob)) if last else None


RESULT = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def scores(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score: base-10 log-probabilities of whole texts."""
    packed = pages(docs, id_col, text_col)
    total = packed.agg(F.sum("n_words")).first()[0] or 0

    buckets = buckets_for(total // 5)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for number, head, body in zip(*(c.to_pylist() for c in b.columns), strict=True):
                keys, vals, _ = distinct_tokens(Tokens(head, body))
                yield pa.RecordBatch.from_pylist(requests(number, keys[:, None], vals, buckets), REQUEST_ARROW)

    raw = written(exchange_rows(packed.select("page", "ids", "body").mapInArrow(frugal(ask), REQUEST_SCHEMA), 1, count_all, note))
    vocab = vocabulary(raw.where("page < 0"))
    net = train(packed, vocab).blob()
    counted = packed.join(answers(raw.where("page >= 0")), "page", "left").select("ids", "body", "said")

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, table = Network(blob=net), vocab.table()
        whole = vocab.tokens + 0.1 * (vocab.words + 1)
        by_kind = vocab.tail_tokens + 0.1 * (vocab.tail_words + 1)
        for group in in_groups(batches):
            parts = [Tokens(head, body) for head, body, _ in group]
            count = np.concatenate([np.frombuffer(b"".join(said), np.int64)[distinct_tokens(t)[2]] for t, (_, _, said) in zip(parts, group, strict=True)])
            numbers = np.concatenate([vocab.numbers(t.hash, t.kind, table) for t in parts])
            sizes = np.concatenate([t.sizes for t in parts])
            begins = np.cumsum(sizes) - sizes
            base = np.log10((count + 0.1) / whole)
            logp = forward_scores(own, lay(sizes, begins, LANES), numbers)
            tail = numbers >= HEAD
            logp[tail] += np.log((count[tail] + 0.1) / by_kind[numbers[tail] - HEAD])
            yield pa.RecordBatch.from_arrays([
                pa.array([i for t in parts for i in t.ids], pa.int64()), pa.array(np.concatenate([t.held for t in parts])), pa.array(sizes),
                pa.array(np.add.reduceat((count > 0).astype(np.int64), begins)), pa.array(np.full(len(sizes), vocab.tokens, np.int64)),
                pa.array(np.add.reduceat(base, begins)), pa.array(np.add.reduceat(logp, begins) / np.log(10)),
            ], names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return counted.mapInArrow(frugal(finish), RESULT)


def count_all(group: np.ndarray, vals: np.ndarray) -> np.ndarray:
    """Training count of each key over all pages."""
    return np.bincount(group, weights=(vals >> 8).astype(float))[group].astype(np.int64)
