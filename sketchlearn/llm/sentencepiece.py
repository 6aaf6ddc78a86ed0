"""SentencePiece encoding and decoding on a relational lattice.

Texts are normalised as the model says (a leading meta blank, blanks as meta
blanks) and cut wherever no piece spans the two characters: a best path passes
through every such place, so the units between them can be encoded apart, each
distinct unit once.

The lattice of the units is relational: substrings up to the longest piece are
exploded, equi-joined to the piece table, and grouped by unit; Spark's aggregate
folds the edges, in the order of their ends, into best scores and back pointers
(Viterbi; of equal scores the longer last piece stays). A character without a
piece is an edge of its own, with the unknown score, and becomes bytes.

Texts get the ids of their units from a head of frequent units, of fixed size,
at every task, and by a look-up by key range for all others.

The path is the one of highest summed score over the model's pieces: the unigram
rule of SentencePiece. For a model file of the merge (BPE) kind this is not the
merge order's segmentation; both decode to the same text.

Defined results: a null or empty text has no ids; a text that holds the meta
blank itself decodes to blanks there; lone surrogates can't come from UTF-8;
repeated rows are answered each.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from pathlib import Path

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import REQUEST_ARROW, REQUEST_SCHEMA, answers, buckets_for, few_rows_a_batch, frugal, frugal_group, page_rows, requests, span_hashes, text_of, unpack_rows, written

META = "▁"
#: Units in the head that goes to every task; characters up to which a unit's lattice is relational (longer ones, which no language has, are folded by the same rule in Python).
HEAD_UNITS, LONG_UNIT = 262_144, 200
#: Places of a task's memory of units that it has sent: one unit each, the last.
REMEMBERED = 1 << 20
#: Characters of a page: its arrays are many times as large.
PAGE_CHARS = 600_000
#: Bytes of text for each partition of the distinct units, and partitions at most.
UNIT_CHARS, MOST_PARTS = 8_000_000, 4_000
#: Characters that are looked at together when a page is cut into units.
AT_ONCE = 1 << 17
#: Page number of rows that offer units of the table rather than ask.
OFFER = -(1 << 63)


class Spans:
    """Tells of two neighbouring characters whether some piece can span them where they stand: a piece of the two, or a longer piece that holds three in a row around them."""

    def __init__(self, pieces: list[str]):
        chars = sorted({c for p in pieces for c in p})
        number = {c: i + 1 for i, c in enumerate(chars)}
        self.width = k = len(chars) + 1
        self.cls = np.zeros(0x110000, np.uint16)  # 0: in no piece of two or more
        self.cls[[ord(c) for c in chars]] = np.arange(1, k)
        self.two, self.three = np.zeros((k, k), bool), np.zeros(k**3 // 8 + 1, np.uint8) if k <= 2048 else None
        for p in pieces:
            n = [number[c] for c in p]
            if len(n) == 2 or self.three is None:
                for x, y in zip(n[:-1], n[1:], strict=True):
                    self.two[x, y] = True
            else:
                for x, y, z in zip(n[:-2], n[1:-1], n[2:], strict=True):
                    key = (x * k + y) * k + z
                    self.three[key >> 3] |= 1 << (key & 7)

    def cuts(self, code: np.ndarray) -> np.ndarray:
        """For each place before, between and after the characters: no piece spans it. Looks at AT_ONCE characters at a time."""
        cut, n = np.ones(len(code) + 1, bool), len(code)
        for at in range(0, n - 1, AT_ONCE):
            # Places at+1 .. at+AT_ONCE: with a character more on either side a triple around each of them is seen whole.
            low, high = max(0, at - 1), min(n, at + AT_ONCE + 2)
            c = self.cls[code[low:high]]
            spanned = self.two[c[:-1], c[1:]]
            if self.three is not None and len(c) > 2:
                w = c.astype(np.int32 if self.width**3 < 1 << 31 else np.int64)
                key = (w[:-2] * self.width + w[1:-1]) * self.width + w[2:]
                held = ((self.three[key >> 3] >> (key & 7).astype(np.uint8)) & 1).astype(bool)
                spanned[1:] |= held
                spanned[:-1] |= held
            end = min(n, at + AT_ONCE + 1)
            cut[at + 1 : end] = ~spanned[at - low : end - low - 1]
        return cut


@dataclass
class Model:
    """The piece table of a model."""

    pieces: list[str]
    scores: list[float]
    normal: list[bool]
    byte_of: dict[int, int]
    unknown_score: float

    @staticmethod
    def load(path: str) -> Model:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        normal = [not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)) for i in range(n)]
        scores = [sp.get_score(i) for i in range(n)]
        byte_of = {int(sp.id_to_piece(i)[3:5], 16): i for i in range(n) if sp.is_byte(i)}
        return Model([sp.id_to_piece(i) for i in range(n)], scores, normal, byte_of, min(s for s, x in zip(scores, normal, strict=True) if x) - 10)

    def table(self) -> dict[str, tuple[int, float]]:
        return {p: (i, float(s)) for i, (p, s, x) in enumerate(zip(self.pieces, self.scores, self.normal, strict=True)) if x}

    def longest(self) -> int:
        return max(len(p) for p, x in zip(self.pieces, self.normal, strict=True) if x)

    def spans(self) -> Spans:
        return Spans([p for p, x in zip(self.pieces, self.normal, strict=True) if x and len(p) > 1])

    def bytes_table(self) -> tuple[np.ndarray, np.ndarray]:
        """Bytes of all pieces in a row, and where each starts."""
        back = {i: bytes([b]) for b, i in self.byte_of.items()}
        raw = [back.get(i, p.encode() if x else b"") for i, (p, x) in enumerate(zip(self.pieces, self.normal, strict=True))]
        return np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(x) for x in raw])])

    def expand(self, ids: list[int]) -> list[int]:
        """Unknown characters (-1 minus their code point) as byte pieces."""
        if min(ids, default=0) >= 0:
            return ids
        return [y for i in ids for y in ([i] if i >= 0 else [self.byte_of.get(b, 0) for b in chr(-1 - i).encode("utf-8", "surrogatepass")])]


# ---------------------------------------------------------------- units


def normalised(text: str | None) -> str:
    return META + text.replace(" ", META) if text else ""


class Units:
    """The units of a page's texts."""

    def __init__(self, head: bytes, body: bytes, spans: Spans):
        self.ids, sizes, raw = unpack_rows(head, body)
        self.texts = [None if t is None else t.decode("utf-8", "surrogatepass") for t in text_of(sizes, raw)]
        parts = [normalised(t) for t in self.texts]
        self.all = "".join(parts)
        code = np.frombuffer(self.all.encode("utf-32-le", "surrogatepass"), np.uint32)
        self.doc_start = np.cumsum([0, *map(len, parts)])
        cut = spans.cuts(code)
        cut[self.doc_start] = True
        edge = np.nonzero(cut)[0]
        self.starts, self.ends = (edge[:-1], edge[1:]) if len(code) else (edge[:0], edge[:0])
        self.hash = span_hashes(code, self.starts, self.ends)
        self.first_unit = np.searchsorted(self.starts, self.doc_start)


def _slots(hashes: np.ndarray, turn: int, size: int) -> np.ndarray:
    """Places in the table of a turn: the hash times an odd number of that turn, its upper bits."""
    odd = np.uint64(xxhash.xxh3_64_intdigest(turn.to_bytes(4, "little")) | 1)
    return ((hashes * odd) >> np.uint64(65 - size.bit_length())).astype(np.int64)


def probe_tables(keys: np.ndarray) -> list[np.ndarray]:
    """Tables from some bits of a hash to a key's place; keys whose place is taken go to the next table, which is smaller, until every key has a place."""
    out, left = [], np.sort(np.unique(keys, return_index=True)[1])
    while len(left):
        size = 1 << min(20, max(8, int(4 * len(left)).bit_length()))
        slot = _slots(keys[left], len(out), size)
        t = np.full(size, -1, np.int32)
        t[slot[::-1]] = left[::-1]
        out.append(t)
        left = left[t[slot] != left]
    return out


def probe(hashes: np.ndarray, keys: np.ndarray, tables: list[np.ndarray]) -> np.ndarray:
    """Places of the hashes among the keys, -1: not there."""
    found = np.full(len(hashes), -1, np.int64)
    for turn, t in enumerate(tables):
        at = t[_slots(hashes, turn, len(t))]
        ok = (at >= 0) & (keys[np.maximum(at, 0)] == hashes)
        found[ok] = at[ok]
    return found


def ragged(values: np.ndarray, at: np.ndarray, n: np.ndarray) -> np.ndarray:
    """values[at[i] : at[i] + n[i]] for all i in a row."""
    total = int(n.sum())
    return values[np.repeat(at - (np.cumsum(n) - n), n) + np.arange(total)]


# ---------------------------------------------------------------- lattice


def viterbi(unit: str, pieces: dict[str, tuple[int, float]], longest: int, unknown: float) -> list[int]:
    """The same best path in Python: for units longer than LONG_UNIT, and for tests."""
    n = len(unit)
    best, back = [0.0] + [None] * n, [(0, 0)] * (n + 1)
    for end in range(1, n + 1):
        for start in range(max(0, end - longest), end):
            hit = pieces.get(unit[start:end])
            if hit is None and end - start == 1:
                hit = (-1 - ord(unit[start]), unknown)
            if hit is not None and best[start] is not None and (best[end] is None or best[start] + hit[1] > best[end]):
                best[end], back[end] = best[start] + hit[1], (start, hit[0])
    ids, at = [], n
    while at:
        at, i = back[at]
        ids.append(i)
    return ids[::-1]


#: Edges in the order of their ends: the score of each prefix grows by the best edge that ends there; then the back pointers are followed from the end.
_FOLD = """aggregate(
  sort_array(concat(edges, transform(array_except(sequence(1, length(unit)), transform(filter(edges, e -> e.stop - e.start = 1), e -> e.stop)),
    i -> named_struct('stop', i, 'start', i - 1, 'id', -1 - ascii(substring(unit, i, 1)), 'score', {unknown})))),
  array(named_struct('score', cast(0 as double), 'start', -1, 'id', 0)),
  (best, e) -> if(size(best) <= e.stop,
    array_append(best, named_struct('score', best[e.start].score + e.score, 'start', e.start, 'id', e.id)),
    if(best[e.start].score + e.score > best[e.stop].score,
      array_append(slice(best, 1, e.stop), named_struct('score', best[e.start].score + e.score, 'start', e.start, 'id', e.id)),
      best)),
  best -> aggregate(best, named_struct('at', size(best) - 1, 'ids', cast(array() as array<int>)),
    (path, step) -> if(path.at = 0, path, named_struct('at', best[path.at].start, 'ids', array_prepend(path.ids, best[path.at].id))),
    path -> path.ids))"""


def encode_units(units: DataFrame, model: Model) -> DataFrame:
    """units: (hash, unit, ...) with distinct units. Adds ids array<int>; unknown characters are -1 minus their code point."""
    spark, longest = units.sparkSession, model.longest()
    rows = [(p, i, float(s)) for i, (p, s, x) in enumerate(zip(model.pieces, model.scores, model.normal, strict=True)) if x]
    if len(rows) > 1_000_000:
        raise ValueError("a piece table of over a million rows is not broadcast")
    pieces = spark.createDataFrame(pd.DataFrame(rows, columns=["piece", "id", "score"]), "piece string, id int, score double")
    # How long a piece can be that begins with three given characters: most places of a unit begin none, and offer no longer substrings.
    first = pd.DataFrame({"prefix": [p[:3] for p, _, _ in rows if len(p) >= 3], "reach": [len(p) for p, _, _ in rows if len(p) >= 3]})
    reach = spark.createDataFrame(first.groupby("prefix", as_index=False)["reach"].max(), "prefix string, reach int")
    # A long unit has one row here and no lattice; both kinds come out of one reading of the texts.
    fits = F.length("unit") <= LONG_UNIT
    starts = units.withColumn("start", F.explode(F.when(fits, F.sequence(F.lit(1), F.length("unit"))).otherwise(F.array(F.lit(1)))))
    starts = starts.join(F.broadcast(reach), F.expr("substring(unit, start, 3)") == F.col("prefix"), "left")
    sizes = F.when(fits, F.expr("sequence(1, least(coalesce(reach, 2), length(unit) - start + 1))")).otherwise(F.array(F.lit(1)))
    substrings = starts.select("unit", "hash", "n", "start", F.explode(sizes).alias("size"))
    edges = substrings.join(F.broadcast(pieces), F.expr("substring(unit, start, size)") == F.col("piece"), "left").where("id is not null or (start = 1 and size = 1)")  # a row for each unit at least
    grouped = edges.groupBy("unit", "hash", "n").agg(F.collect_list(F.when(F.col("id").isNotNull(), F.struct((F.col("start") + F.col("size") - 1).alias("stop"), (F.col("start") - 1).alias("start"), "id", "score"))).alias("edges"))
    folded = grouped.select("hash", "n", F.when(~fits, F.col("unit")).alias("long"), F.when(fits, F.expr(_FOLD.format(unknown=f"cast({model.unknown_score!r} as double)"))).alias("ids"))
    table = {p: (i, s) for p, i, s in rows}

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.column(2).null_count < b.num_rows:
                ids = [viterbi(u, table, longest, model.unknown_score) if u is not None else x for u, x in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True)]
                b = pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(ids, pa.list_(pa.int32()))], names=["hash", "n", "long", "ids"])
            yield b.select(["hash", "n", "ids"])

    return folded.mapInArrow(frugal(fold), "hash long, n long, ids array<int>")


# ---------------------------------------------------------------- Spark


class Paged:
    """Texts cut into pages wherever they are read, in the Python worker that uses the pages. A page is named by what it holds: one that a second
    reading cuts otherwise (other executors, other splits) finds no answers under its name, and its units are encoded where it is. Rows that come
    out of a shuffle have no fixed order and are written first."""

    def __init__(self, docs: DataFrame, id_col: str, text_col: str):
        few_rows_a_batch(docs.sparkSession)
        rows = docs.select(F.col(id_col).cast("long"), F.col(text_col).cast("string"))
        self.rows = written(rows) if "Exchange" in rows._jdf.queryExecution().executedPlan().toString() else rows

    def characters(self) -> int:
        return self.rows.agg(F.sum(F.octet_length(self.rows.columns[1]))).first()[0] or 0

    def map(self, fn, schema: str) -> DataFrame:
        return self.rows.mapInArrow(frugal(lambda batches: fn(page_rows(batches, None, PAGE_CHARS))), schema)


def distinct_units(packed: Paged, model: Model) -> DataFrame:
    """(unit, hash, n): each distinct unit of all texts; n weighs how often it is met."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spans = model.spans()
        sent = np.zeros(REMEMBERED, np.uint64)
        for b in batches:
            for head, body in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                u = Units(head, body, spans)
                keys, at, n = np.unique(u.hash, return_index=True, return_counts=True)
                place = (keys % np.uint64(REMEMBERED)).astype(np.int64)
                new = sent[place] != keys
                keys, at, n, place = keys[new], at[new], n[new], place[new]
                sent[place] = keys
                text, s, e = u.all, u.starts[at].tolist(), u.ends[at].tolist()
                yield pa.RecordBatch.from_arrays([pa.array([text[x:y] for x, y in zip(s, e, strict=True)], pa.string()), pa.array(keys.view(np.int64)), pa.array(n.astype(np.int64))], names=["unit", "hash", "n"])

    # Many small partitions: a task sorts the edges of its units.
    parts = int(np.clip(packed.characters() // UNIT_CHARS, 16, MOST_PARTS))
    return packed.map(send, "unit string, hash long, n long").repartition(parts, "hash").groupBy("unit", "hash").agg(F.sum("n").alias("n"))


RESULT = "doc_id long, n_tokens long, ids array<int>, round_trip boolean"


def encode(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids, round_trip (the ids decode to the text)."""
    spark = docs.sparkSession
    model = Model.load(model_path)
    packed = Paged(docs, id_col, text_col)
    coded = written(encode_units(distinct_units(packed, model), model), spark)
    n_units = coded.count()
    top = coded.orderBy(F.desc("n"), "hash").limit(HEAD_UNITS).select("hash", "ids").toArrow()  # a fixed number of units
    ids = [model.expand(x) for x in top.column("ids").to_pylist()]
    keys = top.column("hash").to_numpy().view(np.uint64).copy() if len(ids) else np.zeros(0, np.uint64)
    sizes = np.array([len(x) for x in ids], np.int64)
    head = spark.sparkContext.broadcast((keys, np.cumsum(sizes) - sizes, sizes, np.array([y for x in ids for y in x], np.int32)))
    buckets = buckets_for(n_units)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spans = model.spans()
        own = head.value[0]
        tables = probe_tables(own)
        for b in batches:
            for number, h, body in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                hashes = Units(h, body, spans).hash
                tail = np.unique(hashes[probe(hashes, own, tables) < 0])
                yield pa.RecordBatch.from_pylist(requests(number, tail[:, None], np.zeros(len(tail), np.int64)[:0], buckets) or [{"page": number, "bucket": 0, "keys": b"", "vals": b""}], REQUEST_ARROW)

    def offer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The table's rows by bucket: keys, and in vals the number of ids and the ids of each."""
        for b in batches:
            keys = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            lists = [np.array(model.expand(x), np.int32) for x in b.column(1).to_pylist()]
            order = np.argsort(keys)
            edges = np.array([(i << 64) // buckets for i in range(1, buckets)], dtype=np.uint64)
            cuts = [0, *np.searchsorted(keys[order], edges).tolist(), len(keys)]
            rows = []
            for k, (i, j) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
                if j > i:
                    mine = [lists[x] for x in order[i:j].tolist()]
                    rows.append({"page": OFFER, "bucket": k, "keys": keys[order[i:j]].tobytes(), "vals": np.array([len(x) for x in mine], np.int32).tobytes() + np.concatenate(mine).tobytes()})
            yield pa.RecordBatch.from_pylist(rows, REQUEST_ARROW)

    def look_up(pdf: pd.DataFrame) -> pd.DataFrame:
        table, asked = pdf[pdf["page"] == OFFER], pdf[pdf["page"] != OFFER].drop_duplicates("page")
        keys, sizes, flat = [np.zeros(0, np.uint64)], [np.zeros(0, np.int32)], [np.zeros(0, np.int32)]
        for k, v in zip(table["keys"], table["vals"], strict=True):
            k, v = np.frombuffer(k, np.uint64), np.frombuffer(v, np.int32)
            keys.append(k)
            sizes.append(v[: len(k)])
            flat.append(v[len(k) :])
        keys, sizes, flat = np.concatenate(keys), np.concatenate(sizes).astype(np.int64), np.concatenate(flat)
        begins, order = np.cumsum(sizes) - sizes, np.argsort(keys)
        said = []
        for k in asked["keys"]:
            at, k = np.searchsorted(keys[order], np.frombuffer(k, np.uint64)), np.frombuffer(k, np.uint64)
            if len(k) and (not len(keys) or (keys[order[np.minimum(at, len(keys) - 1)]] != k).any()):
                raise ValueError("a unit was asked for that nobody offered")
            at = order[at]
            said.append(sizes[at].astype(np.int32).tobytes() + ragged(flat, begins[at], sizes[at]).astype(np.int32).tobytes())
        return pd.DataFrame({"page": asked["page"], "bucket": asked["bucket"], "said": [np.int64(len(k) // 8).tobytes() + x for k, x in zip(asked["keys"], said, strict=True)]})

    asked = packed.map(ask, REQUEST_SCHEMA)
    # The head is at every task already; only the others are offered.
    beyond = coded.join(F.broadcast(spark.createDataFrame(pd.DataFrame({"hash": keys.view(np.int64)}), "hash long")), "hash", "left_anti")
    offered = beyond.select("hash", "ids").mapInArrow(frugal(offer), REQUEST_SCHEMA)
    replies = answers(asked.unionByName(offered).groupBy("bucket").applyInPandas(frugal_group(look_up), "page long, bucket int, said binary"))

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spans = model.spans()
        own, own_at, own_n, own_ids = head.value
        tables = probe_tables(own)
        raw, raw_at = model.bytes_table()
        table, longest = None, model.longest()
        for b in batches:
            for h, body, said in zip(*(c.to_pylist() for c in b.columns), strict=True):
                u = Units(h, body, spans)
                place = probe(u.hash, own, tables)
                tail, first = np.unique(u.hash[place < 0], return_index=True)
                sizes, flat = [own_n], [own_ids]
                if said is None:
                    table = table or model.table()
                    mine = [model.expand(viterbi(u.all[u.starts[i] : u.ends[i]], table, longest, model.unknown_score)) for i in np.nonzero(place < 0)[0][first].tolist()]
                    sizes.append(np.array([len(x) for x in mine], np.int64))
                    flat.append(np.array([y for x in mine for y in x], np.int32))
                for part in said or []:
                    k = int(np.frombuffer(part, np.int64, 1)[0])
                    sizes.append(np.frombuffer(part, np.int32, k, 8).astype(np.int64))
                    flat.append(np.frombuffer(part, np.int32, -1, 8 + 4 * k))
                sizes, flat = np.concatenate(sizes), np.concatenate(flat)
                place[place < 0] = len(own) + np.searchsorted(tail, u.hash[place < 0])
                n = sizes[place]
                ids = ragged(flat, (np.cumsum(sizes) - sizes)[place], n)
                upto = np.concatenate([[0], np.cumsum(n)])[u.first_unit]
                decoded = ragged(raw, raw_at[ids], raw_at[ids + 1] - raw_at[ids]).tobytes()
                whole = decoded == u.all.encode("utf-8", "surrogatepass")
                same = [(t is None or META not in t) if whole else decode_ids(ids[x:y], raw, raw_at) == (t or "") for t, x, y in zip(u.texts, upto[:-1].tolist(), upto[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(u.ids, pa.int64()), pa.array(np.diff(upto)), pa.ListArray.from_arrays(pa.array(upto, pa.int32()), pa.array(ids, pa.int32())), pa.array(same)], names=["doc_id", "n_tokens", "ids", "round_trip"])

    return packed.map(lambda batches: (b.select(["page", "ids", "body"]) for b in batches), "page long, ids binary, body binary").join(replies, "page", "left").select("ids", "body", "said").mapInArrow(frugal(finish), RESULT)


def decode_ids(ids: np.ndarray, raw: np.ndarray, raw_at: np.ndarray) -> str:
    ids = np.asarray(ids, np.int64)
    text = ragged(raw, raw_at[ids], raw_at[ids + 1] - raw_at[ids]).tobytes().decode("utf-8", "replace").replace(META, " ")
    return text[1:] if text.startswith(" ") else text


def decode(encoded: DataFrame, model_path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id, text: pieces put together, meta blanks as blanks, byte pieces as UTF-8; null ids give null."""
    model = Model.load(model_path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        raw, raw_at = model.bytes_table()
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([None if x is None else decode_ids(x, raw, raw_at) for x in b.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    return encoded.select(F.col(id_col).alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(frugal(run), "doc_id long, text string")


def default_model(spark: SparkSession) -> str:
    """The path of the model file: the setting sketchlearn.sentencepiece.model, or the file of the installed public tokenizers."""
    path = spark.conf.get("sketchlearn.sentencepiece.model", None)
    if path is None:
        import public_tokenizers

        path = str(Path(public_tokenizers.path("piece_bpe_32k.model")))
    return path
