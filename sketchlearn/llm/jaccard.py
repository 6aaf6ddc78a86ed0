"""Similarity join on word shingles by a token-group matrix, and its classes.

Two documents link when the Jaccard resemblance of their sets of shingles is at
least num/den. The steps, none of which makes all pairs of a group:

1. Equal sets are one node. A set's tokens are ordered by their hash; of
   similar sets the first so-and-so many tokens share a certain number (prefix()
   and least_shared()). Counts over the corpus tell in how many sets each of
   these tokens stands; a set with too few that stand elsewhere has no partner.
2. Of the tokens that do, a set's rarest are enough to meet every partner. Two
   sets that meet by chance are told apart by size and parity bits, which lose no
   similar pair; of a token that more than LIST sets hold, all are tied to the
   smallest. Sets tied directly or by others form a family (rows and rounds grow
   with the tokens, not with pairs).
3. A family is solved locally by the token-group matrix: similar sets (same
   first shared token) form groups, each stores the union of its tokens, the
   matrix gives for a query set its overlap with all unions at once, and only
   groups whose overlap can reach the least number are opened. A group whose
   members are all linked with the query already stays closed. Families too
   large for a task are cut into blocks by their first shared token; each pair of
   blocks that share rare tokens is a task of the sets that hold these.
4. Components of the links are the classes.

Words are those between blanks, A-Z lower-cased. All texts, all shingles and all tokens take part; blocks bound a task, and
blocks of one group meet in step 3, so nothing is lost between them. Shingles
are 64-bit hashes, sets are told apart by 128 bits.

Defined results: a null or empty text has no shingles and is its own class; one
with fewer words than a shingle is one shingle of all its words; repeated rows
are equal sets; a null id is nobody's smallest id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.graph import connected_components
from ..operators.skew import spread_join
from .common import LOWER_TABLE, REQUEST_ARROW, REQUEST_SCHEMA, Page, buckets_for, exchange, frugal, frugal_group, mix64, pages, requests, written
from .substring import distinct

#: Sets in a group of the matrix and in a block of a family, and bytes of sets that a task solves together.
GROUP, BLOCK, TASK_BYTES = 32, 2048, 8_000_000
#: Least parity bits of a set, sets of a token that are compared in pairs by these, and rows that a task compares.
PARITY, LIST, TASK_MEETS = 512, 64, 100_000
#: Rows of the table of families up to which it is broadcast.
MOST_BROADCAST = 1_000_000
_STEP = np.uint64(0x9E3779B97F4A7C15)


# ---------------------------------------------------------------- sets and bounds


def shingle_sets(page: Page, n: int) -> list[np.ndarray]:
    """For each document its distinct shingle hashes, sorted."""
    flat, size = page.flat, page.sizes
    run = np.zeros(max(0, len(flat) - n + 1), np.uint64)
    for t in range(n):
        run = run * _STEP + flat[t : t + len(run)]
    run = mix64(run)
    out = []
    for at, k in zip(page.begin.tolist(), size.tolist(), strict=True):
        if k >= n:
            s = np.sort(run[at : at + k - n + 1])
            out.append(s[np.concatenate([[True], s[1:] != s[:-1]])])
        elif k:
            x = np.array([k], np.uint64)
            for w in flat[at : at + k]:
                x = x * _STEP + w
            out.append(mix64(x ^ _STEP))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def fingerprint(s: np.ndarray) -> bytes:
    """128 bits of a set: two sums of differently mixed members."""
    return np.array([mix64(s).sum(dtype=np.uint64), mix64(s ^ _STEP).sum(dtype=np.uint64)], np.uint64).tobytes()


def least_overlap(n: int, num: int, den: int) -> int:
    """Members that a set of n shares at least with a similar one: ceil(n * num / den)."""
    return -(-n * num // den)


def spare(n: int, num: int, den: int) -> int:
    """Tokens by which a set's prefix is longer than one shared token would need."""
    return 1 + n * (den - num) // den


def prefix(n: int, num: int, den: int) -> int:
    return min(n, n - least_overlap(n, num, den) + spare(n, num, den))


def least_shared(n: int, num: int, den: int) -> int:
    """Prefix tokens that a set of n shares at least with a similar set's prefix: the lesser spare of the two, and the partner has ceil(n * num / den) members at least."""
    return min(spare(least_overlap(n, num, den), num, den), least_overlap(n, num, den))


def token_keys(tokens: np.ndarray) -> np.ndarray:
    """Prefix tokens are the small hashes; keys are spread over all 64 bits."""
    return mix64(tokens ^ np.uint64(0xA5A5A5A5A5A5A5A5))


def parity(s: np.ndarray) -> bytes:
    """A parity bit for each of PARITY buckets of members, of twice as many from 2,048 members on, and so on."""
    width = PARITY << max(0, len(s).bit_length() - 11)
    return np.packbits(np.bincount((mix64(s + _STEP) % np.uint64(width)).astype(np.int64), minlength=width).astype(np.uint8) & 1, bitorder="little").tobytes()


def possible(x: np.ndarray, y: np.ndarray, sizes: np.ndarray, bits: list[bytes], num: int, den: int) -> np.ndarray:
    """Which of the pairs of sets at places x and y can be similar: those whose sizes allow it, and of whose parity bits, folded to
    as many as the smaller has, no more differ than members of similar sets may, (n1 + n2)(den - num)/(den + num) (see neighbors.alike)."""
    low, high = np.minimum(sizes[x], sizes[y]), np.maximum(sizes[x], sizes[y])
    out, width = den * low >= num * high, np.array([len(b) // 8 for b in bits], np.int64)
    for w in np.unique(width).tolist():
        pairs = np.nonzero(out & (np.minimum(width[x], width[y]) == w))[0]
        who = np.unique(np.concatenate([x[pairs], y[pairs]]))
        table = np.zeros((len(who), w), np.uint64)
        for v in np.unique(width[who]).tolist():
            at = np.nonzero(width[who] == v)[0]
            table[at] = np.bitwise_xor.reduce(np.frombuffer(b"".join(bits[i] for i in who[at].tolist()), np.uint64).reshape(len(at), v // w, w), axis=1)
        for some in (pairs[i : i + 50_000] for i in range(0, len(pairs), 50_000)):
            differ = np.bitwise_count(table[np.searchsorted(who, x[some])] ^ table[np.searchsorted(who, y[some])]).sum(1, dtype=np.int64)
            out[some] = differ * (den + num) <= (sizes[x[some]] + sizes[y[some]]) * (den - num)
    return out


# ---------------------------------------------------------------- local solving


class Matrix:
    """Groups of sets, and for each token of a group's union the groups that have it."""

    def __init__(self, sets: list[np.ndarray], first: np.ndarray):
        """first: of each set its first shared token; sets of one first token are a group of at most GROUP sets."""
        order = np.lexsort(([len(s) for s in sets], first))
        cuts, run = [0], 0
        for x, y in zip(order[:-1].tolist(), order[1:].tolist(), strict=True):
            run += 1
            if first[x] != first[y] or run - cuts[-1] >= GROUP:
                cuts.append(run)
        self.groups = [order[i:j] for i, j in zip(cuts, [*cuts[1:], len(order)], strict=True) if j > i]
        unions = [np.unique(np.concatenate([sets[i] for i in g])) for g in self.groups]
        tokens = np.concatenate(unions)
        sort = np.argsort(tokens, kind="stable")
        self.tokens, self.owner = tokens[sort], np.repeat(np.arange(len(unions)), [len(u) for u in unions])[sort]
        self.held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        self.sets = sets

    def overlaps(self, query: np.ndarray) -> np.ndarray:
        """How many tokens of the query each group's union has."""
        low, high = np.searchsorted(self.tokens, query, "left"), np.searchsorted(self.tokens, query, "right")
        n = high - low
        at = np.repeat(low - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
        return np.bincount(self.owner[at], minlength=len(self.groups))

    def inside(self, group: int, query: np.ndarray) -> np.ndarray:
        """How many tokens of the query each member of an opened group has."""
        if group not in self.held:
            who = self.groups[group]
            self.held[group] = np.concatenate([self.sets[i] for i in who]), np.repeat(np.arange(len(who)), [len(self.sets[i]) for i in who])
        tokens, owner = self.held[group]
        at = np.searchsorted(query, tokens)
        at[at == len(query)] = 0
        return np.bincount(owner[query[at] == tokens], minlength=len(self.groups[group]))


def link_all(sets: list[np.ndarray], first: np.ndarray, num: int, den: int, side: np.ndarray | None = None) -> np.ndarray:
    """For each set the number of the first set of its linked part. With side, only sets of different sides are compared."""
    root = np.arange(len(sets))
    if len(sets) < 2:
        return root
    m, size = Matrix(sets, first), np.array([len(s) for s in sets])
    for i, query in enumerate(sets):
        n = len(query)
        open_ = np.nonzero(m.overlaps(query) >= least_overlap(n, num, den))[0]
        for g in open_.tolist():
            who = m.groups[g]
            other = root[who] != root[i]
            if side is not None:
                other &= side[who] != side[i]
            if not other.any():
                continue
            both = m.inside(g, query)
            for j in who[other & (den * both >= num * (n + size[who] - both))].tolist():
                if root[j] != root[i]:
                    low, high = sorted((root[i], root[j]))
                    root[root == high] = low
    return root


def _arrays(column) -> list[np.ndarray]:
    return [np.frombuffer(x, np.uint64) for x in column]


# ---------------------------------------------------------------- Spark


def classes(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id: the smallest id that links reach."""
    spark = docs.sparkSession
    packed = pages(docs, id_col, text_col)
    total = packed.agg(F.sum("n_words")).first()[0] or 0
    buckets = buckets_for(total * (2 * (den - num)) // den)

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for number, head, body in zip(*(c.to_pylist() for c in b.columns), strict=True):
                page = Page(head, body, LOWER_TABLE)
                sets = shingle_sets(page, n)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(sets), number)), pa.array(np.arange(len(sets))), pa.array(page.ids, pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array([fingerprint(s) if len(s) else None for s in sets], pa.binary())], names=["page", "nth", "doc_id", "n_shingles", "fp"])

    described = written(packed.select("page", "ids", "body").mapInArrow(frugal(describe), "page long, nth long, doc_id long, n_shingles long, fp binary"), spark)
    # Where each distinct set stands first: only there it is sent on.
    firsts = described.where("fp is not null").groupBy("fp").agg(F.min(F.struct("page", "nth")).alias("at")).groupBy("at.page").agg(F.collect_list("at.nth").alias("firsts"))

    def page_sets(head: bytes, body: bytes) -> tuple[list[int], list[np.ndarray]]:
        """The page's distinct sets, and where they stand first in it."""
        out: dict[bytes, tuple[int, np.ndarray]] = {}
        for i, s in enumerate(shingle_sets(Page(head, body, LOWER_TABLE), n)):
            if len(s):
                out.setdefault(fingerprint(s), (i, s))
        return [i for i, _ in out.values()], [s for _, s in out.values()]

    def page_tokens(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        cut = [s[: prefix(len(s), num, den)] for s in sets]
        return distinct(token_keys(np.concatenate(cut) if cut else np.zeros(0, np.uint64))[:, None])

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for number, head, body in zip(*(c.to_pylist() for c in b.columns), strict=True):
                keys, count, _ = page_tokens(page_sets(head, body)[1])
                yield pa.RecordBatch.from_pylist(requests(number, keys, count, buckets), REQUEST_ARROW)

    said = exchange(packed.select("page", "ids", "body").mapInArrow(frugal(ask), REQUEST_SCHEMA), 1, how_many)

    def candidates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for head, body, answer, here in zip(*(c.to_pylist() for c in b.columns), strict=True):
                (nth, sets), here = page_sets(head, body), set(here or ())
                _, _, where = page_tokens(sets)
                count, rows, at = np.frombuffer(b"".join(answer or []), np.uint16)[where] if sets else None, [], 0
                for i, s in zip(nth, sets, strict=True):
                    k = prefix(len(s), num, den)
                    often = count[at : at + k]
                    at += k
                    if i not in here:
                        continue
                    toks, least = s[:k][often > 1], least_shared(len(s), num, den)
                    if len(toks) >= least:
                        rare = toks[np.lexsort((toks, often[often > 1]))[: len(toks) - least + 1]]
                        rows.append({"fp": (f := fingerprint(s)), "id": int(np.frombuffer(f, np.int64)[0]), "g": int(toks[:1].view(np.int64)[0]), "rare": rare.view(np.int64).tolist(), "size": len(s), "parity": parity(s), "held": s.tobytes()})
                yield pa.RecordBatch.from_pylist(rows, pa.schema([("fp", pa.binary()), ("id", pa.int64()), ("g", pa.int64()), ("rare", pa.list_(pa.int64())), ("size", pa.int64()), ("parity", pa.binary()), ("held", pa.binary())]))

    cand = written(packed.join(said.join(firsts, "page", "left"), "page", "left").select("ids", "body", "said", "firsts").mapInArrow(frugal(candidates), "fp binary, id long, g long, rare array<long>, size long, parity binary, held binary"), spark)
    # Families: sets that meet in a rare token and may be similar. 64 bits name a set here; equal names would only join two families.
    tied = cand.select("id", F.explode("rare").alias("token"))
    stars = tied.groupBy("token").agg(F.min("id").alias("low"), F.max("id").alias("high"), F.count(F.lit(1)).alias("n")).where("low < high").select("token", "low", "n")
    meets = written(tied.join(stars, "token").select("token", "id", "low", "n"), spark)
    # Copies share many tokens: equal lists of sets are compared once.
    few = meets.where(F.col("n") <= LIST).groupBy("token").agg(F.sort_array(F.collect_list("id")).alias("ids")).groupBy("ids").agg(F.min("token").alias("token"))
    few = written(few.select("token", F.explode("ids").alias("id")), spark)

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["token", "id"], ignore_index=True)
        names, first, ids = np.unique(pdf["id"].to_numpy(), return_index=True, return_inverse=True)
        sizes, bits = pdf["size"].to_numpy()[first], pdf["parity"].iloc[first].tolist()
        begin = np.concatenate([[0], np.nonzero(np.diff(pdf["token"].to_numpy()))[0] + 1])
        length = np.diff(np.concatenate([begin, [len(pdf)]]))
        src, dst = [], []
        for m in np.unique(length).tolist():
            i, j = np.triu_indices(m, 1)
            lists, step = ids[begin[length == m][:, None] + np.arange(m)], max(1, 1_000_000 // max(1, len(i)))
            for some in (lists[k : k + step] for k in range(0, len(lists), step)):
                key = np.unique(some[:, i].ravel() * len(names) + some[:, j].ravel())
                x, y = key // len(names), key % len(names)
                good = possible(x, y, sizes, bits, num, den)
                src.append(names[x[good]])
                dst.append(names[y[good]])
        return pd.DataFrame({"low": np.concatenate([np.zeros(0, np.int64), *src]), "id": np.concatenate([np.zeros(0, np.int64), *dst])}).drop_duplicates(ignore_index=True)

    tasks = F.pmod(F.xxhash64("token"), F.lit(max(16, few.count() // TASK_MEETS)))
    pairs = few.join(cand.select("id", "size", "parity"), "id").groupBy(tasks).applyInPandas(frugal_group(meet), "low long, id long")
    pairs = written(pairs.distinct(), spark)
    many = meets.where(F.col("n") > LIST)
    ties = pairs.unionByName(many.where("id <> low").select("low", "id").distinct())
    if not ties.head(1):
        return _named(described, None)
    families = connected_components(ties, "id", "low").withColumnsRenamed({"node": "id", "root": "family"})
    large = families.groupBy("family").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > BLOCK).select("family", F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks"))
    placed = written(families.join(large, "family", "left").withColumn("blocks", F.coalesce("blocks", F.lit(1))), spark)
    small = placed.where("blocks = 1")
    if placed.count() <= MOST_BROADCAST:  # 20 bytes a row; beyond, the sets are shuffled to it
        small = F.broadcast(small)
    wide = "fp", "family", "g", "held", "own", "i", "j"
    one = F.lit(0).cast("long")
    tasks = cand.join(small, "id").withColumns({"own": one, "i": one, "j": one}).select(*wide)
    if large.limit(1).count():
        tied = many.select("id", "token").unionByName(pairs.select(F.explode(F.array("low", "id")).alias("id"), F.xxhash64("low", "id").alias("token")))
        dealt = written(_block_pairs(cand, tied, placed))
        if dealt.limit(MOST_BROADCAST + 1).count() <= MOST_BROADCAST:  # so that the sets themselves are shuffled once, to their tasks
            dealt = F.broadcast(dealt)
        tasks = tasks.unionByName(cand.join(dealt, ["id", "fp"]).select(*wide))
    bytes_held = cand.agg(F.sum(F.length("held"))).first()[0] or 0

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        src, dst = [], []
        for _, part in pdf.groupby(["family", "i", "j"], sort=False):
            if len(part) < 2:
                continue
            part = part.sort_values("fp", ignore_index=True)
            i, j, own = part["i"].iloc[0], part["j"].iloc[0], part["own"].to_numpy()
            root = link_all(_arrays(part["held"]), part["g"].to_numpy(), num, den, None if i == j else own)
            fp = part["fp"].to_numpy()
            linked = np.nonzero(root != np.arange(len(root)))[0]
            src += fp[linked].tolist()
            dst += fp[root[linked]].tolist()
        return pd.DataFrame({"src": src, "dst": dst})

    dealt = tasks.withColumn("task", F.pmod(F.xxhash64("family", "i", "j"), F.lit(max(16, bytes_held // TASK_BYTES))))
    links = written(dealt.groupBy("task").applyInPandas(frugal_group(solve), "src binary, dst binary"), spark)
    return _named(described, links)


def _block_pairs(cand: DataFrame, tied: DataFrame, placed: DataFrame) -> DataFrame:
    """(id, fp, family, own, i, j): the sets of families of more than BLOCK sets, dealt to pairs of blocks.

    Sets of one first shared token, which similar sets mostly have in common, lie
    in one block, or in several where they are too many. Two blocks meet only in
    the rare tokens that both hold, as two similar sets do, and only the sets that
    hold one of these go there: a set is sent as often as its rare tokens lie in
    other blocks, not as often as its block has neighbours.
    """
    sets = cand.select("id", "fp", "g").join(placed.where("blocks > 1"), "id").withColumn("bucket", F.pmod(F.xxhash64("g"), F.col("blocks")))
    parts = sets.groupBy("family", "bucket").agg(F.ceil(F.count(F.lit(1)) / (2 * BLOCK)).alias("parts"))  # of about BLOCK sets each; up to twice as many stay together
    own = F.col("bucket") * (1 << 32) + F.pmod(F.xxhash64("fp"), F.col("parts"))
    blocked = written(sets.join(parts, ["family", "bucket"]).select("id", "fp", "family", own.alias("own")))
    held = written(tied.join(blocked, "id").select("id", "fp", "family", "token", "own"))
    blocks = held.select("family", "token", F.col("own").alias("other")).distinct()
    across = held.join(blocks, ["family", "token"]).where("own <> other").select("id", "fp", "family", "own", "other").distinct()
    alone = blocked.select("id", "fp", "family", "own", F.col("own").alias("other"))
    return alone.unionByName(across).select("id", "fp", "family", "own", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))


def how_many(group: np.ndarray, vals: np.ndarray) -> np.ndarray:
    """In how many of the pages' sets a token stands; beyond 65,535 all are alike in rarity."""
    return np.minimum(np.bincount(group, weights=vals)[group], 65535).astype(np.uint16)


def _named(described: DataFrame, links: DataFrame | None) -> DataFrame:
    """Smallest id of each class. A set's class is its component in the links, or itself."""
    smallest = described.where("fp is not null").groupBy("fp").agg(F.min("doc_id").alias("smallest"))
    named = smallest.select("fp", F.col("smallest").alias("component"))
    if links is not None and links.head(1):
        roots = connected_components(links).withColumnRenamed("node", "fp").join(smallest, "fp")
        roots = written(roots)
        label = spread_join(roots, roots.groupBy("root").agg(F.min("smallest").alias("label")), "root", "inner").select("fp", "label")
        named = smallest.join(label, "fp", "left").select("fp", F.coalesce("label", "smallest").alias("component"))
    return spread_join(described, named, "fp").select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))
