"""Operators against brute force on small tables with nulls, empty and long texts, ties, repeated rows and further columns."""

import hashlib
import itertools
import math
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from sketchlearn.llm import common, decontam, jaccard, license, lm, queries, sentencepiece, substring, topk, toxicity, urlfilter, warc

from ..oracle import compare

SF = "/root/testdata/sf0.001"
RNG = np.random.default_rng(3)
VOCAB = [f"w{i}" for i in range(400)]


def prose(n, rng=RNG):
    return " ".join(rng.choice(VOCAB, n))


def corpus(spark):
    """Copies, near copies, shared passages, runs, empties, nulls, a long text, a repeated row, a clashing column."""
    passage = prose(60)
    base = [prose(120) for _ in range(6)]
    rows = [(1, base[0]), (2, base[0]), (3, base[0].replace("w1 ", "x ", 1)), (4, base[1] + " " + passage), (5, passage + " " + base[2]), (6, "a " * 200), (7, ""), (8, None), (9, "one two"), (10, "one  two"), (11, "One TWO"), (12, prose(40) + "\n" + base[3]), (13, " \t\n "), (14, base[4] + " été ñandú 日本"), (15, base[3]), (15, base[3]), (None, base[5]), (17, prose(5000))]
    return spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, page string"), rows


def test_pages_round_trip_and_word_hashes():
    ids, texts = [1, None, 3, 4], ["a bc", None, "", "bc  a\n"]
    head, body = common.pack_rows(ids, texts)
    back, sizes, raw = common.unpack_rows(head, body)
    assert back == ids and common.text_of(sizes, raw) == [b"a bc", None, b"", b"bc  a\n"]
    p = common.Page(head, body)
    assert p.sizes.tolist() == [2, 0, 0, 2]
    words = [p.flat[b : b + n].tolist() for b, n in zip(p.begin, p.sizes)]
    assert words[0] == words[3][::-1] and words[0][0] != words[0][1]


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_sql(spark, name):
    assert compare(spark, queries.QUERIES[name], queries.ORACLES[name]) > 0


# ---------------------------------------------------------------- 1


def test_scores(spark):
    df, rows = corpus(spark)
    got = lm.scores(df).collect()
    tok = lambda t: (t or "").encode().lower().split() + [None]
    held = lambda i: zlib.crc32(b"" if i is None else str(i).encode()) % 10 == 0
    c = Counter(w for i, t in rows if not held(i) for w in tok(t))
    n, v = sum(c.values()), len(c)
    want = sorted((-1 if i is None else i, held(i), len(tok(t)), sum(c[w] > 0 for w in tok(t)), n, round(sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in tok(t)), 6)) for i, t in rows)
    assert sorted((-1 if r.doc_id is None else r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in got) == want
    assert all(r.score < 0 and math.isfinite(r.score) for r in got)
    assert lm.scores(df.limit(0)).count() == 0


def test_model_beats_the_base_on_held_out_documents(spark):
    rows = [r for r in lm.scores(queries.table(spark, "/root/testdata/sf0.01", "documents")).collect() if r.held_out]
    assert sum(r.score for r in rows) > sum(r.base_score for r in rows)


def test_gradients_and_carried_state():
    vocab = lm.Vocabulary(np.arange(1, 11, dtype=np.uint64), np.full(10, 5), np.full(lm.KINDS, 2), np.full(lm.KINDS, 1), 100, 74)
    net = lm.Network(vocab)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    rng = np.random.default_rng(0)
    h, target = rng.standard_normal((6, lm.HIDDEN)), rng.integers(0, 10, 6)
    _, dh, grads = net.outputs(h, target, True)
    for name, at in (("Wc", (3, 0)), ("bw", (0, 2))):
        old = net.p[name][at]
        net.p[name][at] = old + 1e-3
        up = -net.outputs(h, target, False)[0].mean()
        net.p[name][at] = old - 1e-3
        down = -net.outputs(h, target, False)[0].mean()
        net.p[name][at] = old
        assert grads[name][at] == pytest.approx((up - down) / 2e-3, rel=1e-2, abs=1e-5)
    # One document in one lane scores as it does among others, and in windows of any size.
    net = lm.Network(vocab)
    numbers, sizes = rng.integers(0, 10, 700).astype(np.int32), np.array([500, 150, 50])
    whole = lm.forward_scores(net, lm.lay(sizes, np.cumsum(sizes) - sizes, 8), numbers)
    alone = lm.forward_scores(net, lm.lay(sizes[1:2], np.array([0]), 8), numbers[500:650])
    assert np.allclose(whole[500:650], alone, atol=1e-4)


def test_probabilities_sum_to_one():
    vocab = lm.Vocabulary(np.arange(1, 11, dtype=np.uint64), np.full(10, 5), np.full(lm.KINDS, 2), np.full(lm.KINDS, 1), 100, 74)
    net, h = lm.Network(vocab), np.random.default_rng(0).standard_normal((1, lm.HIDDEN)).astype(np.float32)
    every = np.arange(lm.OUTPUTS * lm.CLASS_SIZE)
    total = np.exp(net.outputs(np.repeat(h, len(every), 0), every, False)[0]).sum()
    assert total == pytest.approx(1, rel=1e-3)


# ---------------------------------------------------------------- 2

MODEL = "/opt/tokenizers/piece_bpe_32k.model"


def test_encoding_is_the_best_path_and_decodes(spark):
    df, rows = corpus(spark)
    extra = spark.createDataFrame([(30, "x" * 3000, ""), (31, "\x00 a\ttab  two  ", ""), (32, "▁meta", ""), (33, "ok 😀 \x7f𝔘", "")], df.schema)
    got = {r.doc_id: r for r in sentencepiece.encode(df.unionByName(extra), MODEL).collect()}
    m = sentencepiece.Model.load(MODEL)
    table = {p: (i, s) for i, (p, s, x) in enumerate(zip(m.pieces, m.scores, m.normal)) if x}
    texts = dict(rows) | {30: "x" * 3000, 31: "\x00 a\ttab  two  ", 33: "ok 😀 \x7f𝔘"}
    for i, t in texts.items():
        want = m.expand(sentencepiece.viterbi(sentencepiece.normalised(t), table, m.longest(), m.unknown_score))
        assert list(got[i].ids) == want and got[i].round_trip and got[i].n_tokens == len(want)
    assert not got[32].round_trip
    back = {r.doc_id: r.text for r in sentencepiece.decode(spark.createDataFrame(list(got.values())), MODEL).collect()}
    assert all(back[i] == (t or "") for i, t in texts.items())


def test_encoding_equals_the_library_as_unigram_model(spark):
    import sentencepiece as library
    from sentencepiece import sentencepiece_model_pb2 as pb

    proto = pb.ModelProto()
    proto.ParseFromString(open(MODEL, "rb").read())
    proto.trainer_spec.model_type = 1
    sp = library.SentencePieceProcessor(model_proto=proto.SerializeToString())
    texts = ["The quick brown fox jumps", "Die Katze sitzt auf der Matte.", "été à la plage", "hello, world! 123"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: list(r.ids) for r in sentencepiece.encode(df, MODEL).collect()}
    assert [got[i] for i in range(len(texts))] == [sp.encode(t) for t in texts]


# ---------------------------------------------------------------- 3


def test_archives_round_trip(spark, tmp_path):
    long = "<p>" + "é" * 900
    rows = [(1, "http://a/ x\n", long), (2, None, long), (3, "http://b", long), (3, "http://b", long), (4, "u", "short"), (5, "u", "short"), (6, "u", None), (None, "n", long), (7, "u", "")]
    pages = spark.createDataFrame([(*r, 0) for r in rows], "page_id long, url string, html string, digest int")
    folder = f"file://{tmp_path}/w"
    manifest = common.written(warc.write_archives(pages, folder))
    got = warc.read_archives(manifest, folder).collect()
    assert len(got) == len(rows) and sum(r.records for r in manifest.collect()) == len(rows)
    for r in got:
        html = next((x[2] or "") for x in rows if x[0] == r.page_id).encode()
        assert r.payload_digest == hashlib.sha1(html).hexdigest() and r.payload_bytes == len(html)
        assert (r.record_type, r.refers_to) == (("revisit", 3) if r.page_id in (1, 2, None) else ("response", None))
        assert r.payload == (None if r.record_type == "revisit" else html)
    assert warc.archive_round_trip(spark, pages.limit(0)).count() == 0


def test_archive_layout():
    records = [bytes(f"WARC record {i} " * 50, "ascii") for i in range(300)]
    for some in (records, records[:1]):
        data = warc.archive_bytes(some, 3)
        assert int.from_bytes(data[:4], "little") == warc.DICTIONARY_MAGIC and list(warc.frames(data)) == some


# ---------------------------------------------------------------- 4


def test_fixed_rules(spark):
    urls = {"http://a.example.net/en/1": ("example.net/en/", "allow"), "http://NET/x": ("net/", "block"), "http://xnet/": (None, "allow"), "https://m.example.com/de/?q": ("example.com/de/", "block"), "http://a.org/fr/#x": ("org/fr/", "allow"), "http://a.net": (None, "allow"), "http://a.net?x": (None, "allow"), "no scheme": (None, "allow"), None: (None, "allow"), "": (None, "allow"), "x://h.net/en": ("net/", "block")}
    pages = spark.createDataFrame([(i, u, "c") for i, u in enumerate(urls)], "page_id long, url string, confidence string")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = {r.page_id: (r.rule, r.verdict) for r in urlfilter.judge(pages, labels).collect()}
    assert got == dict(enumerate(urls.values()))
    hosts = {r.page_id: (r.host, r.path) for r in urlfilter.judge(pages, labels).collect()}
    assert hosts[0] == ("a.example.net", "/en/1") and hosts[6] == ("a.net", "") and hosts[8] == ("", "")


def test_mined_rules_match_brute_force(spark):
    rng = np.random.default_rng(5)
    rows = []
    for i in range(400):
        toks = sorted(set(rng.choice(["spam", "shop", "win", "news", "blog", "x"], 3).tolist()))
        bad = {"spam", "win"} <= set(toks) or rng.random() < 0.05
        rows.append((i, "http://" + ".".join(toks) + ".de/", int(not bad)))
    pages = spark.createDataFrame([(i, u) for i, u, _ in rows], "page_id long, url string")
    labels = spark.createDataFrame([(i, q, 0) for i, _, q in rows], "doc_id long, quality int, toxic int")
    sets_ = [(set(u[7:-1].split(".")), not q) for _, u, q in rows]
    rules = []
    for n in (1, 2, 3, 4):
        for need in itertools.combinations(sorted(set().union(*(s for s, _ in sets_))), n):
            hit = [bad for s, bad in sets_ if set(need) <= s]
            if hit and sum(hit) >= 0.002 * len(sets_) and sum(hit) / len(hit) >= 0.5:
                rules.append(set(need))
    want = {i for (i, _, _), (s, _) in zip(rows, sets_) if any(r <= s for r in rules)}
    got = {r.page_id for r in urlfilter.judge(pages, labels).where("verdict = 'block'").collect()}
    assert got == want and want


# ---------------------------------------------------------------- 5


def test_top_k_equals_brute_force(spark):
    rng = np.random.default_rng(9)
    vecs = [(i, rng.normal(size=6).round(2).tolist()) for i in range(300)] + [(300 + i, [0.5] * 6) for i in range(30)]
    vecs += [(400, None), (401, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (402, [float("nan")] * 6), (500, [0.0] * 6), (7, vecs[7][1])]
    df = spark.createDataFrame([(i, v, 1) for i, v in vecs], "vec_id long, embedding array<float>, rank int")
    ok = [(i, [math.floor(1024 * float(np.float32(x))) for x in v]) for i, v in vecs if v and all(x is not None and math.isfinite(x) for x in v)]
    want = []
    for q, a in {i: v for i, v in ok if i % 20 == 0}.items():
        ranked = sorted(((-sum(x * y for x, y in zip(a, b)), i) for i, b in ok if i != q))[:10]
        want += [(q, k + 1, i, -s) for k, (s, i) in enumerate(ranked)]
    got = topk.top_k(df, F.col("vec_id") % 20 == 0).collect()
    assert sorted(map(tuple, got)) == sorted(want)
    assert topk.top_k(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0


# ---------------------------------------------------------------- 6


def test_repeated_passages_equal_brute_force(spark):
    df, rows = corpus(spark)
    words = [(i, (t or "").encode().split()) for i, t in rows]
    n = substring.WINDOW
    count = Counter(tuple(w[s : s + n]) for _, w in words for s in range(len(w) - n + 1))
    want = []
    for i, w in words:
        gone = {p for s in range(len(w) - n + 1) if count[tuple(w[s : s + n])] > 1 for p in range(s, s + n)}
        kept = [x for p, x in enumerate(w) if p not in gone]
        want.append((str(i), len(w), len(gone), hashlib.sha256(b" ".join(kept)).hexdigest()))
    assert sorted((str(r.doc_id), r.n_words, r.n_removed, r.kept_sha256) for r in substring.removed_digest(df).collect()) == sorted(want)
    kept = {str(r.doc_id): r for r in substring.without_repeats(df, chars_col=None).collect()}
    assert kept["9"].text == "one two" and kept["8"].text is None and kept["1"].text == "" and kept["17"].page == "x"
    assert substring.removed_digest(df.limit(0)).count() == 0


# ---------------------------------------------------------------- 7


def test_license_scan(spark):
    texts = ["Released under the MIT License.", "x under the mit license under the MIT license", "Licensed under the Apache License, Version 2.0.", "CC BY-NC", "cc by nc 4.0", "This work is licensed under the GNU General Public License, version 3.", "license license", "", None, "All rights reserved", "intro " * 3000 + "licensed under cc by sa 4 0"]
    df = spark.createDataFrame([(i, t, 0) for i, t in enumerate(texts)], "doc_id long, text string, words int")
    got = {r.doc_id: r for r in license.scan(df).collect()}
    base = {0: ["mit"], 1: ["mit"], 2: ["apache-2"], 3: ["cc-by-nc"], 4: ["cc-by-nc"]}
    assert {i: r.base_labels for i, r in got.items() if r.base_labels} == base
    assert [p.word for p in got[1].places] == [1, 5] and got[1].n_words == 9
    own = {i: r.labels for i, r in got.items() if r.labels}
    assert own == base | {5: ["gpl-3"], 9: ["proprietary"], 10: ["cc-by-sa"]}
    assert all(0 <= r.score <= 1 for r in got.values()) and got[0].score == 1
    assert got[7].n_words == got[8].n_words == 0


def test_license_labels_equal_brute_force(spark):
    df = queries.table(spark, SF, "documents")
    got = {r.doc_id: r for r in queries.op7_license_scan(spark, SF).collect()}
    for r in df.collect():
        w = [x.decode() for x in common.alnum_words(r.text)]
        places = {lab: [i for i in range(len(w)) if w[i : i + len(p.split())] == p.split()] for lab, p in license.BASE_PHRASES.items()}
        flat = [i for v in places.values() for i in v]
        g = got[r.doc_id]
        assert (g.n_words, g.n_base, g.first_word, g.last_word) == (len(w), len(flat), min(flat, default=None), max(flat, default=None))
        labels, best = {k for k, v in places.items() if v}, 0.0
        for t in license.TEMPLATES:
            own, key = t.text.split(), t.key.split()
            at = next(i for i in range(len(own)) if own[i : i + len(key)] == key)
            for o in range(-len(own), len(w)):
                if o + at >= 0 and w[o + at : o + at + len(key)] == key:
                    share = sum(0 <= o + p < len(w) and w[o + p] == x for p, x in enumerate(own)) / len(own)
                    best = max(best, share)
                    labels |= {t.label} if share >= license.LEAST_SCORE else set()
        assert g.labels == ",".join(sorted(labels)) and g.score == pytest.approx(best)


# ---------------------------------------------------------------- 8


def test_toxicity_on_held_out_rows(spark):
    docs, labels = (queries.table(spark, "/root/testdata/sf0.1", t) for t in ("documents", "labels"))
    held = F.pmod(F.xxhash64("text"), F.lit(4)) == 0
    out = toxicity.classify(docs.where(held), labels, train_docs=docs.where(~held)).join(labels, "doc_id").collect()
    hit = sum(r.rejected and r.toxic for r in out)
    assert hit / sum(r.rejected for r in out) > 0.9 and hit / sum(r.toxic for r in out) > 0.9
    assert all(0 <= r.p_toxic <= 1 and 0 <= r.p_low_quality <= 1 for r in out)


def test_toxicity_edges(spark):
    df, rows = corpus(spark)
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert not any(r.rejected for r in toxicity.classify(df, none).collect())
    assert toxicity.without_toxic(df, none).count() == len(rows)
    some = spark.createDataFrame([(1, 1, 0), (1, 1, 0), (4, None, 1), (99, 0, 1), (None, 1, 1)], "doc_id long, quality int, toxic int")
    assert toxicity.classify(df, some).count() == len(rows)
    assert toxicity.classify(df.limit(0), some).count() == 0


# ---------------------------------------------------------------- 9


@pytest.mark.parametrize(("n", "num"), [(3, 90), (5, 80), (2, 60)])
def test_classes_equal_brute_force(spark, n, num, monkeypatch):
    monkeypatch.setattr(jaccard, "BLOCK", 5)  # families of several blocks
    rng = np.random.default_rng(n)
    texts = []
    for _ in range(12):
        base = rng.choice(VOCAB, int(rng.integers(2, 80))).tolist()
        for _ in range(int(rng.integers(1, 9))):
            t = list(base)
            for _ in range(int(rng.integers(0, 4))):
                t[int(rng.integers(0, len(t)))] = f"e{rng.integers(0, 50)}"
            texts.append(" ".join(t))
    df, rows = corpus(spark)
    rows = [(i, t) for i, t in rows if i is not None] + [(100 + i, t) for i, t in enumerate(texts)]
    df = spark.createDataFrame([(i, t, 0) for i, t in rows], "doc_id long, text string, component int")
    sets_ = []
    for _, t in rows:
        w = (t or "").encode().lower().split()
        sets_.append({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} or ({tuple(w)} if w else set()))
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, j in itertools.combinations(range(len(rows)), 2):
        both = len(sets_[i] & sets_[j])
        if both and 100 * both >= num * len(sets_[i] | sets_[j]):
            root[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        least[find(i)] = min(least.get(find(i), d), d)
    want = sorted((d, len(sets_[i]), least[find(i)]) for i, (d, _) in enumerate(rows))
    assert sorted(map(tuple, jaccard.classes(df, n, num, 100).collect())) == want


def test_prefix_bounds():
    """Of similar sets the prefixes share what least_shared() says."""
    rng = np.random.default_rng(1)
    for _ in range(300):
        n = int(rng.integers(1, 60))
        a = np.unique(rng.integers(0, 1 << 62, n)).astype(np.uint64)
        b = a.copy()
        for _ in range(int(rng.integers(0, 8))):
            b[int(rng.integers(0, len(b)))] = rng.integers(0, 1 << 62)
        b = np.unique(b)
        for num in (80, 90):
            both = len(np.intersect1d(a, b))
            if 100 * both >= num * (len(a) + len(b) - both):
                k = len(np.intersect1d(a[: jaccard.prefix(len(a), num, 100)], b[: jaccard.prefix(len(b), num, 100)]))
                assert k >= max(jaccard.least_shared(len(a), num, 100), jaccard.least_shared(len(b), num, 100))


# ---------------------------------------------------------------- 10


@pytest.mark.parametrize("num", [40, 60, 90])
def test_jaccard_parity_bits_lose_no_similar_pair(num):
    rng, sets = np.random.default_rng(num), []
    for n in (1, 2, 9, 60, 500, 2040, 2050, 5000):
        base = rng.integers(0, 1 << 63, n, dtype=np.uint64)
        for other in (0, 1, n // 30, n // 9, n // 2, n):
            sets.append(np.unique(np.concatenate([base[other:], rng.integers(0, 1 << 63, other // 2, dtype=np.uint64)])))
    sets = [s for s in sets if len(s)]
    x, y = np.triu_indices(len(sets), 1)
    good = jaccard.possible(x, y, np.array([len(s) for s in sets]), [jaccard.parity(s) for s in sets], num, 100)
    x, y = x[good], y[good]
    both = lambda a, b: len(np.intersect1d(a, b))
    want = {(i, j) for j in range(len(sets)) for i in range(j) if 100 * (k := both(sets[i], sets[j])) >= num * (len(sets[i]) + len(sets[j]) - k)}
    found = set(zip(x.tolist(), y.tolist(), strict=True))
    assert want and want <= found and len(found) < len(sets) * (len(sets) - 1) // 2


def test_jaccard_sends_sets_as_often_as_they_meet_not_as_their_block_does(spark, monkeypatch):
    monkeypatch.setattr(jaccard, "BLOCK", 8)
    n = 256
    cand = spark.createDataFrame([(i, b"%d" % i, i) for i in range(n)], "id long, fp binary, g long")
    # A family that chance meetings hold together: each set shares one token with the next and one with a set far away.
    far = np.random.default_rng(1).permutation(n).tolist()
    tied = spark.createDataFrame([(x, t) for i in range(n) for t, pair in ((i, (i, (i + 1) % n)), (n + i, (i, far[i]))) for x in set(pair)], "id long, token long")
    placed = spark.createDataFrame([(i, 0, n // 8) for i in range(n)], "id long, family long, blocks int")
    dealt = jaccard._block_pairs(cand, tied, placed).collect()
    tasks = {}
    for r in dealt:
        tasks.setdefault(r.id, set()).add((r.i, r.j))
    assert len(dealt) <= n + 4 * n
    assert all(tasks[i] & tasks[j] for i in range(n) for j in ((i + 1) % n, far[i]))


def test_decontamination_equals_brute_force(spark, monkeypatch):
    bench = [(1, prose(25)), (2, "Zebra, quagga!"), (3, ""), (4, None), (None, prose(12)), (1, prose(11)), (20, prose(10))]
    texts = [prose(30) + " " + bench[0][1].upper() + ". " + prose(5), "A zebra quagga ZEBRA-QUAGGA", bench[6][1] + " " + bench[5][1], "", None, prose(2000)]
    docs = spark.createDataFrame([(i, t, 0) for i, t in enumerate(texts)], "doc_id long, text string, items int")
    b = spark.createDataFrame([(i, t, "x") for i, t in bench], "item_id long, text string, runs string")

    def brute():
        for i, t in enumerate(texts):
            w, hit, who = common.alnum_words(t), set(), set()
            for item, x in bench:
                if item is not None:
                    for win in decontam.windows_of(common.alnum_words(x), 10):
                        for s in range(len(w) - len(win) + 1):
                            if tuple(w[s : s + len(win)]) == win:
                                hit |= set(range(s, s + len(win)))
                                who.add(item)
            yield i, len(w), len(hit), sorted(who)

    for most in (500_000, 3):  # one automaton, and several in turn
        monkeypatch.setattr(decontam, "MOST_WINDOWS", most)
        got = decontam.decontaminate(docs, b).collect()
        assert sorted((r.doc_id, r.n_words, r.n_hit, list(r.items)) for r in got) == list(brute())
        for r in got:
            assert sum(len(common.alnum_words(texts[r.doc_id][s.start : s.stop])) for s in r.spans) == r.n_hit
        assert [r.doc_id for r in decontam.without_contaminated(docs, b).orderBy("doc_id").collect()] == [3, 4, 5]


def test_repeats_that_begin_or_end_in_runs_equal_brute_force(spark):
    rng, rows = np.random.default_rng(11), []
    for k in range(12):
        mid, outer = [f"s{k}_{i}" for i in range(15)], [[f"o{k}_{j}_{i}" for i in range(30)] for j in range(4)]
        one, other = int(rng.integers(20, 30)), int(rng.integers(60, 90))
        for j, run in enumerate((one, other)):
            row = [f"-{k}"] * run + mid if k % 2 else mid + [f"-{k}"] * run
            rows.append((2 * k + j, " ".join(outer[j] + row + outer[2 + j])))
    n = substring.WINDOW
    words = {i: t.split() for i, t in rows}
    count = Counter(tuple(w[s : s + n]) for w in words.values() for s in range(len(w) - n + 1))
    want = {i: len({p for s in range(len(w) - n + 1) if count[tuple(w[s : s + n])] > 1 for p in range(s, s + n)}) for i, w in words.items()}
    got = {r.doc_id: r.n_removed for r in substring.removed_digest(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == want and min(want.values()) >= n


def test_cut_does_not_follow_the_sample(spark):
    rng = np.random.default_rng(4)
    y = (rng.random(3000) < 0.1).astype(int)
    filler, rows = [f"f{i}" for i in range(50)], []
    for i, toxic in enumerate(y.tolist()):
        words = rng.choice(filler, 12).tolist()
        for name, hot, cold in (("gray", 0.7, 0.25), ("dark", 0.5, 0.08), ("night", 0.4, 0.05)):
            words += [name] * int(rng.random() < (hot if toxic else cold))
        rows.append((i, " ".join(words), 1, toxic))
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(i, q, t) for i, _, q, t in rows], "doc_id long, quality int, toxic int")
    whole, half = (toxicity.fitted(docs, labels, m) for m in (6000, 500))
    cache = toxicity.Features()
    share = [np.mean([c.logits(t, cache)[-1] > c.thresholds[-1] for _, t, _, _ in rows]) for c in (whole, half)]
    assert abs(share[0] - share[1]) < 0.06
    each = [r.each for r in toxicity.labelled_sample(docs, labels, 500).where("toxic = 0").collect()]
    assert abs(sum(each) - (1 - y).sum()) < 1e-6
    score, label, times = rng.normal(size=40), rng.integers(0, 2, 40), rng.integers(1, 5, 40)
    assert toxicity.best_cut(score, label, times.astype(float)) == toxicity.best_cut(np.repeat(score, times), np.repeat(label, times))


def test_small_tables_are_passed_over_once(spark):
    df, _ = corpus(spark)
    packed = lm.pages(df.coalesce(1), "doc_id", "text")
    (row,) = packed.select("ids", "body").collect()
    vocab = lm.Vocabulary(np.arange(1, 11, dtype=np.uint64), np.full(10, 5), np.full(lm.KINDS, 2), np.full(lm.KINDS, 1), 100, 74)
    t, own = lm.Tokens(row.ids, row.body), lm.Trainer(lm.Network(vocab))
    begins, sizes = (np.cumsum(t.sizes) - t.sizes)[~t.held], t.sizes[~t.held]
    width = int(np.clip(int(sizes.sum()) // (lm.STEPS * 150), 8, lm.LANES))
    own.learn(lm.lay(sizes, begins, width), vocab.numbers(t.hash, t.kind, vocab.table()))
    trained = lm.train(packed, vocab, rounds=1)
    assert all(np.allclose(trained.p[k], own.net.p[k], atol=1e-6) for k in own.net.p)


def test_units_of_many_ids_beyond_the_head(spark, monkeypatch):
    monkeypatch.setattr(sentencepiece, "HEAD_UNITS", 0)
    texts = {1: "before", 2: "".join(np.random.default_rng(2).choice(list("acgt"), 240_000)), 3: "other words come after it"}
    got = {r.doc_id: r for r in sentencepiece.encode(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), MODEL).collect()}
    m = sentencepiece.Model.load(MODEL)
    table = {p: (i, s) for i, (p, s, x) in enumerate(zip(m.pieces, m.scores, m.normal)) if x}
    for i, t in texts.items():
        want = m.expand(sentencepiece.viterbi(sentencepiece.normalised(t), table, m.longest(), m.unknown_score))
        assert list(got[i].ids) == want and got[i].round_trip
    assert got[2].n_tokens > 65_535


@pytest.mark.parametrize("times", [2, 5])
def test_top_k_of_a_repeated_query_row(spark, times):
    rng = np.random.default_rng(6)
    vecs = [(i, rng.normal(size=4).round(2).tolist()) for i in range(60)]
    vecs += [(0, [9.0, 9.0, 9.0, 9.0])] * times
    df = spark.createDataFrame(vecs, "vec_id long, embedding array<float>")
    whole = [(i, [math.floor(1024 * float(np.float32(x))) for x in v]) for i, v in vecs]
    got = topk.top_k(df.where("vec_id > 0 or embedding[0] = 9"), F.col("vec_id") == 0).collect()
    ranked = sorted((-sum(x * 9216 for x in b), i) for i, b in whole if i != 0)[:10]
    assert sorted(map(tuple, got)) == [(0, k + 1, i, -s) for k, (s, i) in enumerate(ranked)]


# ---------------------------------------------------------------- bounds and recovery


def test_long_and_repeated_urls_end(spark):
    words = [f"t{i}" for i in range(200)]
    rows = [(0, "http://a.com/" + "/".join(words)), (1, "http://b.com/x"), (2, "http://b.com/y")] + [(10 + i, "http://c.com/" + "/".join(words[: 100 + i])) for i in range(40)]
    pages = spark.createDataFrame(rows, "page_id long, url string")
    labels = spark.createDataFrame([(i, int(i != 0 and i % 3 != 0), 0) for i, _ in rows], "doc_id long, quality int, toxic int")
    got = {r.page_id: r.verdict for r in urlfilter.judge(pages, labels).collect()}
    assert len(got) == len(rows) and got[0] == "block" and got[1] == "allow"


def test_rules_grown_by_size_are_those_of_growth(spark, monkeypatch):
    rng = np.random.default_rng(8)
    rows = [(i, "http://" + ".".join(sorted(set(rng.choice(list("abcdefg"), 4)))) + ".de/", int(rng.random() < 0.5)) for i in range(300)]
    labelled = spark.createDataFrame([(i, u) for i, u, _ in rows], "page_id long, url string").join(spark.createDataFrame([(i, bool(b)) for i, _, b in rows], "page_id long, rejected boolean"), "page_id").select(urlfilter.tokens(F.col("url")).alias("tokens"), "rejected")
    held = lambda: {(str(r.need), r.key, round(r.confidence, 9)) for r in urlfilter.mine_rules(labelled).collect()}
    grown = held()
    monkeypatch.setattr(urlfilter, "LONG_BASKET", 1)
    assert held() == grown and any(len(eval(need)) > 1 for need, _, _ in grown)


def test_urls_beyond_the_broadcast_bound(spark, monkeypatch):
    pages = spark.createDataFrame([(i, f"http://{'spam' if i % 3 else 'news'}.de/{i % 5}") for i in range(60)], "page_id long, url string")
    labels = spark.createDataFrame([(i, int(i % 3 == 0), 0) for i in range(60)], "doc_id long, quality int, toxic int")
    want = {r.page_id: r.verdict for r in urlfilter.judge(pages, labels).collect()}
    monkeypatch.setattr(urlfilter, "MOST_BROADCAST", 0)
    assert {r.page_id: r.verdict for r in urlfilter.judge(pages, labels).collect()} == want


def test_words_of_a_thousand_letters_are_told_apart():
    a = b"".join(b"b" if bin(i).count("1") % 2 else b"a" for i in range(2048))
    data = np.frombuffer(a + b" " + a.translate(bytes.maketrans(b"ab", b"ba")), np.uint8)
    x, y = common.span_hashes(data, *common.word_spans(data))
    assert x != y


def test_revisits_beyond_the_broadcast_bound(spark, monkeypatch):
    long = "x" * 1200
    pages = spark.createDataFrame([(i, "u", long if i % 2 else f"{i}" * 700 if i % 4 else "") for i in range(40)] + [(None, "u", long)], "page_id long, url string, html string")
    key = lambda: sorted(str((r.page_id, r.digest, r.refers_to)) for r in warc.with_revisits(pages, 1000).collect())
    want = key()
    monkeypatch.setattr(warc, "MOST_BROADCAST", 0)
    assert key() == want and sum("39)" in x for x in want) == 20


def test_pages_cut_otherwise_are_encoded_where_they_are(spark, monkeypatch):
    df, _ = corpus(spark)
    want = sorted(str((r.doc_id, list(r.ids))) for r in sentencepiece.encode(df, MODEL).collect())
    monkeypatch.setattr(sentencepiece, "HEAD_UNITS", 1)
    monkeypatch.setattr(sentencepiece, "answers", lambda said: common.answers(said).where("page = 0"))  # no page finds its answers
    assert sorted(str((r.doc_id, list(r.ids))) for r in sentencepiece.encode(df.repartition(3), MODEL).collect()) == want


def test_large_families_are_split_by_tokens(spark, monkeypatch):
    rng = np.random.default_rng(4)
    base = prose(150, rng).split()
    rows = []
    for i in range(120):  # a chain: each text shares most of its words with the next
        own = base[i : i + 60] + prose(8, rng).split()
        rows.append((i, " ".join(own if i % 3 else rows[-1][1].split()[:-1] + ["z"]) if i else " ".join(own)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = {r.doc_id: r.component_id for r in jaccard.classes(df, 2, 60, 100).collect()}
    monkeypatch.setattr(jaccard, "BLOCK", 8)
    got = {r.doc_id: r.component_id for r in jaccard.classes(df, 2, 60, 100).collect()}
    assert got == want and len(set(want.values())) < len(rows)


def test_top_k_of_odd_vectors_and_pruning(spark):
    big = [(100, [3e18, 1.0]), (101, [3e18, 1.0]), (200, []), (None, [1.0, 1.0]), (300, [1.0, 2.0])]
    got = topk.top_k(spark.createDataFrame(big, "vec_id long, embedding array<double>"), F.col("vec_id") % 100 == 0, 3).collect()
    assert {r.query_id for r in got} == {100, 300} and max(r.score for r in got) == 2**63 - 1
    rng = np.random.default_rng(2)
    rows = [(i, (rng.normal(size=8) * 0.01 + np.eye(8)[i % 8] * 4).tolist()) for i in range(800)]
    kept = topk.pruned(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") % 100 == 0).first()
    assert 0 < kept.meetings < kept.all_meetings / 2


def test_top_k_sends_queries_once_to_a_part(spark, monkeypatch):
    monkeypatch.setattr(topk, "LEAST_PART", 40)
    monkeypatch.setattr(topk, "PART_BYTES", 40 * 8 * 6)
    monkeypatch.setattr(topk, "ASKED_BYTES", 8 * 6 * 5)
    monkeypatch.setattr(topk, "SCORES", 100)
    rng = np.random.default_rng(12)
    vecs = [(i, rng.normal(size=6).tolist()) for i in range(400)] + [(400 + i, [40.5] + [0.5] * 5) for i in range(150)]
    whole = np.array([np.floor(1024 * np.array(v)) for _, v in vecs]).astype(np.int64)
    scores, want = whole @ whole.T, []
    for q in range(0, 550, 20):
        order = sorted((-int(s), i) for i, s in enumerate(scores[q]) if i != q)[:10]
        want += [(q, k + 1, i, -s) for k, (s, i) in enumerate(order)]
    _, _, found = topk._join(spark.createDataFrame(vecs, "vec_id long, embedding array<double>"), F.col("vec_id") % 20 == 0)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "CoGroup" in plan and "Broadcast" not in plan and "Join" not in plan  # blocks of queries went out once a block of a cell, and to the driver where Spark took them for small
    got = topk.top_k(spark.createDataFrame(vecs, "vec_id long, embedding array<double>"), F.col("vec_id") % 20 == 0).collect()
    assert sorted(map(tuple, got)) == sorted(want)


def test_every_unit_of_the_head_is_found():
    keys = np.random.default_rng(1).integers(0, 1 << 64, sentencepiece.HEAD_UNITS, dtype=np.uint64)
    tables = sentencepiece.probe_tables(keys)
    assert (sentencepiece.probe(keys, keys, tables) == np.arange(len(keys))).all()  # two were lost
    assert (sentencepiece.probe(keys[:1000] + np.uint64(1), keys, tables) == -1).all()
    twice = np.array([5, 5, 7], np.uint64)
    assert sentencepiece.probe(twice, twice, sentencepiece.probe_tables(twice)).tolist() == [0, 0, 2]
