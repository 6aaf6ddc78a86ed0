from collections import Counter

import numpy as np

import corpus_pipeline as pipeline
from sketchlearn.llm import common, decontam, sentencepiece, substring

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names, before = docs.columns, docs.count()
    for name, stage in pipeline.STAGES[:-1]:
        docs = common.written(stage(spark, docs, SF), spark)
        assert docs.columns == names and 0 < docs.count() <= before, name
        before = docs.count()
    assert docs.select("doc_id").distinct().count() == before
    assert decontam.decontaminate(docs, spark.read.parquet(f"{SF}/benchmark.parquet")).where("n_hit > 0").count() == 0
    assert docs.where("n_chars <> length(text)").count() == 0
    out = pipeline.STAGES[-1][1](spark, docs, SF)
    assert out.count() == before and out.where("not round_trip").count() == 0


def test_edge_rows(spark):
    rows = [(1, "a b c d e f"), (1, "a b c d e f"), (2, "A b c d e f"), (3, None), (4, ""), (None, "x y z")]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    kept = pipeline.near_duplicates(spark, docs, SF).collect()
    assert sorted((str(r.doc_id), r.text) for r in kept if r.text) == [("1", "a b c d e f"), ("None", "x y z")]
    assert sorted(r.doc_id for r in kept if not r.text) == [3, 4]
    for _, stage in pipeline.STAGES:
        assert stage(spark, docs.limit(0), SF).count() == 0


def test_whole_run_equals_brute_force(spark, tmp_path):
    """Without labels the first stage keeps all; the others are done here by their definitions."""
    rng = np.random.default_rng(12)
    vocabulary = [f"w{i}" for i in range(500)]
    prose = lambda n: " ".join(rng.choice(vocabulary, n))
    passage, item, base = prose(50), prose(14), [prose(90) for _ in range(12)]
    texts = [*base[:6], base[0], base[1].replace(" ", "  ", 3), base[2] + " tail", "W1 " + base[3][3:], base[6] + " " + passage, passage + "\n" + base[7], base[8] + " " + item, item.upper() + ". " + base[9], "short text", "", None, "a " * 300, base[10] + " \u2581 \u00e9\u00df", "  " + base[11]]
    docs = [(i, t, "en", "s", len(t or "")) for i, t in enumerate(texts)]
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").coalesce(1).write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")

    words = lambda t: [w.lower() for w in common.blank_words(t)]
    held = {i: (w := words(t)) and {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} for i, t in enumerate(texts)}
    root = {i: i for i in held}
    for a in held:
        for b in held:
            if held[a] and held[b] and 100 * len(held[a] & held[b]) >= 80 * len(held[a] | held[b]):
                low, high = sorted((root[a], root[b]))
                root = {i: low if r == high else r for i, r in root.items()}
    kept = {i: texts[i] for i in root if root[i] == i}
    n = substring.WINDOW
    every = Counter(tuple(w[s : s + n]) for t in kept.values() for w in [common.blank_words(t)] for s in range(len(w) - n + 1))
    out = {}
    for i, t in kept.items():
        w = common.blank_words(t)
        gone = np.zeros(len(w), bool)
        for s in range(len(w) - n + 1):
            if every[tuple(w[s : s + n])] > 1:
                gone[s : s + n] = True
        out[i] = substring.cut(t.encode(), gone).decode() if gone.any() else t
    asked = common.alnum_words(item)
    windows = {tuple(asked[s : s + 10]) for s in range(len(asked) - 9)}
    clean = {i: t for i, t in out.items() if not any(tuple(w[s : s + 10]) in windows for w in [common.alnum_words(t)] for s in range(len(w) - 9))}
    m = sentencepiece.Model.load(sentencepiece.default_model(spark))
    want = {i: m.expand(sentencepiece.viterbi(sentencepiece.normalised(t), m.table(), m.longest(), m.unknown_score)) for i, t in clean.items()}
    got = {r.doc_id: list(r.ids) for r in pipeline.run(spark, str(tmp_path)).collect()}
    assert got == want
    assert not {6, 7, 8, 9, 12, 13} & set(got) and {10, 11, 14, 15, 16, 17} <= set(got) and out[10] != texts[10]


def test_further_columns_pass(spark, tmp_path):
    """Columns named like those that the stages use themselves."""
    rows = [(i, f"text {i} " + "word " * 60 * (i % 3), i, "p", f"f{i}", [i], i * 2) for i in range(8)] + [(8, None, None, None, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, page long, lang string, fp string, said array<int>, n_chars long")
    none = spark.createDataFrame([], "item_id long, text string, doc_id long, quality int, toxic int").coalesce(1)
    for name in ("labels", "benchmark"):
        none.write.parquet(f"{tmp_path}/{name}.parquet")
    for _, stage in pipeline.STAGES[:-1]:
        docs = common.written(stage(spark, docs, str(tmp_path)), spark)
        assert docs.columns == ["doc_id", "text", "page", "lang", "fp", "said", "n_chars"]
    kept = {r.doc_id: r for r in docs.collect()}
    assert all(kept[i].fp == f"f{i}" and list(kept[i].said) == [i] and kept[i].page == i for i in kept if i < 8) and kept[8].text is None
    assert pipeline.STAGES[-1][1](spark, docs, str(tmp_path)).count() == len(kept)
