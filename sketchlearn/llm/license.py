"""License scan with a positional index of rare words. DataFrame functions only.

Each template is a run of words with a mandatory key phrase. The template words
are weighed by their document frequency over all texts, and the rarest of each
template make one positional index: word -> (template, place). A file is looked
through once; each of its words that the index holds turns its own place into
places where templates would begin. Beginnings on which two words agree are
kept, the key phrase is verified there, and the share of template words in
their places is the score. Files without any key phrase can't pass the
verification and skip the look-up.

Defined results: a null or empty text has no words, labels or places, and score
0; a phrase counts at each place where it stands, overlaps included; repeated
rows are answered each; other columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import LOWER, UPPER

# The phrases of the base labels, as the job states them.
BASE_PHRASES = {
    "mit": "under the mit license",
    "apache-2": "apache license version 2",
    "cc-by-nc": "cc by nc",
}


@dataclass(frozen=True)
class Template:
    label: str
    text: str
    key: str


# Customary license lines and notices, in words, with their mandatory phrases.
TEMPLATES = (
    Template("apache-2", "licensed under the apache license version 2 0", "apache license version 2"),
    Template("apache-2", "you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0", "apache org licenses license 2 0"),
    Template("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "redistribution and use in source and binary forms"),
    Template("cc-by", "licensed under cc by 4 0", "cc by 4 0"),
    Template("cc-by-nc", "licensed under cc by nc 4 0", "cc by nc"),
    Template("cc-by-sa", "licensed under cc by sa 4 0", "cc by sa"),
    Template("gpl-3", "this work is licensed under the gnu general public license version 3", "gnu general public license version 3"),
    Template("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", "gnu general public license"),
    Template("mit", "released under the mit license", "mit license"),
    Template("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files to deal in the software without restriction", "permission is hereby granted free of charge"),
    Template("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0", "mozilla public license v 2 0"),
    Template("lgpl", "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation", "gnu lesser general public license"),
    Template("lgpl", "licensed under the gnu lesser general public license version 3", "gnu lesser general public license"),
    Template("agpl-3", "it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license", "gnu affero general public license"),
    Template("agpl-3", "licensed under the gnu affero general public license version 3", "gnu affero general public license"),
    Template("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies", "permission to use copy modify and or distribute this software"),
    Template("epl-2", "this program and the accompanying materials are made available under the terms of the eclipse public license 2 0", "eclipse public license"),
    Template("cc0", "to the extent possible under law the author has waived all copyright and related or neighboring rights to this work", "waived all copyright and related or neighboring rights"),
    Template("cc0", "licensed under cc0 1 0 universal", "cc0 1 0"),
    Template("unlicense", "this is free and unencumbered software released into the public domain", "free and unencumbered software released into the public domain"),
    Template("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software", "in no event will the authors be held liable"),
    Template("bsl-1", "distributed under the boost software license version 1 0", "boost software license version 1 0"),
    Template("mit", "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software", "shall be included in all copies or substantial portions of the software"),
    Template("bsd", "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software", "may be used to endorse or promote products derived from this software"),
    Template("proprietary", "all rights reserved", "all rights reserved"),
)
#: Rarest words of a template that the index holds beside two of its key phrase, and the least share of words in place.
RARE_WORDS, LEAST_SCORE = 4, 0.6

_APART = "".join(chr(b) for b in range(128) if not (48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122))


def words(text: Column) -> Column:
    """Words of letters, digits and non-ASCII characters, A-Z lower-cased: one translation and one split at blanks."""
    plain = F.translate(F.coalesce(text, F.lit("")), UPPER + _APART, LOWER + " " * len(_APART))
    return F.filter(F.split(plain, " "), lambda w: w != "")


def _array(items: list[str]) -> str:
    return "array(" + ", ".join(f"'{x}'" for x in items) + ")"


def document_frequencies(rows: DataFrame, vocabulary: list[str]) -> dict[str, int]:
    """In how many texts each template word stands, over all rows; the result is as small as the templates."""
    held = F.array_intersect("words", F.array(*map(F.lit, vocabulary)))
    return {r.w: r.n for r in rows.select(F.explode(held).alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("n")).collect()}


def templates_sql(templates: tuple[Template, ...]) -> str:
    parts = []
    for t in templates:
        own, key = t.text.split(), t.key.split()
        at = next(i for i in range(len(own)) if own[i : i + len(key)] == key)
        parts.append(f"named_struct('label', '{t.label}', 'own', {_array(own)}, 'key', {_array(key)}, 'at', {at})")
    return f"array({', '.join(parts)})"


def postings(templates: tuple[Template, ...], df: dict[str, int]) -> dict[str, list[tuple[int, int]]]:
    """Of the rarest words of each template (those of the highest IDF), where they stand: word -> (template, place).
    The two rarest words of the key phrase are always among them: a verified place has their two votes, so none is missed."""
    out: dict[str, list[tuple[int, int]]] = {}
    for n, t in enumerate(templates):
        own = t.text.split()
        rarest = lambda some: sorted(set(some), key=lambda w: (df.get(w, 0), w))
        rare = {*rarest(own)[:RARE_WORDS], *rarest(t.key.split())[:2]}
        for place, w in enumerate(own):
            if w in rare:
                out.setdefault(w, []).append((n, place))
    return out


def _match(templates: tuple[Template, ...], index: dict[str, list[tuple[int, int]]]) -> str:
    """Label and score of each beginning on which two indexed words agree and where the key phrase stands. A word is found in the index by a hash set first, so that most words of a file cost one probe."""
    held = ", ".join(f"'{w}'" for w in sorted(index))
    table = "map(" + ", ".join(f"'{w}', array(" + ", ".join(f"named_struct('t', {t}, 'at', {at})" for t, at in index[w]) + ")" for w in sorted(index)) + ")"
    votes = f"""array_sort(flatten(transform(filter(sequence(0, size(words) - 1), i -> get(words, i) in ({held})),
      i -> transform(element_at({table}, get(words, i)), p -> named_struct('t', p.t, 'o', i - p.at)))))"""
    agreed = f"aggregate(array({votes}), cast(array() as array<struct<t:int,o:int>>), (none, all) -> array_distinct(filter(all, (x, i) -> get(all, i - 1) = x)))"
    scored = """named_struct('label', c.m.label, 'score', if(c.o + c.m.at >= 0 and slice(words, greatest(c.o + c.m.at, 0) + 1, size(c.m.key)) = c.m.key,
      aggregate(sequence(0, size(c.m.own) - 1), 0, (n, p) -> n + if(get(words, c.o + p) = get(c.m.own, p), 1, 0)) / size(c.m.own), null))"""
    return f"transform(transform({agreed}, v -> named_struct('m', get({templates_sql(templates)}, v.t), 'o', v.o)), c -> {scored})"


def scan(docs: DataFrame, templates: tuple[Template, ...] = TEMPLATES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, places (array of struct(label, word): the base phrases), base_labels and labels (sorted arrays), score."""
    rows = docs.select(F.col(id_col).alias("doc_id"), words(F.col(text_col).cast("string")).alias("words"))
    df = document_frequencies(rows, sorted({w for t in templates for w in t.text.split()}))
    keys = sorted({t.key for t in templates} | set(BASE_PHRASES.values()))
    joined = rows.withColumn("joined", F.concat(F.lit(" "), F.array_join("words", " "), F.lit(" ")))
    any_key = " or ".join(f"contains(joined, ' {k} ')" for k in keys)

    def places(label: str, phrase: str) -> str:
        own = phrase.split()
        here = " and ".join(f"get(words, i + {j}) = '{w}'" for j, w in enumerate(own))
        return f"if(contains(joined, ' {phrase} '), transform(filter(sequence(0, size(words) - {len(own)}), i -> {here}), i -> named_struct('label', '{label}', 'word', cast(i as bigint))), cast(array() as array<struct<label:string,word:bigint>>))"

    gated = joined.select("doc_id", "words", F.expr("cast(size(words) as bigint)").alias("n_words"), F.expr("concat(" + ", ".join(places(*x) for x in BASE_PHRASES.items()) + ")").alias("places"), F.expr(any_key).alias("gate"))
    empty = "cast(array() as array<struct<label:string,score:double>>)"
    match = _match(templates, postings(templates, df))
    found = gated.select("doc_id", "n_words", "places", F.expr(f"if(gate, filter({match}, m -> m.score is not null), {empty})").alias("found"))
    base = F.array_sort(F.array_distinct(F.transform("places", lambda p: p.label)))
    own = F.transform(F.filter("found", lambda m: m.score >= LEAST_SCORE), lambda m: m.label)
    return found.select("doc_id", "n_words", "places", base.alias("base_labels"), F.array_sort(F.array_distinct(F.concat(base, own))).alias("labels"), F.coalesce(F.array_max(F.transform("found", lambda m: m.score)), F.lit(0.0)).alias("score"))
