"""A training corpus from the documents table: five stages, each an operator of sketchlearn.llm.

Each stage gets what the one before kept, and its decisions take effect: toxic
documents go, of near duplicates one stays, repeated passages are cut out,
documents with benchmark passages go, and what is left is encoded.

Defined results: rows of null id pass the duplicate stage (they name no
document); null and empty texts are kept, and encoded to no ids; of rows that
repeat each other in id and text one stays; an empty table passes all stages as
an empty table, and without labels or benchmark items nothing is rejected;
further columns, whatever their names, go through unread up to the last stage,
whose columns are its own; n_chars follows a text that was cut.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sketchlearn.llm import decontam, jaccard, sentencepiece, substring, toxicity
from sketchlearn.llm.common import written


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier chain does not reject."""
    return toxicity.without_toxic(docs, _table(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near duplicates (five words, similarity 0.8) the document with the smallest id, once."""
    found = jaccard.classes(docs, n=5, num=80, den=100)
    kept = found.where(F.col("doc_id") == F.col("component_id")).select("doc_id").distinct()
    named = docs.where("doc_id is not null").join(kept, "doc_id", "left_semi").dropDuplicates(["doc_id", "text"])
    return named.select(docs.columns).unionByName(docs.where("doc_id is null"))


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the words of windows of 35 words that stand elsewhere too."""
    return substring.without_repeats(docs)


def contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no window of ten words of a benchmark item."""
    return decontam.without_contaminated(docs, _table(spark, sf_dir, "benchmark"))


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids, round_trip."""
    return sentencepiece.encode(docs, sentencepiece.default_model(spark))


STAGES = [
    ("toxicity", toxic),
    ("n-gram Jaccard join", near_duplicates),
    ("substring dedup", repeated_passages),
    ("benchmark decontamination", contaminated),
    ("SentencePiece encoding and decoding", encoded),
]

#: The fitted classifier can't be said in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table, each written and read again."""
    docs = _table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), spark)
    return STAGES[-1][1](spark, docs, sf_dir)
