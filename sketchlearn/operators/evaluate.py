"""Splits, accuracy, reports and comparisons."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.sets import md5_number


def split(key: Column, test_fraction: float, seed: int = 7) -> Column:
    """"test" or "train" by a hash of the key: the same in every engine and run. With the text as key copies fall on one side."""
    return F.when(md5_number(F.concat_ws("|", F.lit(f"{seed}|split"), key.cast("string")), 1000) < int(1000 * test_fraction), "test").otherwise("train")


def accuracy(df: DataFrame, *keys: str) -> DataFrame:
    return df.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_test"), F.avg((F.col("pred") == F.col("y")).cast("double")).alias("accuracy"))


def binary_report(df: DataFrame) -> DataFrame:
    """Confusion counts, precision, recall, F1, balanced accuracy, and AUC from mean ranks of tied scores.

    Ranks in two steps: the counts of 64ths of a point are summed up in one small
    window, the scores inside each in a window of its own.
    """
    counted = df.groupBy("score").agg(F.count_if(F.col("y") == 1).alias("p"), F.count_if(F.col("y") == -1).alias("n")).withColumn("g", F.floor(F.col("score") * 64))
    coarse = counted.groupBy("g").agg(F.sum("n").alias("gn")).withColumn("g_below", F.sum("gn").over(Window.orderBy("g")) - F.col("gn"))
    inside = counted.withColumn("inside", F.sum("n").over(Window.partitionBy("g").orderBy("score")) - F.col("n"))
    ranked = inside.join(coarse.select("g", "g_below"), "g").withColumn("below", F.col("g_below") + F.col("inside"))
    auc = ranked.agg((F.sum(F.col("p") * (F.col("below") + F.col("n") / 2)) / F.nullif(F.sum("p") * F.sum("n"), F.lit(0))).alias("auc"))
    hit = lambda y, p: F.count_if((F.col("y") == y) & (F.col("pred") == p))
    c = df.agg(hit(1, 1).alias("tp"), hit(-1, 1).alias("fp"), hit(1, -1).alias("fn"), hit(-1, -1).alias("tn"))
    part = lambda a, b: F.col(a) / F.nullif(F.col(a) + F.col(b), F.lit(0))
    return c.crossJoin(auc).select("tp", "fp", "fn", "tn", part("tp", "fp").alias("precision"), part("tp", "fn").alias("recall"), (2 * F.col("tp") / F.nullif(2 * F.col("tp") + F.col("fp") + F.col("fn"), F.lit(0))).alias("f1"), ((part("tp", "fn") + part("tn", "fp")) / 2).alias("balanced_accuracy"), "auc")


def match_accuracy(results: DataFrame, target: float, *keys: str) -> DataFrame:
    """For each method (or other keys) the smallest k that reaches the accuracy, and its bits a row."""
    keys = keys or ("method",)
    return results.where(F.col("accuracy") >= target).groupBy(*keys).agg(F.min(F.struct("k", "bits_per_row")).alias("x")).select(*keys, "x.k", "x.bits_per_row")


def binned_report(bins: DataFrame, *keys: str) -> DataFrame:
    """(keys, n_test, accuracy, auc) from counts of positive, negative and right rows by score bin. Counts are summed before
    the shuffle and one key's bins are ranked in one task: as many as scores differ, not as there are rows. AUC: scores of a bin are ties."""
    total = bins.groupBy(*keys, "bin").agg(F.sum("p").alias("p"), F.sum("n").alias("n"), F.sum("good").alias("good"))
    ranked = total.withColumn("below", F.sum("n").over(Window.partitionBy(*keys).orderBy("bin")) - F.col("n"))
    both = F.nullif(F.sum("p") * F.sum("n"), F.lit(0))
    return ranked.groupBy(*keys).agg(F.sum(F.col("p") + F.col("n")).alias("n_test"), (F.sum("good") / F.sum(F.col("p") + F.col("n"))).alias("accuracy"), (F.sum(F.col("p") * (F.col("below") + F.col("n") / 2)) / both).alias("auc"))


def mean_of_runs(runs: DataFrame, *keys: str) -> DataFrame:
    """(keys, runs, accuracy, deviation) of rows (keys, run, accuracy)."""
    return runs.groupBy(*keys).agg(F.count(F.lit(1)).alias("runs"), F.avg("accuracy").alias("accuracy"), F.stddev_samp("accuracy").alias("deviation"))


def estimator_error(df: DataFrame, *keys: str) -> DataFrame:
    """Over repeated seeds: bias, variance and mean squared error of `estimate` against `truth`."""
    d = F.col("estimate") - F.col("truth")
    return df.groupBy(*keys).agg(F.avg(d).alias("bias"), F.var_samp("estimate").alias("variance"), F.avg(d * d).alias("mse"))


def auc(score: np.ndarray, y: np.ndarray) -> float:
    order = np.argsort(score, kind="stable")
    rank = np.empty(len(score))
    s = score[order]
    first = np.searchsorted(s, s, "left")
    last = np.searchsorted(s, s, "right")
    rank[order] = (first + last + 1) / 2
    p = (y > 0).sum()
    n = len(y) - p
    return float((rank[y > 0].sum() - p * (p + 1) / 2) / (p * n)) if p and n else float("nan")
