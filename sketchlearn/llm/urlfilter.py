"""URL filter: fixed host and path rules, and rules mined from labelled pages.

DataFrame functions only. A url's tokens are its host labels and path and query
words. FP-growth over the tokens and label of labelled pages gives association
rules {tokens} -> rejected of at most three tokens (a parameter); those with
enough support and confidence are kept, and of them those that no kept rule
with fewer tokens makes redundant. An inverted index maps a rule's rarest token
to the rule: a url meets only the rules under its own tokens, and a rule holds
if all its tokens are there. Tokens that no label can tell apart are one token
here, so that a long url, however often it is labelled, has no subsets to list.

Defined results: a null url, or one without "://", has empty host and path, no
rule, no tokens, and is allowed; a label of a page that is not there is unused;
without labels no rules are mined; repeated rows are judged alike.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, written

#: Tokens of a basket up to which FP-growth lists its subsets; rows of rules or urls up to which they are broadcast; shares of a hot key beyond.
LONG_BASKET, MOST_BROADCAST, SALTS = 16, 200_000, 32
#: Item that stands for a rejected page among the mined items; a token never holds a blank.
REJECTED = "is rejected"


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str

    @property
    def name(self) -> str:
        return self.host + self.path


#: The rules that the job states.
FIXED_RULES = (
    Rule("block", "net", "/"),
    Rule("allow", "example.net", "/en/"),
    Rule("block", "example.com", "/de/"),
    Rule("allow", "org", "/fr/"),
)


def host_path(url: Column) -> tuple[Column, Column]:
    """Host: after the first "://" up to "/", "?", "#" or the end, A-Z lower-cased; path: from there up to "?", "#" or the end."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    return F.coalesce(ascii_lower(host), F.lit("")), F.coalesce(path, F.lit(""))


def fixed_rule(host: Column, path: Column, rules=FIXED_RULES) -> tuple[Column, Column]:
    """Name and verdict of the longest rule that fits; null if none does."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.name), r.name)):  # the longest is tried first
        fits = ((host == r.host) | F.endswith(host, F.lit("." + r.host))) & F.startswith(path, F.lit(r.path))
        name, verdict = F.when(fits, F.lit(r.name)).otherwise(name), F.when(fits, F.lit(r.verdict)).otherwise(verdict)
    return name, verdict


def tokens(url: Column) -> Column:
    """Distinct lower-case tokens of host, path and query; numbers alone say nothing and are left out."""
    rest = ascii_lower(F.regexp_replace(F.coalesce(url, F.lit("")), r"(?s)^.*?://", ""))
    return F.array_distinct(F.filter(F.split(rest, r"[^a-z0-9\u0080-￿]+"), lambda t: (t != "") & ~t.rlike("^[0-9]+$")))


def _stats(baskets: DataFrame) -> DataFrame:
    """(token, n, bad, a, b): pages and rejected pages with a token, and a 128-bit name of the set of baskets that hold it."""
    name = lambda salt: F.xxhash64("tokens", "rejected", F.lit(salt))
    seen = baskets.select("n", "rejected", name(0).alias("a"), name(1).alias("b"), F.explode("tokens").alias("token"))
    return seen.groupBy("token").agg(F.sum("n").alias("n"), F.sum(F.when(F.col("rejected"), F.col("n")).otherwise(0)).alias("bad"), F.bit_xor("a").alias("a"), F.bit_xor("b").alias("b"))


def _bounded(df: DataFrame, most: int = MOST_BROADCAST) -> DataFrame:
    """Broadcast where the counted rows allow it."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def _by_growth(baskets: DataFrame, least: int, most_tokens: int) -> DataFrame:
    """(need, n, bad) of sets of 2 to most_tokens tokens that stand in `least` rejected pages, by FP-growth over the tokens and the label."""
    rows = baskets.withColumn("one", F.explode(F.sequence(F.lit(1).cast("long"), F.col("n")))).select(F.when(F.col("rejected"), F.array_append("tokens", F.lit(REJECTED))).otherwise(F.col("tokens")).alias("items"))
    model = FPGrowth(itemsCol="items", minSupport=(least - 0.5) / baskets.agg(F.sum("n")).first()[0], minConfidence=0.0).fit(rows)
    found = written(model.freqItemsets.where(F.size("items") <= most_tokens + 1))
    bad = F.array_contains("items", REJECTED)
    need = F.array_sort(F.array_remove("items", REJECTED))
    with_label = found.where(bad & (F.size("items") > 2)).select(need.alias("need"), F.col("freq").alias("bad"))
    return with_label.join(found.where(~bad & (F.size("items") > 1)).select(need.alias("need"), F.col("freq").alias("n")), "need").select("need", "n", "bad")


def _by_size(baskets: DataFrame, least: int, most_tokens: int) -> DataFrame:
    """The same sets grown by size, a token at a time and only from sets that are frequent: for baskets whose subsets are too many to be listed."""
    rest = lambda at: F.slice("tokens", at + 1, F.size("tokens"))
    grown = baskets.select("n", "rejected", F.posexplode("tokens").alias("i", "t"), "tokens").select("n", "rejected", F.array("t").alias("need"), rest(F.col("i") + 1).alias("tokens"))
    out = None
    for _ in range(most_tokens - 1):
        grown = grown.select("n", "rejected", "need", F.posexplode("tokens").alias("i", "t"), "tokens").select("n", "rejected", F.array_append("need", F.col("t")).alias("need"), rest(F.col("i") + 1).alias("tokens"))
        counts = written(grown.groupBy("need").agg(F.sum("n").alias("n"), F.sum(F.when(F.col("rejected"), F.col("n")).otherwise(0)).alias("bad")).where(F.col("bad") >= least))
        out = counts if out is None else out.unionByName(counts)
        grown = grown.join(_bounded(counts.select("need")), "need", "left_semi")
    return out


def mine_rules(labelled: DataFrame, min_support: float = 0.002, min_confidence: float = 0.5, most_tokens: int = 3) -> DataFrame:
    """labelled: tokens array<string>, rejected boolean. Returns need array<array<string>>, key (a token of the rule's rarest part), confidence, support.

    A rule holds if of each of its parts one token is there. A part is all
    tokens that stand in the same baskets: they can't be told apart by the
    labels, and one of them is mined for all. A token found on rejected pages
    only is a rule by itself, and every rule with it is redundant, so it is not
    mined further. What is left goes to FP-growth; where a basket of more than
    LONG_BASKET such tokens would have too many subsets, the same sets are grown
    by size. Rules have most_tokens parts at most, in either way.
    """
    spark = labelled.sparkSession
    empty = spark.createDataFrame([], "need array<array<string>>, key string, confidence double, support double")
    baskets = written(labelled.where(F.size("tokens") > 0).groupBy(F.array_sort("tokens").alias("tokens"), "rejected").agg(F.count(F.lit(1)).alias("n")))
    total = baskets.agg(F.sum("n")).first()[0]
    if not total:
        return empty
    least = max(1, math.ceil(min_support * total - 1e-9))
    stats = written(_stats(baskets).where(F.col("bad") >= least))
    parts = written(stats.groupBy("n", "bad", "a", "b").agg(F.min("token").alias("token"), F.sort_array(F.collect_list("token")).alias("tokens")).select("token", "tokens", "n", "bad"))
    open_ = parts.where("bad < n").select("token")
    reduced = baskets.withColumn("id", F.xxhash64("tokens", "rejected")).select("id", "n", "rejected", F.explode("tokens").alias("token"))
    reduced = written(reduced.join(_bounded(open_), "token", "left_semi").groupBy("id", "n", "rejected").agg(F.sort_array(F.collect_set("token")).alias("tokens")).select("n", "rejected", "tokens"))
    single = parts.select(F.array("token").alias("need"), "n", "bad")
    longest = reduced.agg(F.max(F.size("tokens"))).first()[0] or 0
    grown = single.limit(0) if longest < 2 else (_by_growth if longest <= LONG_BASKET else _by_size)(reduced, least, most_tokens)
    rules = written(single.unionByName(grown).withColumn("confidence", F.col("bad") / F.col("n")).where(F.col("confidence") >= min_confidence))
    # A rule is redundant if a rule over some of its parts is at least as confident: joined by each of its subsets.
    some = F.expr("filter(transform(sequence(1, cast(shiftleft(1, size(need)) - 2 as int)), m -> filter(need, (t, i) -> getbit(m, i) = 1)), x -> size(x) < size(need))")
    subsets = rules.where(F.size("need") > 1).select("need", "confidence", F.explode(some).alias("less"))
    redundant = subsets.join(rules.select(F.col("need").alias("less"), F.col("confidence").alias("at_least")), "less").where("at_least >= confidence").select("need").distinct()
    kept = rules.join(redundant, "need", "left_anti")
    each = kept.select(F.xxhash64("need").alias("rule_id"), "confidence", (F.col("bad") / total).alias("support"), F.explode("need").alias("token")).join(parts.select("token", "tokens", "n"), "token")
    whole = each.groupBy("rule_id", "confidence", "support").agg(F.sort_array(F.collect_list("tokens")).alias("need"), F.min_by("tokens", F.struct("n", "token")).alias("keys"))
    return written(whole.select("need", F.explode("keys").alias("key"), "confidence", "support"))


def matched_urls(urls: DataFrame, rules: DataFrame) -> DataFrame:
    """Distinct urls that a mined rule rejects: (url, confidence of the best rule). Rules up to a counted bound go to every task; beyond it a key's urls are dealt out by salt."""
    seen = urls.where(F.col("url").isNotNull()).groupBy("url").agg(F.lit(1).alias("one")).select("url", tokens(F.col("url")).alias("tokens"))
    asked = seen.select("url", "tokens", F.explode("tokens").alias("key"))
    if rules.limit(MOST_BROADCAST + 1).count() <= MOST_BROADCAST:
        met = asked.join(F.broadcast(rules), "key")
    else:
        met = asked.withColumn("salt", F.pmod(F.xxhash64("url"), F.lit(SALTS))).join(rules.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)).cast("array<bigint>"))), ["key", "salt"])
    return met.where(F.forall("need", lambda part: F.arrays_overlap(part, F.col("tokens")))).groupBy("url").agg(F.max("confidence").alias("confidence"))


def with_match(own: DataFrame, matched: DataFrame) -> DataFrame:
    """own with the confidence of its url's rule. A url that a third of all rows hold is one row of matched and is dealt to SALTS tasks, not to one."""
    matched = written(matched)
    if matched.limit(MOST_BROADCAST + 1).count() <= MOST_BROADCAST:
        return own.join(F.broadcast(matched), "url", "left")
    salted = own.withColumn("salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)))
    return salted.join(matched.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)).cast("array<bigint>"))), ["url", "salt"], "left").drop("salt")


def judge(pages: DataFrame, labels: DataFrame, min_support: float = 0.002, min_confidence: float = 0.5) -> DataFrame:
    """page_id, host, path, rule, verdict, confidence (of the mined rule, where one rejects the url and no fixed rule fits).

    A page is rejected in the sense of the labels if the label of its number says quality 0 or toxic 1.
    """
    own = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"))
    said = labels.groupBy(F.col("doc_id").cast("long").alias("page_id")).agg(F.max((F.coalesce("quality", F.lit(1)) == 0) | (F.coalesce("toxic", F.lit(0)) == 1)).alias("rejected"))
    rules = mine_rules(own.join(said, "page_id").select(tokens(F.col("url")).alias("tokens"), "rejected"), min_support, min_confidence)
    host, path = host_path(F.col("url"))
    name, verdict = fixed_rule(F.col("host"), F.col("path"))
    out = with_match(own, matched_urls(own, rules)).withColumn("host", host).withColumn("path", path)
    return out.select("page_id", "host", "path", name.alias("rule"), F.coalesce(verdict, F.when(F.col("confidence").isNotNull(), F.lit("block")).otherwise(F.lit("allow"))).alias("verdict"), F.when(verdict.isNull(), F.col("confidence")).alias("confidence"))
