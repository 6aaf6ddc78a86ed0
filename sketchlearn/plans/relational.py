"""Operators around the methods, each as one plan on the tables: filters, joins, aggregates, windows, set operations, and the batch twins of the streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import minwise, sets
from ..functions.hashing import TwoUniversal
from ..sources.tables import load_table

K_EVENTS = 8


def filter_documents(spark, d):
    """Equality and range predicates, pushed to the scan."""
    t = load_table(spark, d, "documents")
    return t.where((F.col("lang") == "en") & F.col("source").isin("src1", "src2", "src3") & F.col("n_chars").between(500, 2000)).select("doc_id", "source", "n_chars")


def filter_pages(spark, d):
    return load_table(spark, d, "pages").where(F.col("url").like("https://%") & F.col("url").rlike("/(en|fr)/")).select("page_id", "url")


def customer_part_sets(spark, d):
    """Shuffled equi-join and set building: part counts of each customer."""
    return sets.customers(spark, d).select("id", F.size("items").cast("long").alias("parts"), F.array_min("items").alias("least"), F.array_max("items").alias("most"))


def labelled_documents(spark, d):
    docs, labels = load_table(spark, d, "documents"), load_table(spark, d, "labels")
    return docs.join(labels, "doc_id").groupBy("lang", "quality", "toxic").agg(F.count(F.lit(1)).alias("n"))


def semi_labelled(spark, d):
    return load_table(spark, d, "documents").join(load_table(spark, d, "labels"), "doc_id", "left_semi").select("doc_id", "lang")


def anti_labelled(spark, d):
    return load_table(spark, d, "documents").join(load_table(spark, d, "labels"), "doc_id", "left_anti").select("doc_id", "lang")


def full_outer_labels(spark, d):
    """Documents and labels, either side absent: counted by presence."""
    a = load_table(spark, d, "documents").select("doc_id", F.lit(1).alias("in_documents"))
    b = load_table(spark, d, "labels").select("doc_id", F.lit(1).alias("in_labels"))
    return a.join(b, "doc_id", "full_outer").groupBy(F.coalesce("in_documents", F.lit(0)).alias("in_documents"), F.coalesce("in_labels", F.lit(0)).alias("in_labels")).agg(F.count(F.lit(1)).alias("n"))


def _events(spark, d) -> DataFrame:
    return load_table(spark, d, "events").select("event_id", "user_id", "event_type", "value", "props", F.col("ts").cast("timestamp").alias("ts"))


def asof_event(spark, d):
    """For each purchase the last view of the same user not after it: one window, no range join."""
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = _events(spark, d).withColumn("view_ts", F.last(F.when(F.col("event_type") == "view", F.col("ts")), ignorenulls=True).over(w))
    return seen.where("event_type = 'purchase'").select("event_id", F.unix_timestamp("view_ts").alias("view_at"))


def interval_events(spark, d):
    """Errors within an hour after a click of the same user: hour buckets make the range join an equi-join."""
    e = _events(spark, d).withColumn("s", F.unix_timestamp("ts")).withColumn("h", F.floor(F.col("s") / 3600))
    click = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("s").alias("s1"), F.explode(F.array(F.col("h"), F.col("h") + 1)).alias("h"))
    err = e.where("event_type = 'error'").select("user_id", F.col("event_id").alias("error"), F.col("s").alias("s2"), "h")
    return click.join(err, ["user_id", "h"]).where("s2 >= s1 and s2 <= s1 + 3600").select("click", "error")


def distinct_tokens(spark, d):
    words = load_table(spark, d, "documents").select("lang", F.explode(sets.tokens(F.col("text"))).alias("w"))
    return words.groupBy("lang").agg(F.countDistinct("w").alias("n"))


def rollup_documents(spark, d):
    return load_table(spark, d, "documents").rollup("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


def cube_labels(spark, d):
    return load_table(spark, d, "labels").cube("quality", "toxic").agg(F.count(F.lit(1)).alias("n"))


def grouping_sets_orders(spark, d):
    o = load_table(spark, d, "orders")
    return o.groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


def pivot_labels(spark, d):
    docs = load_table(spark, d, "documents").select("doc_id", "lang")
    return docs.join(load_table(spark, d, "labels"), "doc_id").groupBy("quality").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1)))


def rank_documents(spark, d):
    """Rank, dense rank, percent rank and quartile of length by language. Four languages hold all rows, so ranks come from the counts of each length (a window over lengths, not over rows) and rows only meet those of their own length."""
    docs = load_table(spark, d, "documents").select("doc_id", "lang", "n_chars")
    w = Window.partitionBy("lang").orderBy("n_chars")
    lengths = docs.groupBy("lang", "n_chars").agg(F.count(F.lit(1)).alias("c"))
    lengths = lengths.select("lang", "n_chars", (F.sum("c").over(w) - F.col("c")).alias("below"), F.row_number().over(w).alias("dense"), F.sum("c").over(Window.partitionBy("lang")).alias("total"))
    same = Window.partitionBy("lang", "n_chars").orderBy("doc_id")
    rows = docs.withColumn("nth", F.row_number().over(same)).join(lengths, ["lang", "n_chars"]).withColumn("r", F.col("below") + F.col("nth") - 1)
    q, m = F.floor(F.col("total") / 4), F.col("total") % 4
    wide = m * (q + 1)  # rows of the quartiles that hold one more
    quartile = F.when(F.col("r") < wide, F.floor(F.col("r") / (q + 1)) + 1).otherwise(m + F.floor((F.col("r") - wide) / F.greatest(q, F.lit(1))) + 1)
    share = F.when(F.col("total") > 1, F.col("below") / F.nullif(F.col("total") - 1, F.lit(0))).otherwise(0.0)
    return rows.select("doc_id", (F.col("below") + 1).cast("int").alias("rank"), F.col("dense").cast("int"), F.round(share, 6).alias("share"), quartile.cast("int").alias("quartile"))


def event_gaps(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return _events(spark, d).select("event_id", (F.unix_timestamp("ts") - F.unix_timestamp(F.lag("ts").over(w))).alias("gap"), F.lead("event_type").over(w).alias("next_type"))


def _event_items(spark, d) -> DataFrame:
    e = sets.event_tokens(spark, d)
    return e.select("id", "ts", sets.md5_number(F.col("token"), sets.RANGE).alias("t"))


def running_signature(spark, d):
    """Signature of a user's growing set after each event (first hash function), as a running minimum."""
    e = _events(spark, d)
    t = sets.md5_number(F.concat_ws("|", "event_type", F.hour("ts")), sets.RANGE)
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return e.select("event_id", F.min(TwoUniversal(1).column(t, 0)).over(w).alias("z"))


def range_window_events(spark, d):
    """Events of the same user in the 6 hours up to each event."""
    e = _events(spark, d).withColumn("s", F.unix_timestamp("ts"))
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-6 * 3600, 0)
    return e.select("event_id", F.count(F.lit(1)).over(w).alias("n"), F.round(F.sum("value").over(w), 4).alias("total"))


def union_texts(spark, d):
    parts = [load_table(spark, d, t).select(F.lit(t).alias("source"), F.length("text").cast("long").alias("size")) for t in ("documents", "benchmark", "conversations")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("chars"))


def _nation_parts(spark, d, region: str) -> DataFrame:
    s = load_table(spark, d, "supplier").join(load_table(spark, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).where(F.col("n_regionkey") == int(region))
    return load_table(spark, d, "lineitem").join(s.select("s_suppkey"), F.col("l_suppkey") == F.col("s_suppkey")).select("l_partkey")


def intersect_parts(spark, d):
    return _nation_parts(spark, d, "0").intersect(_nation_parts(spark, d, "1"))


def except_parts(spark, d):
    return load_table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey")).exceptAll(_nation_parts(spark, d, "0").distinct())


def event_props(spark, d):
    k = F.get_json_object("props", "$.k")
    return _events(spark, d).groupBy("event_type", k.alias("k")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))


def profile_events(spark, d):
    e = sets.event_tokens(spark, d).groupBy("id").agg(F.collect_set(sets.md5_number(F.col("token"), sets.RANGE)).alias("items"))
    return sets.profile(e)


def _minima():
    f = TwoUniversal(K_EVENTS)
    return [F.min(f.column(F.col("t"), j)).alias(f"z{j}") for j in range(K_EVENTS)]


def tumbling(items: DataFrame) -> DataFrame:
    """Signature of each user's day; the same plan on a stream."""
    return items.groupBy(F.window("ts", "1 day").alias("w"), "id").agg(*_minima()).select(F.unix_timestamp("w.start").alias("start"), "id", *(f"z{j}" for j in range(K_EVENTS)))


def sliding(items: DataFrame) -> DataFrame:
    return items.groupBy(F.window("ts", "7 days", "1 day").alias("w"), "id").agg(*_minima()).select(F.unix_timestamp("w.start").alias("start"), "id", *(f"z{j}" for j in range(K_EVENTS)))


def sessions(items: DataFrame) -> DataFrame:
    return items.groupBy(F.session_window("ts", "30 minutes").alias("w"), "id").agg(*_minima()).select(F.unix_timestamp("w.start").alias("start"), F.unix_timestamp("w.end").alias("stop"), "id", *(f"z{j}" for j in range(K_EVENTS)))


def events_tumbling_signature(spark, d):
    return tumbling(_event_items(spark, d))


def events_sliding_signature(spark, d):
    return sliding(_event_items(spark, d))


def events_session_signature(spark, d):
    return sessions(_event_items(spark, d))


def all_pairs(df: DataFrame, key: str, most_rows: int = 10_000) -> DataFrame:
    """Nested loop over all pairs of a small table: refused beyond most_rows, counted first."""
    n = df.limit(most_rows + 1).count()
    if n > most_rows:
        raise ValueError(f"more than {most_rows} rows: all pairs are for small tables")
    return df.withColumnsRenamed({c: f"{c}1" for c in df.columns}).crossJoin(df.withColumnsRenamed({c: f"{c}2" for c in df.columns})).where(F.col(f"{key}1") < F.col(f"{key}2"))


def nation_pairs(spark, d):
    """All pairs of nations with the resemblance of the market segments' sets of their customers with a positive balance."""
    c = load_table(spark, d, "customer").where("c_acctbal > 0")
    sets_ = c.groupBy(F.col("c_nationkey").alias("id")).agg(F.collect_set(F.concat_ws("|", "c_mktsegment", F.floor(F.col("c_acctbal") / 1000).cast("string"))).alias("items"))
    from ..functions.similarity import resemblance

    return all_pairs(sets_, "id").select("id1", "id2", F.round(resemblance(F.col("items1"), F.col("items2")), 6).alias("r"))


def bit_aggregates(spark, d):
    """Bits of a supplier's part numbers: any, all, parity."""
    lines = load_table(spark, d, "lineitem")
    return lines.groupBy("l_suppkey").agg(F.bit_or("l_partkey").alias("any_bit"), F.bit_and("l_partkey").alias("all_bits"), F.bit_xor("l_partkey").alias("parity"))


def sketch_distinct(spark, d):
    """Distinct parts of a return flag: exact, and whether the library's three sketches come within a tenth."""
    lines = load_table(spark, d, "lineitem")
    near = lambda c: F.abs(c - F.col("n")) <= F.col("n") / 10
    counted = lines.groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("n"), F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", F.lit(14))).alias("h"), F.theta_sketch_estimate(F.theta_sketch_agg("l_partkey")).alias("t"))
    return counted.select("l_returnflag", "n", near(F.col("a")).alias("approximate_near"), near(F.col("h")).alias("hll_near"), near(F.col("t")).alias("theta_near"))


def page_of_orders(spark, d, offset: int = 100, limit: int = 50):
    """One page of the orders in the order of their keys."""
    return load_table(spark, d, "orders").select("o_orderkey", "o_custkey").orderBy("o_orderkey").offset(offset).limit(limit)


def event_type_maps(spark, d):
    """Of each user's map from event type to count: its size, clicks, and the types met three times or more."""
    n = load_table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    kinds = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    often = F.array_sort(F.map_keys(F.map_filter("m", lambda k, v: v >= 3)))
    doubled = F.aggregate(F.map_values(F.transform_values("m", lambda k, v: v * 2)), F.lit(0).cast("long"), lambda t, v: t + v)
    return kinds.select("user_id", F.size("m").alias("kinds"), F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0).cast("long")).alias("clicks"), F.array_join(often, ",").alias("often"), doubled.alias("twice_all"))


def label_moments(spark, d):
    """Means, deviations and the correlation of the two labels, by language."""
    rows = load_table(spark, d, "documents").select("doc_id", "lang", "n_chars").join(load_table(spark, d, "labels"), "doc_id")
    six = lambda c, name: F.round(c, 6).alias(name)
    return rows.groupBy("lang").agg(six(F.avg("quality"), "mean"), six(F.var_samp("quality"), "variance"), six(F.stddev_samp("toxic"), "deviation"), six(F.covar_samp("quality", "toxic") / F.nullif(F.stddev_samp("quality") * F.stddev_samp("toxic"), F.lit(0.0)), "correlation"))


def binarised_quantities(spark, d, threshold: float = 25.0):
    """Customer and part with a summed quantity over the threshold, as 0/1 items."""
    return sets.binarise(sets.basket_lines(spark, d), "v", threshold).groupBy("id").agg(F.count(F.lit(1)).alias("items"))


NAMES = """nation_pairs bit_aggregates sketch_distinct page_of_orders event_type_maps label_moments binarised_quantities filter_documents filter_pages customer_part_sets labelled_documents semi_labelled anti_labelled full_outer_labels
asof_event interval_events distinct_tokens rollup_documents cube_labels grouping_sets_orders pivot_labels rank_documents
event_gaps running_signature range_window_events union_texts intersect_parts except_parts event_props profile_events
events_tumbling_signature events_sliding_signature events_session_signature""".split()
QUERIES = {name: globals()[name] for name in NAMES}
