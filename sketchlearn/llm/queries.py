"""The queries opN_<name> and their SQL for DuckDB. Each query applies its operator to the whole table and derives the stated columns from the operator's result."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, jaccard, license, lm, sentencepiece, substring, topk, toxicity, urlfilter, warc


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.scores(table(spark, sf_dir, "documents"))


def op2_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentencepiece.encode(table(spark, sf_dir, "documents"), sentencepiece.default_model(spark))


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_round_trip(spark, table(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge(table(spark, sf_dir, "pages"), table(spark, sf_dir, "labels"))


def op5_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0)


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.removed_digest(table(spark, sf_dir, "documents"))


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = license.scan(table(spark, sf_dir, "documents"))
    at = F.transform("places", lambda p: p.word)
    return found.select("doc_id", "n_words", F.size("places").cast("long").alias("n_base"), F.array_min(at).alias("first_word"), F.array_max(at).alias("last_word"), F.array_join("base_labels", ",").alias("base_labels"), F.array_join("labels", ",").alias("labels"), "score")


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op9_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.classes(table(spark, sf_dir, "documents"), n=3, num=90, den=100)


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontam.decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    names = F.array_sort(F.transform("items", lambda i: i.cast("string")))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", names), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


QUERIES = {
    "op1_lm_scoring": op1_lm_scoring,
    "op2_sentencepiece": op2_sentencepiece,
    "op3_warc": op3_warc,
    "op4_url_filter": op4_url_filter,
    "op5_top_k": op5_top_k,
    "op6_substring_dedup": op6_substring_dedup,
    "op7_license_scan": op7_license_scan,
    "op8_toxicity": op8_toxicity,
    "op9_ngram_jaccard": op9_ngram_jaccard,
    "op10_decontamination": op10_decontamination,
}

_LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_ALNUM = "list_filter(string_split_regex(" + _LOWER + r", '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '')"
_BLANK = r"list_filter(string_split_regex({}, '[\x20\x09-\x0D]+'), lambda x: x <> '')"

ORACLES = {
    "op3_warc": """
with p as (select page_id, coalesce(html, '') as h from pages),
q as (select page_id, octet_length(encode(h)) as payload_bytes, sha1(h) as payload_digest from p),
m as (select payload_digest, max(page_id) as head from q where payload_bytes >= 1000 group by payload_digest)
select q.page_id, cast(payload_bytes as bigint) as payload_bytes, q.payload_digest,
       case when payload_bytes >= 1000 and head is not null and page_id is distinct from head then 'revisit' else 'response' end as record_type,
       case when payload_bytes >= 1000 and page_id is distinct from head then head end as refers_to
from q left join m using (payload_digest)""",
    "op5_top_k": """
with v as (select vec_id, list_transform(embedding, lambda x: cast(floor(1024 * cast(x as double)) as bigint)) as e
           from embeddings where embedding is not null and len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) = 0),
p as (select q.vec_id as query_id, c.vec_id as vec_id, cast(list_sum(list_transform(range(1, len(q.e) + 1), lambda i: q.e[i] * c.e[i])) as bigint) as score
      from v q join v c on q.vec_id <> c.vec_id where q.vec_id % 100 = 0),
r as (select *, cast(row_number() over (partition by query_id order by score desc, vec_id) as integer) as rank from p)
select query_id, rank, vec_id, score from r where rank <= 10""",
    "op6_substring_dedup": f"""
with d as (select row_number() over () as r, doc_id, coalesce({_BLANK.format('text')}, []) as w from documents),
s as (select r, w, unnest(range(len(w) - 34)) as s from d where len(w) >= 35),
h as (select r, s, md5(array_to_string(list_slice(w, s + 1, s + 35), ' ')) as h from s),
twice as (select h from h group by h having count(*) > 1),
gone as (select r, list(distinct pos) as pos from (select r, unnest(range(s, s + 35)) as pos from h semi join twice using (h)) group by r)
select doc_id, len(w)::bigint as n_words, coalesce(len(pos), 0)::bigint as n_removed,
       sha256(array_to_string(case when pos is null then w else list_filter(w, lambda x, i: not list_contains(pos, i - 1)) end, ' ')) as kept_sha256
from d left join gone using (r)""",
    "op9_ngram_jaccard": f"""
with recursive d as (select row_number() over () as r, doc_id, coalesce({_BLANK.format(_LOWER.format('text'))}, []) as w from documents),
sh as (select distinct r, array_to_string(list_slice(w, s + 1, s + 3), ' ') as g from (select r, w, unnest(range(greatest(1, len(w) - 2))) as s from d where len(w) > 0)),
n as (select r, count(*) as n from sh group by r),
common as (select a.r as a, b.r as b, count(*) as k from sh a join sh b on a.g = b.g and a.r <> b.r group by a.r, b.r),
link as (select a, b from common join n x on x.r = a join n y on y.r = b where 100 * k >= 90 * (x.n + y.n - k)),
reach as (select r as a, r as b from d union select reach.a, link.b from reach join link on reach.b = link.a)
select d.doc_id, coalesce(n.n, 0)::bigint as n_shingles, c.component_id from d left join n using (r)
join (select a, min(doc_id) as component_id from reach join d on d.r = reach.b group by a) c on c.a = d.r""",
    "op10_decontamination": f"""
with d as (select doc_id, coalesce({_ALNUM.format('text')}, []) as w from documents),
b as (select item_id, {_ALNUM.format('text')} as w from benchmark where item_id is not null and text is not null),
bw as (select item_id, unnest(range(greatest(1, len(w) - 9))) as s, w from b where len(w) > 0),
pat as (select distinct item_id, array_to_string(list_slice(w, s + 1, s + 10), ' ') as win, least(len(w), 10) as n from bw),
sizes as (select distinct n from pat),
dw as (select doc_id, n, unnest(range(len(w) - n + 1)) as s, w from d, sizes where len(w) >= n),
hit as (select doc_id, dw.n, dw.s, item_id from dw join pat on dw.n = pat.n and array_to_string(list_slice(w, s + 1, s + dw.n), ' ') = win),
cov as (select doc_id, count(distinct pos) as n_hit from (select doc_id, unnest(range(s, s + n)) as pos from hit) group by doc_id),
its as (select doc_id, count(distinct item_id) as n_items, string_agg(distinct cast(item_id as varchar), ',' order by cast(item_id as varchar)) as names from hit group by doc_id)
select d.doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items,
       sha256(coalesce(names, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from d left join cov using (doc_id) left join its using (doc_id)""",
}
