"""The registered query of each text operator, over whole tables, and its SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, decontaminate, exact, jaccard, linechunks, perspectives, substrings, surrogates, toxicity, urlrules


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vocabulary_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


# The listed url rules of production, as (verdict, host, path).
URL_RULES = [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/")]


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages whose label (of the document with the page's id) says low quality or toxic are the bad examples.

    Rules need 20 bad urls, a lift of 1.2 and to hold on the half of the urls they were not mined from.
    """
    pages = table(spark, sf_dir, "pages")
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("page_id"), ((F.col("quality") == 0) | (F.col("toxic") == 1)).alias("bad"))
    rules = urlrules.mine_rules(pages.select("page_id", "url").join(labels, "page_id"), min_support=0.002, min_confidence=0.6)
    judged = urlrules.judge(pages.select("page_id", "url"), URL_RULES, rules)
    return judged.select("page_id", "host", "path", "rule", "verdict", "learnt_rule")


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return toxicity.score(docs, table(spark, sf_dir, "labels")).select("doc_id", "held_out", "score", "predicted")


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return linechunks.drop_repeated_chunks(docs).select("doc_id", "n_lines", "n_removed", "text")


def op8_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return surrogates.checked(surrogates.replace_entities(docs, key="manifold")).select("doc_id", "text", F.size("pii").cast("long").alias("n_entities"))


def op9_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    return perspectives.flat(perspectives.rotate(table(spark, sf_dir, "conversations")))


def op4_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(table(spark, sf_dir, "documents"), vocabulary_path())


def op5_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.near_groups(table(spark, sf_dir, "documents"), n=4, threshold=0.85)


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.exact_groups(table(spark, sf_dir, "documents"), keep="max")


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.digest(decontaminate.benchmark_hits(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), span=10))


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substrings.digest(substrings.repeated_spans(table(spark, sf_dir, "documents"), span=50))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_url_filter": op1_url_filter,
    "op2_toxicity": op2_toxicity,
    "op3_line_dedup": op3_line_dedup,
    "op4_bpe": op4_bpe,
    "op5_jaccard_join": op5_jaccard_join,
    "op6_exact_dedup": op6_exact_dedup,
    "op7_decontaminate": op7_decontaminate,
    "op8_pii": op8_pii,
    "op9_chat": op9_chat,
    "op10_substring_dedup": op10_substring_dedup,
}

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

OP7_SQL = rf"""
with d as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as ws from documents),
b as (select item_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as ws from benchmark),
bw as (select distinct item_id, least(10, len(ws)) as m, array_to_string(ws[i : i + least(10, len(ws)) - 1], ' ') as k
       from (select item_id, ws, unnest(range(1, len(ws) - least(10, len(ws)) + 2)) as i from b where len(ws) > 0)),
ms as (select distinct m from bw),
dw as (select doc_id, m, i, array_to_string(ws[i : i + m - 1], ' ') as k
       from (select doc_id, ws, m, unnest(range(1, len(ws) - m + 2)) as i from d, ms where len(ws) >= m)),
hit as (select distinct doc_id, dw.m, i, item_id from dw join bw on dw.m = bw.m and dw.k = bw.k),
pos as (select doc_id, count(distinct j) as n from (select doc_id, unnest(range(i, i + m)) as j from hit) group by doc_id),
it as (select doc_id, count(*) as n, string_agg(s, ',' order by s) as l from (select distinct doc_id, cast(item_id as varchar) as s from hit where item_id is not null) group by doc_id)
select d.doc_id, cast(len(ws) as bigint) as n_words, cast(coalesce(pos.n, 0) as bigint) as n_hit, cast(coalesce(it.n, 0) as bigint) as n_items,
       sha256(coalesce(it.l, '')) as items_sha256, coalesce(pos.n, 0) > 0 as contaminated
from d left join pos on d.doc_id = pos.doc_id left join it on d.doc_id = it.doc_id
"""

OP10_SQL = r"""
with d as (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as ws from documents),
w as (select doc_id, i, md5(array_to_string(ws[i : i + 49], ' ')) as k from (select doc_id, ws, unnest(range(1, len(ws) - 48)) as i from d where len(ws) >= 50)),
m as (select doc_id, i, min(doc_id) over (partition by k) as least from w),
gone as (select distinct doc_id, unnest(range(i, i + 50)) as j from m where least < doc_id),
t as (select doc_id, unnest(ws) as x, unnest(range(1, len(ws) + 1)) as j from d where len(ws) > 0),
kept as (select t.doc_id, count(*) as n, string_agg(x, ' ' order by t.j) as s from t anti join gone on t.doc_id = gone.doc_id and t.j = gone.j group by t.doc_id)
select d.doc_id, cast(len(ws) as bigint) as n_words, cast(len(ws) - coalesce(n, 0) as bigint) as n_removed, sha256(coalesce(s, '')) as kept_sha256
from d left join kept on d.doc_id = kept.doc_id
"""

OP5_SQL = rf"""
with recursive d as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\x20\x09-\x0D]+') as ws from documents),
s as (select distinct doc_id, md5(array_to_string(ws[i : i + least(4, len(ws)) - 1], ' ')) as k
      from (select doc_id, ws, unnest(range(1, len(ws) - least(4, len(ws)) + 2)) as i from d where len(ws) > 0)),
n as (select doc_id, count(*) as n from s group by doc_id),
l as (select a, b from (select x.doc_id as a, y.doc_id as b, count(*) as o from s x join s y on x.k = y.k and x.doc_id <> y.doc_id group by x.doc_id, y.doc_id)
      join n p on p.doc_id = a join n q on q.doc_id = b where 100 * o >= 85 * (p.n + q.n - o)),
r as (select a as doc_id, b as other from l union select r.doc_id, l.b from r join l on r.other = l.a)
select d.doc_id, cast(coalesce(n.n, 0) as bigint) as n_shingles, least(d.doc_id, coalesce(c.m, d.doc_id)) as component_id
from d left join n on d.doc_id = n.doc_id left join (select doc_id, min(other) as m from r group by doc_id) c on d.doc_id = c.doc_id
"""

ORACLE_SQL: dict[str, str] = {
    "op3_line_dedup": linechunks.ORACLE,
    "op5_jaccard_join": OP5_SQL,
    "op6_exact_dedup": exact.ORACLE,
    "op7_decontaminate": OP7_SQL,
    "op9_chat": perspectives.ORACLE,
    "op10_substring_dedup": OP10_SQL,
}
