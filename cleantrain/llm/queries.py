"""The operators' registered queries, each over its whole table, and their SQL where SQL can say the same."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, html_main_text, language_id, license_scan, line_windows, mtree, probminhash, sentencepiece_lattice, token_rollup, url_filter
from .common import scratch_dir


def _read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licences(_read(spark, sf_dir, "documents"))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify_documents(_read(spark, sf_dir, "documents"))


def language_id_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages by all four kinds of evidence, with the text model trained on the labelled documents."""
    model = language_id.train(_read(spark, sf_dir, "documents").select("text", "lang"))
    return language_id.identify(language_id.page_evidence(_read(spark, sf_dir, "pages")), model).withColumn("page_id", F.col("page_id").cast("long"))


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(_read(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


def op4_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination_report(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "benchmark"))


def op5_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    coded = sentencepiece_lattice.encode(_read(spark, sf_dir, "documents"), decoded=True)
    return coded.select("doc_id", "n_tokens", "ids", F.sha2("decoded", 256).alias("decoded_sha256"))


def op6_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_main_text.extract_main_text(_read(spark, sf_dir, "pages"))


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return probminhash.near_duplicates(_read(spark, sf_dir, "documents"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_windows.dedup_report(_read(spark, sf_dir, "documents"))


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    rollup = token_rollup.TokenRollup(spark, scratch_dir(spark))
    rollup.commit("load", upserts=_read(spark, sf_dir, "documents"))
    rollup.commit("load", upserts=_read(spark, sf_dir, "documents"))  # the same batch again changes nothing
    return rollup.totals()


def token_counts_revised(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Word totals after three batches: all documents, those of low quality with their text twice, and toxic ones withdrawn."""
    docs, labels = _read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels")
    low, toxic = labels.where("quality = 0"), labels.where("toxic = 1")
    rollup = token_rollup.TokenRollup(spark, scratch_dir(spark))
    rollup.commit("load", upserts=docs)
    for _ in range(2):  # a batch that comes again changes nothing
        rollup.commit("revise", upserts=docs.join(low, "doc_id", "left_semi").withColumn("text", F.concat("text", F.lit(" "), "text")))
    rollup.commit("withdraw", deletes=toxic.select("doc_id"))
    return rollup.totals().where("tokenizer = 'words@1'").drop("tokenizer")


def op10_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mtree.top_k(_read(spark, sf_dir, "embeddings"))


def queries() -> dict:
    named = (op1_licence_scan, op2_language_id, language_id_pages, op3_url_filter, op4_decontaminate, op5_sentencepiece, op6_main_text, op7_near_duplicates, op8_line_dedup, op9_token_counts, token_counts_revised, op10_top_k)
    return {f.__name__: f for f in named}


CONTAMINATION_SQL = r"""
with doc as (select row_number() over () as r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from documents),
item as (select distinct item_id::varchar as item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from benchmark where item_id is not null),
sized as (select item_id, w, least(10, len(w)) as k from item where len(w) > 0),
placed as (select item_id, w, k, unnest(range(0, len(w) - k + 1)) as s from sized),
windows as (select distinct item_id, k, array_to_string(w[s + 1 : s + k], ' ') as g from placed),
size as (select distinct k from windows),
spots as (select r, w, k, unnest(range(0, len(w) - k + 1)) as s from doc, size where len(w) >= k),
grams as (select r, k, s, array_to_string(w[s + 1 : s + k], ' ') as g from spots),
hits as (select r, s, grams.k, item_id from grams join windows on grams.k = windows.k and grams.g = windows.g),
words as (select r, count(distinct p) as n_hit from (select r, unnest(range(s, s + k)) as p from hits) group by r),
names as (select r, count(*) as n_items, string_agg(item_id, ',' order by item_id) as names from (select distinct r, item_id from hits) group by r)
select doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items, sha256(coalesce(names, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from doc left join words on doc.r = words.r left join names on doc.r = names.r"""


REVISED_SQL = r"""
with d as (select source, lang, case when doc_id in (select doc_id from labels where quality = 0) then text || ' ' || text else text end as text
  from documents where doc_id is null or doc_id not in (select doc_id from labels where toxic = 1 and doc_id is not null))
select source, lang, count(*)::bigint as n_docs, sum(len(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')))::bigint as n_tokens,
  sum(strlen(coalesce(text, '')))::bigint as n_bytes from d group by source, lang"""


def oracle_sql() -> dict:
    return {"token_counts_revised": REVISED_SQL, "op3_url_filter": url_filter.judge_sql(), "op4_decontaminate": CONTAMINATION_SQL, "op8_line_dedup": line_windows.DEDUP_SQL, "op10_top_k": mtree.TOP_K_SQL}
