"""Queries and oracle SQL of this folder, for ``__spark_entry__``."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def read(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import score, train

    docs = read(spark, sf_dir, "documents", "doc_id", "text")
    return score(docs, train(docs, read(spark, sf_dir, "labels", "doc_id", "toxic")))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality import measures, score_measured, train_on

    docs = measures(read(spark, sf_dir, "documents", "doc_id", "text"))
    return score_measured(docs, train_on(docs, read(spark, sf_dir, "labels", "doc_id", "quality")))


def op2_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pii import find

    return find(read(spark, sf_dir, "documents", "doc_id", "text"))


def op3_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_files import round_trip

    return round_trip(read(spark, sf_dir, "documents", "doc_id", "text"))


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack_documents

    return pack_documents(read(spark, sf_dir, "documents", "doc_id", "text"))


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .exact_dedup import classes

    return classes(read(spark, sf_dir, "documents", "doc_id", "text"))


OP5_SQL = """
with d as (select doc_id, sha256(coalesce(text, '')) as text_sha256 from documents),
g as (select text_sha256, max(doc_id) as keep_id, count(*) as group_size from d group by 1)
select doc_id, keep_id, group_size, doc_id = keep_id as kept, text_sha256 from d join g using (text_sha256)
"""


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontaminate import matches

    return matches(read(spark, sf_dir, "documents", "doc_id", "text"), read(spark, sf_dir, "benchmark", "item_id", "text"))


OP7_SQL = """
with words as (
  select 'd' as kind, doc_id as id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') as w from documents
  union all
  select 'i', item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') from benchmark
), sh as (
  select distinct kind, id, s from (
    select kind, id, unnest(case when len(w) = 0 then []::varchar[] when len(w) < 5 then ['<' || array_to_string(w, ' ')]
      else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) end) as s from words)
), items as (select id as item_id, s, count(*) over (partition by id) as n_item from sh where kind = 'i')
select d.id as doc_id, item_id, n_item, count(*) as n_shared, count(*) / n_item as containment
from sh d join items using (s) where d.kind = 'd'
group by 1, 2, 3 having count(*) * 1000 >= n_item * 800
"""


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .jaccard_join import near_copies

    return near_copies(read(spark, sf_dir, "documents", "doc_id", "text"))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .warc import round_trip

    return round_trip(read(spark, sf_dir, "pages", "page_id", "url", "html"))


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .substring_dedup import digests

    return digests(read(spark, sf_dir, "documents", "doc_id", "text"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if name.startswith("op") and name[2].isdigit() and callable(f)}


def oracle_sql() -> dict[str, str]:
    sql = {name[:-4].lower(): text for name, text in globals().items() if name.startswith("OP") and name.endswith("_SQL")}
    return {name: sql[name.split("_")[0]] for name in queries() if name.split("_")[0] in sql}
