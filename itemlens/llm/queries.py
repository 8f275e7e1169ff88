"""The corpus operators as queries over the given tables, and the SQL that checks those which SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import chat, exact_dedup, fingerprints, html_text, language_id, mixing, packing, pii, quality, similarity_join
from .common import table


def op1_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similarity_join.similarity_classes(table(spark, sf_dir, "documents"))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identified(table(spark, sf_dir, "documents"))


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(table(spark, sf_dir, "documents"))


def op4_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.edited_fingerprints(table(spark, sf_dir, "documents"))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.scored(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(extra)
    return chat.read_back(chat.windows(turns))


def op7_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extracted(table(spark, sf_dir, "pages"))


def op8_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_duplicates(table(spark, sf_dir, "documents"))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixed(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(pii.detected(table(spark, sf_dir, "documents")))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (op1_ngram_join, op2_language_id, op3_packing, op4_fingerprints, op5_quality, op6_chat, op7_html, op8_exact_dedup, op9_mixing, op10_pii, pipeline)
    return {f.__name__: f for f in own}


#: The windows' costs, ranges and marks are those of chat.py, written out again in SQL.
CHAT_SQL = """
with recursive turns as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -7, 0, 'user', '</s>[INST] ok [/INST]'
  union all select -7, 1, 'assistant', '</s>[INST] ok [/INST]'
), written as (
  select *, concat('<', replace(replace(replace(role, '~', '~0'), '<', '~1'), '>', '~2'), '>', replace(replace(text, '~', '~0'), '<', '~1'), '<end>') as line from turns
), costed as (
  select *, cast(ceil(strlen(line) / 4.0) as bigint) as cost, length(line) as chars, row_number() over (partition by conv_id order by turn, role, text) as number from written
), placed as (
  select *, coalesce(sum(cost) over (partition by conv_id order by number rows between unbounded preceding and 1 preceding), 0)::bigint as begins,
         max(case when number = 1 and role = 'system' then cost else 0 end) over (partition by conv_id) as sys
  from costed
), recent as (
  select *, greatest(min(number) over near, case when sys > 0 then 2 else 1 end) as back, begins - greatest(min(begins) over near, sys) as past
  from placed window near as (partition by conv_id order by begins range between 256 preceding and current row)
), spans as materialized (
  select *, begins + cost as ends, number > 1 and sys + past + cost <= 1024 as fits from recent
), limits as materialized (
  select conv_id, number, ends, chars, sys, case when fits then back else number end as start,
         begins + greatest(cost, case when number = 1 then 1024 else 1024 - sys - case when fits then past else 0 end end) as most from spans
), w as (
  select conv_id, number as first, start, most from limits where number = 1
  union all
  select n.conv_id, n.number, n.start, n.most from w, lateral (select * from limits l where l.conv_id = w.conv_id and l.ends > w.most order by l.number limit 1) n
), repeats as (
  select w.conv_id, sum(l.chars) as chars from w join limits l on l.conv_id = w.conv_id and l.number < w.first and (l.number >= w.start or l.number = 1 and l.sys > 0) group by w.conv_id
), digests as (
  select conv_id, count(*) as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by number)) as turns_sha256,
         cast(coalesce(sum(case when role = 'assistant' then length(text) end), 0) as bigint) as loss_chars,
         sha256(coalesce(string_agg(case when role = 'assistant' then text end, '' order by number), '')) as loss_sha256, sum(chars) as chars
  from spans group by conv_id
)
select d.conv_id, d.n_turns, d.turns_sha256, d.loss_chars, d.loss_sha256, cast(d.chars + coalesce(r.chars, 0) as bigint) as formatted_chars
from digests d left join repeats r on r.conv_id = d.conv_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op8_exact_dedup": exact_dedup.ORACLE_SQL, "op6_chat": CHAT_SQL}
