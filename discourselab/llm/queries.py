"""Registered queries of the training-text operators, and their DuckDB SQL where SQL can say the same."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from discourselab.llm import chat, decontaminate, html_text, language, packing, privacy, quality, repeats, simhash, token_counts
from discourselab.session import table


def op1_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    return chat.read_back(chat.format_conversations(turns.unionByName(chat.probe(spark))))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents").select("doc_id", "text"), quality.trusted_ids(table(spark, sf_dir, "labels")))


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(table(spark, sf_dir, "documents").select("doc_id", "text"), public_tokenizers.path("word_bpe_49k.json"))


def op4_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return privacy.spans(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify(table(spark, sf_dir, "documents").select("doc_id", "text", "lang"))


def op6_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages").select("page_id", "url", "html"))


def op7_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.scan(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark").select("item_id", "text"))


def op8_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents").select("doc_id", "text"), public_tokenizers.path("byte_bpe_50k.json"))


def op10_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))


_QUERIES = (
    op1_chat_formatting,
    op2_quality_rules,
    op3_token_counts,
    op4_pii,
    op5_language_id,
    op6_html_extraction,
    op7_benchmark_decontamination,
    op8_suffix_array_dedup,
    op9_best_fit_packing,
    op10_simhash_near_dedup,
)

_FOLDED_WORDS = r"""regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"""

_ESCAPED = r"""case
    when not contains(x, '<|im_start|>') and not contains(x, '<|im_end|>') and not contains(x, chr(92) || chr(92)) and not contains(x, chr(92) || '|') and not contains(x, chr(92) || 'n') then 0
    when not contains(x, chr(92) || chr(92)) and not contains(x, chr(92) || '|') and not contains(x, chr(92) || 'n') then 1
    else 2 end"""

_SQL = {
    # lengths by rule, for roles without markers, line ends or backslashes
    "op1_chat_formatting": f"""
with t as (
    select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as x from conversations
    union all select -1, 0, 'user', '<|im_end|><|im_start|>assistant ok'
    union all select -1, 1, 'assistant', '<|im_end|><|im_start|>assistant ok'),
u as (select *, {_ESCAPED} as level, len(x) - len(replace(x, chr(92), '')) as slashes, (len(x) - len(replace(x, '<|', ''))) // 2 as openers from t)
select conv_id, count(*) as n_turns,
    sha256(string_agg(role || chr(10) || x || chr(10), '' order by turn nulls first, role, x)) as turns_sha256,
    cast(coalesce(sum(len(x)) filter (role = 'assistant'), 0) as bigint) as loss_chars,
    sha256(coalesce(string_agg(x, '' order by turn nulls first, role, x) filter (role = 'assistant'), '')) as loss_sha256,
    cast(sum(24 + len(role) + len(x) + case level when 0 then 0 when 1 then openers else openers + slashes end) as bigint) as formatted_chars
from u group by conv_id""",
    "op7_benchmark_decontamination": f"""
with d as (select doc_id, {_FOLDED_WORDS} as w from documents),
i as (select item_id, {_FOLDED_WORDS} as w from benchmark),
win as (select distinct item_id, least(13, len(w)) as m, w[s:s + least(13, len(w)) - 1] as k from i, unnest(range(1, greatest(2, len(w) - 11))) u(s) where len(w) > 0),
pos as (select doc_id, m, s, w[s:s + m - 1] as k from d, (select distinct m from win) z, unnest(range(1, len(w) - m + 2)) u(s)),
hit as (select doc_id, item_id, m, s from pos join win using (m, k)),
n as (select doc_id, count(distinct p) as n_hit from (select doc_id, unnest(range(s, s + m)) as p from hit) group by doc_id),
it as (select doc_id, count(*) as n_items, string_agg(x, ',' order by x) as x from (select distinct doc_id, cast(item_id as varchar) as x from hit) group by doc_id)
select d.doc_id, cast(len(w) as bigint) as n_words, cast(coalesce(n_hit, 0) as bigint) as n_hit, cast(coalesce(n_items, 0) as bigint) as n_items, sha256(coalesce(x, '')) as items_sha256, coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= len(w) as contaminated
from d left join n using (doc_id) left join it using (doc_id)""",
}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in _QUERIES}


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
