"""The queries op1_ to op10_ over the given tables, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from utilmine.llm import chat, decontamination, language_id, mixing, near_dedup, pii, quality_classifier, quality_rules, sharding, substring_dedup
from utilmine.llm.shared import documents


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.dedup_passages(documents(spark, sf_dir))


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = sharding.shards(documents(spark, sf_dir).select("doc_id", "text"), 40)
    text = F.coalesce(F.col("text"), F.lit(""))
    grown = sharding.shard_of(F.col("doc_id"), 41, seed=7)
    return rows.select("doc_id", sharding.record_size(F.col("text")).alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.lit("key").alias("law"), "shard", "slot", grown.alias("grown_shard"))


def op3_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = "</s>[INST] ok [/INST]"
    rows = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    more = spark.createDataFrame([(-1, 0, "user", said), (-1, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    back = chat.read_back(chat.format_conversations(rows.union(more)))
    whole = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    sha = lambda c: F.sha2(c.cast("binary"), 256)
    return back.select("conv_id", F.size("turns").cast("long").alias("n_turns"), sha(whole).alias("turns_sha256"), F.length("loss").cast("long").alias("loss_chars"), sha(F.col("loss")).alias("loss_sha256"), "formatted_chars")


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_classifier.classify(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = pii.find(documents(spark, sf_dir))
    return rows.select("doc_id", *(f"n_{k}" for k in pii.KINDS), F.sha2(F.col("base_spans").cast("binary"), 256).alias("base_sha256"), "spans")


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.contaminated(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.score(documents(spark, sf_dir)).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(documents(spark, sf_dir))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mixing.mix(documents(spark, sf_dir))
    return rows.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def op10_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(documents(spark, sf_dir))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_substring_dedup": op1_substring_dedup,
    "op2_sharding": op2_sharding,
    "op3_chat_formatting": op3_chat_formatting,
    "op4_quality_classifier": op4_quality_classifier,
    "op5_pii": op5_pii,
    "op6_decontamination": op6_decontamination,
    "op7_quality_rules": op7_quality_rules,
    "op8_language_id": op8_language_id,
    "op9_mixing": op9_mixing,
    "op10_near_dedup": op10_near_dedup,
}

#: A control string, plain or with backslashes behind its first character.
_UNSAFE = r"(<\\*\|turn\|>|<\\*\|text\|>|<\\*\|end\|>|<\\*s>|<\\*/s>|\[\\*INST\]|\[\\*/INST\]|<\\*<SYS>>|<\\*</SYS>>|<\\*\|endoftext\|>|<\\*\|im_start\|>|<\\*\|im_end\|>)"
_ESCAPES = f"len(regexp_extract_all(%s, '{_UNSAFE}'))"

_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_STOP = ", ".join(f"'{w}'" for w in dict.fromkeys(quality_rules.STOP_WORDS))
_LINES = r"list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]'))"

ORACLES: dict[str, str] = {
    "op1_substring_dedup": f"""
with d as materialized (select doc_id, {_WORDS} as ws from documents),
w as materialized (select doc_id, len(ws) as n, p, ws[p] as word, case when p + 49 <= len(ws) then md5(array_to_string(ws[p:p + 49], ' ')) end as k from d, unnest(range(1, len(ws) + 1)) r(p)),
first as (select k, min(doc_id) as low from w where k is not null group by k),
hit as (select w.*, max(case when low < doc_id then 1 else 0 end) over (partition by doc_id order by p rows between 49 preceding and current row) as gone from w left join first using (k)),
kept as (select doc_id, sum(gone)::bigint as n_removed, string_agg(word, ' ' order by p) filter (gone = 0) as words from hit group by doc_id)
select doc_id, len(ws)::bigint as n_words, coalesce(n_removed, 0)::bigint as n_removed, sha256(coalesce(words, '')) as kept_sha256 from d left join kept using (doc_id)""",
    "op7_quality_rules": f"""
with d as materialized (select doc_id, coalesce(text, '') as t, {_WORDS} as ws, {_LINES} as lines from documents),
w as (select doc_id, p, case when p + 4 <= len(ws) then array_to_string(ws[p:p + 4], ' ') end as k from d, unnest(range(1, len(ws) + 1)) r(p)),
c as (select doc_id, p, case when k is not null and count(*) over (partition by doc_id, k) > 1 then 1 else 0 end as twice from w),
r as (select doc_id, sum(m)::bigint as n_repeat_words from (select doc_id, max(twice) over (partition by doc_id order by p rows between 4 preceding and current row) as m from c) group by doc_id),
m as (select doc_id, len(ws)::bigint as n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::bigint as word_chars,
  (length(t) - length(translate(t, '{quality_rules.SYMBOLS}', '')))::bigint as n_symbols, (len(lines) - len(list_distinct(lines)))::bigint as n_dup_lines, len(lines) as n_lines, coalesce(n_repeat_words, 0)::bigint as n_repeat_words,
  len(list_filter(ws, lambda x: rtrim(lower(x), '.,;:!?') in ({_STOP}))) as n_stop, length(t) - length(translate(t, 'ABCDEFGHIJKLMNOPQRSTUVWXYZÄÖÜÀÂÇÉÈÊËÎÏÔÛÙÑÁÍÓÚ', '')) as n_upper from d left join r using (doc_id)),
v as (select *, n_words < 10 or 100 * n_repeat_words > 20 * n_words as base_failed from m)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, not base_failed and word_chars >= 2 * n_words and word_chars <= 14 * n_words and 100 * n_symbols <= 30 * n_words
  and 100 * n_dup_lines <= 30 * n_lines and 50 * n_stop >= n_words and 100 * n_upper <= 60 * word_chars as kept from v""",
    "op3_chat_formatting": f"""
with r as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -1, 0, 'user', '</s>[INST] ok [/INST]' union all select -1, 1, 'assistant', '</s>[INST] ok [/INST]')
select conv_id, count(*) as n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
  coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (role = 'assistant'), '')) as loss_sha256,
  sum(length(role) + length(text) + {_ESCAPES % 'role'} + {_ESCAPES % 'text'} + length('<|turn|><|text|><|end|>') + 1)::bigint as formatted_chars
from r group by conv_id""",
}
