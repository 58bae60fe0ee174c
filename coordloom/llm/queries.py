"""The queries ``opN_<name>`` over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coordloom.llm import chat_format, decontaminate, html_labeller, jaccard_join, license_scan, line_dedup, mixing, quality_rules, recompression, warc
from coordloom.llm.common import table

Query = Callable[[SparkSession, str], DataFrame]


def op1_warc_derivatives(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return warc.derivatives(warc.responses_from_pages(pages), "page_id").withColumnRenamed("source_key", "page_id")


def op2_license_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "n_detections")


def op3_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    fixed = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-7, 0, "user", fixed), (-7, 1, "assistant", fixed)], chat_format.TURNS)
    turns = chat_format.turns_from_table(table(spark, sf_dir, "conversations")).unionByName(extra)
    return chat_format.digests(chat_format.format_turns(turns))


def op4_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.Mix(table(spark, sf_dir, "documents")).taken()


def op5_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.jaccard_components(table(spark, sf_dir, "documents"))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality_rules.apply_policy(quality_rules.ledger(table(spark, sf_dir, "documents")), quality_rules.POLICIES["v1"])
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_text_lines", "n_ellipsis_lines", "n_bullet_lines", "fail_bits")


def op7_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The contaminated documents: one row for each with each benchmark item that it holds."""
    return decontaminate.overlaps(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = line_dedup.drop_lines(docs, line_dedup.build_runs(docs), counts=("n_lines", "n_dropped"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("kept_sha256"))


def op9_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_labeller.extract_main_text(table(spark, sf_dir, "pages"))


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = recompression.remove_repeats(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in (op1_warc_derivatives, op2_license_scans, op3_chat_formatting, op4_source_mixing, op5_jaccard_join, op6_quality_rules, op7_benchmark_decontamination, op8_line_dedup, op9_html_extraction, op10_substring_dedup)}


#: Fixed text of the SQL: white space between words.
_SPACE_SQL = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
_WORDS_SQL = "list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '')"

OP4_SQL = f"""
with sized as (
  select doc_id, source, len({_WORDS_SQL})::bigint as size from documents),
ranked as (
  select source, sum(size)::bigint as source_size, row_number() over (order by source nulls last) - 1 as sid from sized group by source),
weighed as (select *, sid % 3 + 1 as w, 3 * source_size as cap from ranked),
filled as (
  select *,
    (sum(source_size) over ()) - coalesce(sum(cap) over (order by cap / w, sid rows between unbounded preceding and 1 preceding), 0) as rest_words,
    (sum(w) over ()) - coalesce(sum(w) over (order by cap / w, sid rows between unbounded preceding and 1 preceding), 0) as rest_weight
  from weighed),
flagged as (select *, cap * rest_weight < rest_words * w as capped from filled),
lam as (
  select (select sum(source_size) from flagged) - coalesce(sum(cap) filter (capped), 0) as words, (select sum(w) from flagged) - coalesce(sum(w) filter (capped), 0) as weight from flagged),
plan as (
  select f.source, f.source_size, case when capped then cap::double else (words * w)::double / weight::double end as target from flagged f, lam),
quota as (
  select *, least(3 * source_size, floor(target + 0.5))::bigint as q from plan),
passes as (select *, case when source_size > 0 then q // source_size else 0 end as full_passes, case when source_size > 0 then q % source_size else 0 end as rest from quota),
numbered as (
  select d.doc_id, d.source, d.size, row_number() over (partition by doc_id order by source, size)::varchar as rn from sized d),
blocks as (
  select n.doc_id, n.rn, n.source, p.rest, b.block, least(256, n.size - b.block * 256) as words,
    ('0x' || substr(md5('17:' || n.doc_id || ':' || n.rn || ':' || b.block || ':' || p.full_passes), 1, 15))::bigint as key
  from numbered n join passes p on n.source is not distinct from p.source, lateral (select unnest(range((n.size + 255) // 256)) as block) b
  where p.rest > 0),
placed as (
  select *, coalesce(sum(words) over (partition by source order by key, doc_id, rn, block rows between unbounded preceding and 1 preceding), 0) as before from blocks),
part as (select doc_id, rn, sum(greatest(0, least(words, rest - before)))::bigint as words from placed group by doc_id, rn)
select n.doc_id, n.size, p.source_size, p.target, (p.full_passes * n.size + coalesce(part.words, 0))::bigint as taken
from numbered n join passes p on n.source is not distinct from p.source left join part on part.doc_id = n.doc_id and part.rn = n.rn
"""

OP6_SQL = f"""
with base as (
  select doc_id, coalesce(text, '') as t, {_WORDS_SQL} as w from documents),
lines as (
  select doc_id, list_filter(string_split(t, chr(10)), lambda x: length(trim(x, {_SPACE_SQL})) > 0) as l from base),
windows as (
  select doc_id, i, array_to_string(w[i:i + 7], ' ') as k from base, lateral (select unnest(range(1, len(w) - 6)) as i) where len(w) >= 8),
twins as (
  select doc_id, i from (select doc_id, i, count(*) over (partition by doc_id, k) as n from windows) where n > 1),
covered as (
  select doc_id, count(distinct i + j)::bigint as n_repeat_words from twins, (select unnest(range(8)) as j) group by doc_id),
counted as (
  select b.doc_id, len(w)::bigint as n_words, length(array_to_string(w, ''))::bigint as word_chars,
    (length(t) - length(translate(t, '#*$%&|<>', '')))::bigint as n_symbols,
    (len(l) - len(list_distinct(l)))::bigint as n_dup_lines, coalesce(n_repeat_words, 0)::bigint as n_repeat_words, len(l)::bigint as n_text_lines,
    len(list_filter(l, lambda x: rtrim(x, ' ') like '%...' or rtrim(x, ' ') like '%…'))::bigint as n_ellipsis_lines,
    len(list_filter(l, lambda x: ltrim(x, ' ')[1] in ('-', '*', '•')))::bigint as n_bullet_lines
  from base b join lines using (doc_id) left join covered using (doc_id)),
bits as (
  select *, (case when n_words < 20 then 1 else 0 end + case when 100 * n_repeat_words > 30 * n_words then 2 else 0 end
    + case when word_chars < 2 * n_words then 4 else 0 end + case when word_chars > 16 * n_words then 8 else 0 end
    + case when n_symbols > n_words then 16 else 0 end + case when n_text_lines >= 4 and 100 * n_dup_lines > 60 * n_text_lines then 32 else 0 end
    + case when n_text_lines >= 4 and 100 * n_ellipsis_lines > 60 * n_text_lines then 64 else 0 end
    + case when n_text_lines >= 4 and 100 * n_bullet_lines > 95 * n_text_lines then 128 else 0 end)::bigint as fail_bits from counted)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (fail_bits & 3) <> 0 as base_failed, fail_bits = 0 as kept,
  n_text_lines, n_ellipsis_lines, n_bullet_lines, fail_bits from bits
"""

OP8_SQL = f"""
with lines as (
  select doc_id, p.i, p.line, translate(trim(p.line, {_SPACE_SQL}), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as k
  from documents, lateral (select unnest(list_transform(string_split(coalesce(text, ''), chr(10)), lambda x, j: struct_pack(i := j, line := x))) as p)),
often as (select k from lines where k <> '' group by k having count(distinct coalesce(doc_id::varchar, '')) >= 10)
select doc_id, count(*)::bigint as n_lines, count(o.k)::bigint as n_dropped,
  sha256(coalesce(string_agg(line, chr(10) order by i) filter (o.k is null), '')) as kept_sha256
from lines left join often o on lines.k = o.k group by doc_id
"""


OP10_SQL = f"""
with words as (
  select doc_id, {_WORDS_SQL} as w from documents),
windows as (
  select doc_id, i, array_to_string(w[i:i + 49], ' ') as k from words, lateral (select unnest(range(1, len(w) - 48)) as i) where len(w) >= 50),
repeated as (
  select doc_id, i from (select doc_id, i, min(doc_id) over (partition by k) as first from windows) where first < doc_id),
gone as (
  select doc_id, list(distinct i + j) as places from repeated, (select unnest(range(50)) as j) group by doc_id)
select doc_id, len(w)::bigint as n_words, coalesce(len(places), 0)::bigint as n_removed,
  sha256(array_to_string(case when places is null then w else list_transform(list_filter(list_zip(w, range(1, len(w) + 1)), lambda p: not list_contains(places, p[2])), lambda p: p[1]) end, ' ')) as kept_sha256
from words left join gone using (doc_id)
"""

_CONTROL_SQL = "|".join("".join(("\\" if ch in "[]/<>:" and ch in "[]" else "") + ch + (f"{chat_format.JOINER}*" if k == 0 else "") for k, ch in enumerate(c)) for c in chat_format.CONTROLS)
_ESCAPED = "(length({c}) + len(regexp_extract_all({c}, '" + _CONTROL_SQL + "')))"

OP3_SQL = f"""
with turns as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all values (-7, 0, 'user', '</s>[INST] ok [/INST]'), (-7, 1, 'assistant', '</s>[INST] ok [/INST]')),
sized as (
  select *, {_ESCAPED.format(c="text")} + case role when 'system' then 15 when 'user' then 13 when 'assistant' then 4 else 16 + {_ESCAPED.format(c="role")} end as chars from turns)
select conv_id, count(*)::bigint as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
  coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars, sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (role = 'assistant'), '')) as loss_sha256, (3 + sum(chars))::bigint as formatted_chars
from sized group by conv_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_chat_formatting": OP3_SQL, "op10_substring_dedup": OP10_SQL, "op4_source_mixing": OP4_SQL, "op6_quality_rules": OP6_SQL, "op8_line_dedup": OP8_SQL}
