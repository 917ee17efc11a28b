"""The queries of this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, html_extract, license_scan, pii, pu_quality, quality_rules, sharding, simhash, sp_codec, url_filter
from .common import table


def op1_string_tiling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op2_block_labeller(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract(table(spark, sf_dir, "pages"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op4_markov_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages"))


def op5_line_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality_rules.judge(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op6_virtual_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.assign(table(spark, sf_dir, "documents"))
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "virtual_slot", "map_version")


def op7_streaming_viterbi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sp_codec.encode(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "n_ids", "round_trip", "ids")


def op8_license_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(table(spark, sf_dir, "documents"))


def op9_weak_supervision(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.find(table(spark, sf_dir, "documents"))


def op10_pu_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pu_quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Host, path and rule of every URL, without the models."""
    judged = url_filter.judged_by_rules(table(spark, sf_dir, "pages"), "page_id", "url", url_filter.RULES)
    return judged.select(F.col("id").alias("page_id"), "host", "path", "rule", "ruled")


def shard_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.sized(table(spark, sf_dir, "documents")).select("doc_id", "size")


def license_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What op8 finds of the fixed phrases."""
    return license_scan.scan(table(spark, sf_dir, "documents"), templates=[]).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels")


def personal_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What op9 finds by fixed patterns."""
    found = pii.find(table(spark, sf_dir, "documents"), model=pii.SpanModel({}, {}, {}))
    return found.select("doc_id", "n_email", "n_ip", "n_card", "n_phone")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_string_tiling, op2_block_labeller, op3_simhash, op4_markov_ratio, op5_line_rules, op6_virtual_slots, op7_streaming_viterbi, op8_license_templates, op9_weak_supervision, op10_pu_quality, pipeline, url_rules, shard_sizes, license_base, personal_base)}

_OP5_RULES = quality_rules.LineRules()
#: Line rules and counts of op5 for DuckDB. A line fails by marks, by lack of punctuation, or as short navigation or boilerplate.
_OP5 = rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT r, doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws, string_split(t, chr(10)) AS ls FROM d),
lines AS (SELECT r, unnest(ls) AS l FROM w),
judged AS (SELECT r, l, regexp_matches(l, '[^\x20\x09-\x0D]') AS word,
  100 * length(regexp_replace(l, '[^#*$%&|<>!?~^_=+{{}}\[\]\\]+', '', 'g')) > {_OP5_RULES.mark_percent} * length(l) AS marked,
  NOT regexp_matches(l, '[.,;:!?…。，]') AND len(regexp_extract_all(l, '[^\x20\x09-\x0D]+')) >= {_OP5_RULES.bare_words} AS bare,
  length(l) <= {_OP5_RULES.short_line} AND (
    regexp_matches(l, '^(?i:[\x20\x09-\x0D]*(?:{quality_rules.NAVIGATION})(?:[\x20\x09-\x0D|»›>/·-]+|$))+$')
    OR regexp_matches(l, '\b(?i:{quality_rules.BOILERPLATE})\b')) AS chrome FROM lines),
lost AS (SELECT r, sum(CASE WHEN word AND (marked OR bare OR chrome) THEN length(regexp_replace(l, '[\x20\x09-\x0D]+', '', 'g')) ELSE 0 END) AS lost,
  count(*) FILTER (word) - count(DISTINCT l) FILTER (word) AS n_dup_lines FROM judged GROUP BY r),
win AS (SELECT r, unnest(range(1, len(ws) - 3)) AS i, ws FROM w WHERE len(ws) >= 5),
many AS (SELECT r, i, count(*) OVER (PARTITION BY r, array_to_string(ws[i:i + 4], ' ')) AS n FROM win),
twice AS (SELECT r, i, lead(i) OVER (PARTITION BY r ORDER BY i) AS nxt FROM many WHERE n > 1),
rep AS (SELECT r, CAST(sum(least(5, coalesce(nxt - i, 5))) AS BIGINT) AS n FROM twice GROUP BY r),
m AS (SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
  CAST(length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols, n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words, lost
  FROM w JOIN lost USING (r) LEFT JOIN rep USING (r))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  n_words < {_OP5_RULES.min_words} OR 100 * n_repeat_words > {_OP5_RULES.repeat_percent} * n_words AS base_failed,
  NOT (n_words < {_OP5_RULES.min_words} OR 100 * n_repeat_words > {_OP5_RULES.repeat_percent} * n_words) AND 100 * lost <= {_OP5_RULES.loss_percent} * word_chars AS kept FROM m"""

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _fits(rule: str) -> str:
    name, _, rest = rule.partition("/")
    return f"(host = '{name}' OR ends_with(host, '.{name}')) AND starts_with(path, '/{rest}')"


_URLS = url_filter.RULES
_URL_RULES = rf"""
WITH u AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) END AS rest FROM pages),
h AS (SELECT page_id, rest, coalesce(regexp_extract(rest, '^[^/?#]*'), '') AS raw FROM u),
p AS (SELECT page_id, translate(raw, '{_UPPER}', '{_LOWER}') AS host, coalesce(regexp_extract(substr(rest, length(raw) + 1), '^[^?#]*'), '') AS path FROM h),
r AS (SELECT *, CASE {" ".join(f"WHEN {_fits(x)} THEN '{x}'" for x in sorted(_URLS, key=lambda x: (-len(x), x)))} END AS rule FROM p)
SELECT page_id, host, path, rule, CASE {" ".join(f"WHEN rule = '{x}' THEN '{v}'" for x, v in _URLS.items())} END AS ruled FROM r"""

_SIZES = f"SELECT doc_id, CAST(coalesce(octet_length(encode(text)), 0) + {sharding.OVERHEAD_BYTES} AS BIGINT) AS size FROM documents"

_PHRASE = "list_transform(list_filter(range(1, len(w) + 1), lambda i: array_to_string(w[i:i + {m}], ' ') = '{p}'), lambda i: {{'at': i - 1, 'label': '{v}'}})"
_LICENSES = rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
f AS (SELECT r, doc_id, len(w) AS n, flatten([{", ".join(_PHRASE.format(m=len(p.split()) - 1, p=p, v=v) for p, v in license_scan.PHRASES.items())}]) AS found FROM d)
SELECT doc_id, CAST(n AS BIGINT) AS n_words, CAST(len(found) AS BIGINT) AS n_base,
  CAST(list_min(list_transform(found, lambda x: x.at)) AS BIGINT) AS first_word, CAST(list_max(list_transform(found, lambda x: x.at)) AS BIGINT) AS last_word,
  array_to_string(list_sort(list_distinct(list_transform(found, lambda x: x.label))), ',') AS base_labels FROM f"""

_PERSONAL = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
m AS (SELECT doc_id, regexp_extract_all(t, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+') AS mails, regexp_extract_all(t, '[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)') AS ips,
  list_filter(list_transform(regexp_extract_all(t, '[0-9]([\x20-]?[0-9])+'), lambda x: regexp_replace(x, '[^0-9]', '', 'g')), lambda x: length(x) BETWEEN 16 AND 19) AS cards,
  list_transform(regexp_extract_all(t, '\+[0-9][\x20().0-9-]+[0-9]'), lambda x: regexp_replace(x, '[^0-9]', '', 'g')) AS phones FROM d)
SELECT doc_id, CAST(len(mails) AS BIGINT) AS n_email,
  CAST(len(list_filter(ips, lambda x: list_bool_and(list_transform(string_split(x, '.'), lambda p: length(ltrim(p, '0')) <= 3 AND coalesce(TRY_CAST(ltrim(p, '0') AS INTEGER), 0) <= 255)))) AS BIGINT) AS n_ip,
  CAST(len(list_filter(cards, lambda x: list_sum(list_transform(range(1, length(x) + 1), lambda i: CASE WHEN i % 2 = 1 THEN CAST(substr(x, length(x) + 1 - i, 1) AS INTEGER)
    ELSE 2 * CAST(substr(x, length(x) + 1 - i, 1) AS INTEGER) - CASE WHEN CAST(substr(x, length(x) + 1 - i, 1) AS INTEGER) > 4 THEN 9 ELSE 0 END END)) % 10 = 0)) AS BIGINT) AS n_card,
  CAST(len(list_filter(phones, lambda x: length(x) BETWEEN 8 AND 15)) AS BIGINT) AS n_phone FROM m"""

ORACLE: dict[str, str] = {"op5_line_rules": _OP5, "url_rules": _URL_RULES, "shard_sizes": _SIZES, "license_base": _LICENSES, "personal_base": _PERSONAL}
