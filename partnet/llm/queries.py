"""The ten operators over their whole tables, as registered queries, and their SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from partnet.llm import exact_dedup, html_text, mixing, packing, quality, rules, shards, simhash, token_files, urls
from partnet.llm.common import read_table


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    weights = quality.fit_quality(documents, read_table(spark, sf_dir, "labels"))
    scored = quality.score_documents(documents, weights)
    return scored.select("doc_id", quality.is_held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(read_table(spark, sf_dir, "documents"), ["doc_id"])


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rules.quality_rules(read_table(spark, sf_dir, "documents")).drop("rejected_by")  # which rule was first depends on the order


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.best_fit_pack(read_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(read_table(spark, sf_dir, "documents"))


def op6_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.token_round_trip(read_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.systematic_mix(read_table(spark, sf_dir, "documents"), ["doc_id"])
    return mixed.select("doc_id", "size", "source_size", "target", "taken")


def op8_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract_pages(read_table(spark, sf_dir, "pages"))


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = urls.judge_urls(read_table(spark, sf_dir, "pages"), urls.entries(spark, urls.RULES, urls.LISTED))
    return judged.select("page_id", "host", "path", "rule", "verdict")


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = shards.shard_rows(read_table(spark, sf_dir, "documents"))
    return placed.select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_quality, op2_exact_dedup, op3_quality_rules, op4_best_fit_packing, op5_simhash, op6_token_files, op7_mixing, op8_html_text, op9_url_filter, op10_sharding)
}

SPACE, WORD = r"[\x20\x09-\x0D]+", r"[^\x20\x09-\x0D]+"

OP2_SQL = f"""
SELECT doc_id, MIN(doc_id) OVER same AS keep_id, count(*) OVER same AS group_size, doc_id = MIN(doc_id) OVER same AS kept, sha256(t) AS text_sha256
FROM (SELECT doc_id, regexp_replace(coalesce(text, ''), '{SPACE}', ' ', 'g') AS t FROM documents) WINDOW same AS (PARTITION BY t)
"""

OP3_SQL = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '{WORD}') AS w FROM documents),
x AS (SELECT doc_id, unnest(w) AS a, generate_subscripts(w, 1) AS k FROM d),
p AS (SELECT doc_id, k, a, lead(a) OVER (PARTITION BY doc_id ORDER BY k) AS b, lead(a, 2) OVER (PARTITION BY doc_id ORDER BY k) AS c FROM x),
g AS (SELECT doc_id, k, count(*) OVER (PARTITION BY doc_id, a, b, c) AS n FROM p WHERE c IS NOT NULL),
r AS (SELECT doc_id, count(DISTINCT place) AS n_repeat_words FROM (SELECT doc_id, unnest([k, k + 1, k + 2]) AS place FROM g WHERE n > 1) GROUP BY doc_id),
l AS (SELECT doc_id, count(*) AS lines, count(*) - count(DISTINCT line) AS n_dup_lines FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM d) WHERE regexp_matches(line, '{WORD}') GROUP BY doc_id),
m AS (SELECT doc_id, len(w) AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars, length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS n_symbols,
  coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(lines, 0) AS lines, len(list_filter(w, lambda x: regexp_matches(x, '\\p{{L}}'))) AS lettered,
  len(regexp_extract_all(text, '\\p{{Lu}}')) AS upper_n, len(regexp_extract_all(text, '\\p{{Ll}}')) AS lower_n
  FROM d LEFT JOIN r USING (doc_id) LEFT JOIN l USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT (base_failed OR 5 * n_symbols > n_words OR 10 * n_dup_lines > 3 * lines OR word_chars < 2 * n_words OR word_chars > 15 * n_words OR 10 * lettered < 7 * n_words OR upper_n > lower_n) AS kept
FROM (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m)
"""

OP7_SQL = f"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{WORD}'))::BIGINT AS size FROM documents),
s AS (SELECT source, SUM(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, [5.0, 2.0, 1.0][((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::INT]::DOUBLE AS weight, source_size * 2.0::DOUBLE AS cap FROM s),
o AS (SELECT *, row_number() OVER (ORDER BY cap / weight, source NULLS LAST) AS k FROM w),
f AS (SELECT *, SUM(source_size) OVER () * 1.5::DOUBLE - coalesce(SUM(cap) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0) AS rest, SUM(weight) OVER (ORDER BY k ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS weight_left FROM o),
v AS (SELECT rest / weight_left AS level FROM f WHERE rest / weight_left * weight <= cap ORDER BY k LIMIT 1),
t AS (SELECT source, source_size, coalesce(least(cap, (SELECT level FROM v) * weight), cap) AS target FROM f),
r AS (SELECT d.doc_id, d.source, d.size, row_number() OVER (PARTITION BY d.source ORDER BY d.size DESC, d.doc_id % {mixing.SALTS}, d.doc_id) - 1 AS k FROM d),
c AS (SELECT r.doc_id, r.size, t.source_size, t.target, r.k::DOUBLE AS k, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0.0 END AS rate, ('0x' || substr(md5('7:' || coalesce(r.source, chr(0))), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS u
  FROM r JOIN t ON r.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target, ((floor((k + 1) * rate + u) - floor(k * rate + u))::BIGINT * size)::BIGINT AS taken FROM c
"""

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
FITS = "(host = e.h OR ends_with(host, '.' || e.h)) AND starts_with(path, e.p)"
OP9_SQL = f"""
WITH e(h, p, verdict, is_rule) AS (VALUES {", ".join([f"('{k[:k.index('/')]}', '{k[k.index('/'):]}', '{v}', true)" for k, v in urls.RULES] + [f"('{k[:k.index('/')]}', '{k[k.index('/'):]}', 'block', false)" for k in urls.LISTED])}),
u AS (SELECT page_id, translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 1), ''), '{UPPER}', '{LOWER}') AS host, coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 2), '') AS path FROM pages),
r AS (SELECT page_id, host, path, (SELECT arg_max(e.h || e.p, length(e.h || e.p)) FROM e WHERE is_rule AND {FITS}) AS rule, (SELECT count(*) FROM e WHERE NOT is_rule AND {FITS}) AS listed FROM u)
SELECT page_id, host, path, rule, coalesce((SELECT verdict FROM e WHERE is_rule AND e.h || e.p = rule), CASE WHEN listed > 0 THEN 'block' ELSE 'allow' END) AS verdict FROM r
"""

ORACLES: dict[str, str] = {"op2_exact_dedup": OP2_SQL, "op3_quality_rules": OP3_SQL, "op7_mixing": OP7_SQL, "op9_url_filter": OP9_SQL}
