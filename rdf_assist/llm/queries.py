"""The registered queries of this subpackage and, where SQL can express them, their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe_trie, chat, lattice, media, packing, quality, simhash, suffixes, tokenfile, urls
from .common import table
from .tokens import public_path

# The url rules of the query, as (verdict, host, path).
URL_RULES = [
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
]


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality.quality(table(spark, sf_dir, "documents"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("quality", 6).alias("quality"))


def op2_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(table(spark, sf_dir, "pages"), urls.rule_frame(spark, URL_RULES))


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), public_path("byte_bpe_50k.json"))


def op4_lattice_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lattice.score(table(spark, sf_dir, "documents"), public_path("piece_bpe_32k.model"))


def op5_preference_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = chat.format_pairs(chat.reply_pairs(table(spark, sf_dir, "conversations")))

    def spans(name: str):
        return F.array_join(F.transform(name, lambda s: F.format_string("%d-%d", s["from"], s["to"])), ",")

    return made.select("conv_id", "other_id", "n_common", "prompt", F.col("chosen_text").alias("chosen"), F.col("rejected_text").alias("rejected"), spans("chosen_mask").alias("chosen_mask"), spans("rejected_mask").alias("rejected_mask"))


def op6_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenfile.round_trip(table(spark, sf_dir, "documents"), public_path("word_bpe_49k.json"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.digests(table(spark, sf_dir, "documents"))


def op9_bpe_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_trie.digests(table(spark, sf_dir, "documents"), public_path("word_bpe_49k.json"))


def op10_media_webp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.features(media.store(table(spark, sf_dir, "documents")))


ALL = (op1_quality_rules, op2_url_filters, op3_packing, op4_lattice_score, op5_preference_format, op6_token_files, op7_simhash, op8_suffix_dedup, op9_bpe_trie, op10_media_webp)


def queries() -> dict:
    return {f.__name__: f for f in ALL}


OP2_SQL = """
WITH rules(verdict, host, path) AS (VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/')),
rests AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
parts AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path, row_number() OVER () AS n FROM rests),
fits AS (
    SELECT p.*, r.host || r.path AS rule, r.verdict, row_number() OVER (PARTITION BY p.n ORDER BY length(r.host || r.path) DESC NULLS LAST, length(r.host) DESC) AS best
    FROM parts p LEFT JOIN rules r ON (p.host = r.host OR ends_with(p.host, '.' || r.host)) AND starts_with(p.path, r.path))
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM fits WHERE best = 1
"""

OP5_SQL = """
WITH turns AS (
    SELECT conv_id, replace(coalesce(role, ''), '<|', '< |') AS role, replace(coalesce(text, ''), '<|', '< |') AS text,
        row_number() OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS i
    FROM conversations WHERE conv_id IS NOT NULL),
ends AS (SELECT conv_id, max(i) AS n FROM turns WHERE role = 'assistant' GROUP BY conv_id),
replies AS (SELECT t.conv_id, t.text, e.n FROM turns t JOIN ends e ON t.conv_id = e.conv_id AND t.i = e.n),
pairs AS (SELECT a.conv_id, b.conv_id AS other_id, a.n, a.text AS chosen, b.text AS rejected FROM replies a JOIN replies b ON b.conv_id = xor(a.conv_id, 1)),
shared AS (
    SELECT p.conv_id, string_agg('<|' || t.role || '|>' || chr(10) || t.text || '<|end|>' || chr(10), '' ORDER BY t.i) AS prompt
    FROM pairs p JOIN turns t ON t.conv_id = p.conv_id AND (t.i < p.n OR p.chosen = p.rejected AND t.i = p.n) GROUP BY p.conv_id)
SELECT p.conv_id, p.other_id, CASE WHEN chosen = rejected THEN n ELSE n - 1 END AS n_common, coalesce(prompt, '') AS prompt,
    CASE WHEN chosen = rejected THEN '' ELSE '<|assistant|>' || chr(10) || chosen || '<|end|>' || chr(10) END AS chosen,
    CASE WHEN chosen = rejected THEN '' ELSE '<|assistant|>' || chr(10) || rejected || '<|end|>' || chr(10) END AS rejected,
    CASE WHEN chosen = rejected THEN '' ELSE '14-' || (length(chosen) + 22) END AS chosen_mask,
    CASE WHEN chosen = rejected THEN '' ELSE '14-' || (length(rejected) + 22) END AS rejected_mask
FROM pairs p LEFT JOIN shared s USING (conv_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_url_filters": OP2_SQL, "op5_preference_format": OP5_SQL}
