"""The registered queries of this subpackage: each applies its operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontamination, html, licenses, linededup, neardup, packing, pii, quality, rules, sharding
from .scratch import table


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign_shards(table(spark, sf_dir, "documents"))


def op2_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(table(spark, sf_dir, "documents"))


def op3_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = html.main_text(table(spark, sf_dir, "pages"))
    return found.withColumn("n_chars", F.length("text").cast("long"))


def op4_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each document and benchmark item found in it."""
    return decontamination.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op5_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"), k=2)


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = rules.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    marked = quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return marked.select("doc_id", (quality.fold() == quality.HELD_OUT).alias("held_out"), "score", "predicted")


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.digest(table(spark, sf_dir, "documents"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, source, the cleaned text and its line counts."""
    return linededup.drop_boilerplate(table(spark, sf_dir, "documents")).select("doc_id", "source", "text", "n_lines", "n_dropped")


def law_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the law and the slots of op1 come to, shard by shard."""
    placed = sharding.assign_shards(table(spark, sf_dir, "documents"))
    count = lambda c: c.cast("long")  # noqa: E731
    return placed.groupBy("shard").agg(F.count("*").alias("n_rows"), count(F.min("slot")).alias("first_slot"), count(F.max("slot")).alias("last_slot"), F.countDistinct("slot").alias("n_slots"))


def sizes_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign_shards(table(spark, sf_dir, "documents")).select("doc_id", "size", "law")


def base_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The base counts of op2."""
    return pii.digest(table(spark, sf_dir, "documents")).select("doc_id", "n_email", "n_ip", "n_card", "n_phone")


def base_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The base measures of op6."""
    rows = rules.measured(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", rules.base_failed().alias("base_failed"))


def base_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The base places of op9."""
    return licenses.digest(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_sharding": op1_sharding,
    "op2_pii": op2_pii,
    "op3_html_extraction": op3_html_extraction,
    "op4_benchmark_decontamination": op4_benchmark_decontamination,
    "op5_minhash_near_dedup": op5_minhash_near_dedup,
    "op6_quality_rules": op6_quality_rules,
    "op7_best_fit_packing": op7_best_fit_packing,
    "op8_quality_classifier": op8_quality_classifier,
    "op9_license_scan": op9_license_scan,
    "op10_line_dedup": op10_line_dedup,
    # parts of the above that SQL can express
    "law_sharding": law_sharding,
    "sizes_sharding": sizes_sharding,
    "base_pii": base_pii,
    "base_rules": base_rules,
    "base_licenses": base_licenses,
}

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_DIGITS = "regexp_replace(m, '[^0-9]', '', 'g')"

ORACLES: dict[str, str] = {
    "law_sharding": """
SELECT CAST(s AS INTEGER) AS shard, n AS n_rows, CAST(0 AS BIGINT) AS first_slot, n - 1 AS last_slot, n AS n_slots
FROM (SELECT s, ((SELECT count(*) FROM documents) + 15 - s) // 16 AS n FROM range(16) AS r(s)) WHERE n > 0
""",
    "sizes_sharding": "SELECT doc_id, CAST(coalesce(strlen(text), 0) + 1 AS BIGINT) AS size, 'rows' AS law FROM documents",
    "base_pii": rf"""
WITH found AS (
  SELECT doc_id, regexp_extract_all(t, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+') AS email, regexp_extract_all(t, '[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+') AS ip,
         regexp_extract_all(t, '[0-9](?:[ -]?[0-9])+') AS card, regexp_extract_all(t, '\+[0-9][ ().0-9-]+[0-9]') AS phone
  FROM (SELECT doc_id, coalesce(text, '') AS t FROM documents)
)
SELECT doc_id, CAST(len(email) AS BIGINT) AS n_email,
  CAST(len(list_filter(ip, lambda m: list_bool_and(list_transform(string_split(m, '.'), lambda x: length(ltrim(x, '0')) < 3 OR (length(ltrim(x, '0')) = 3 AND ltrim(x, '0') <= '255'))))) AS BIGINT) AS n_ip,
  CAST(len(list_filter(card, lambda m: length({_DIGITS}) BETWEEN 12 AND 19 AND list_sum(list_transform(range(1, length({_DIGITS}) + 1), lambda i:
    CASE WHEN (length({_DIGITS}) - i) % 2 = 0 THEN ascii(substr({_DIGITS}, i, 1)) - 48 WHEN ascii(substr({_DIGITS}, i, 1)) > 52 THEN 2 * (ascii(substr({_DIGITS}, i, 1)) - 48) - 9 ELSE 2 * (ascii(substr({_DIGITS}, i, 1)) - 48) END)) % 10 = 0)) AS BIGINT) AS n_card,
  CAST(len(list_filter(phone, lambda m: length({_DIGITS}) BETWEEN 9 AND 15)) AS BIGINT) AS n_phone
FROM found
""",
    "base_rules": r"""
WITH words AS (
  SELECT doc_id, coalesce(text, '') AS t, list_filter(regexp_split_to_array(coalesce(text, ''), '[ 	-]+'), lambda x: x <> '') AS w FROM documents
), grams AS (
  SELECT doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM words WHERE len(w) >= 3)
), twins AS (
  SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS n FROM grams) WHERE n > 1
), covered AS (
  SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS p FROM twins) GROUP BY doc_id
), measured AS (
  SELECT words.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
    CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, coalesce(n, 0) AS n_repeat_words
  FROM (SELECT *, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^ 	-]')) AS l FROM words) words LEFT JOIN covered ON covered.doc_id = words.doc_id
)
SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM measured
""",
    "base_licenses": rf"""
WITH words AS (
  SELECT doc_id, regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), places AS (
  SELECT doc_id, i - 1 AS pos, CASE WHEN w[i] = 'mit' AND w[i + 1] = 'license' THEN 'mit' WHEN w[i] = 'apache' AND w[i + 1] = 'license' THEN 'apache'
    WHEN w[i] = 'general' AND w[i + 1] = 'public' AND w[i + 2] = 'license' THEN 'gpl' END AS label
  FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM words)
), found AS (
  SELECT doc_id, count(*) AS n, min(pos) AS first, max(pos) AS last, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM places WHERE label IS NOT NULL GROUP BY doc_id
)
SELECT words.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n, 0) AS n_base, first AS first_word, last AS last_word, coalesce(labels, '') AS base_labels FROM words LEFT JOIN found ON found.doc_id = words.doc_id
""",
    "op5_minhash_near_dedup": r"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[ \t-\r]+'), lambda x: x <> '') AS w
  FROM documents
), sets AS (
  SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) = 1 THEN [w[1]]
                               ELSE list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) END) AS s
  FROM words
), classes AS (
  SELECT min(doc_id) AS node, list_sort(s) AS s FROM sets GROUP BY list_sort(s) HAVING len(list_sort(s)) > 0
), shingles AS (
  SELECT node, len(s) AS n, unnest(s) AS g FROM classes
), links AS (
  SELECT a.node AS a, b.node AS b
  FROM shingles a JOIN shingles b ON a.g = b.g AND a.node < b.node AND 5 * least(a.n, b.n) >= 4 * greatest(a.n, b.n)
  GROUP BY a.node, b.node, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))
), edges AS (
  SELECT a, b FROM links UNION ALL SELECT b, a FROM links
), reach(node, hit) AS (
  SELECT node, node FROM classes UNION SELECT reach.node, edges.b FROM reach JOIN edges ON reach.hit = edges.a
), comp AS (
  SELECT node, min(hit) AS c FROM reach GROUP BY node
)
SELECT d.doc_id, CAST(len(d.s) AS BIGINT) AS n_shingles, coalesce(comp.c, d.doc_id) AS component_id, d.doc_id = coalesce(comp.c, d.doc_id) AS kept
FROM sets d LEFT JOIN classes ON list_sort(d.s) = classes.s LEFT JOIN comp ON comp.node = classes.node
""",
    "op10_line_dedup": r"""
WITH lines AS (
  SELECT doc_id, source, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos
  FROM documents
), keyed AS (
  SELECT *, trim(line, ' ' || chr(9) || chr(11) || chr(12) || chr(13)) AS k FROM lines
), sites AS (
  SELECT source AS of, count(*) AS site_pages FROM documents GROUP BY source
), boiler AS (
  SELECT source, k FROM (SELECT source, k, count(DISTINCT doc_id) AS pages FROM keyed WHERE k <> '' GROUP BY source, k)
  JOIN sites ON source IS NOT DISTINCT FROM of
  WHERE pages >= 3 AND pages > 0.05 * site_pages
), kept AS (
  SELECT keyed.doc_id, string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE boiler.k IS NULL) AS text,
         count(*) FILTER (WHERE keyed.k <> '') AS n_lines, count(*) FILTER (WHERE boiler.k IS NOT NULL) AS n_dropped
  FROM keyed LEFT JOIN boiler ON keyed.k = boiler.k AND keyed.source IS NOT DISTINCT FROM boiler.source
  GROUP BY keyed.doc_id
)
SELECT d.doc_id, d.source, CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(kept.text, '') END AS text,
       coalesce(kept.n_lines, 0) AS n_lines, coalesce(kept.n_dropped, 0) AS n_dropped
FROM documents d LEFT JOIN kept ON d.doc_id = kept.doc_id
""",
}
