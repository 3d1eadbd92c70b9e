"""Queries of this subpackage, and their SQL where SQL can say them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patternlm.llm import exact_dedup, jaccard_join, language_id, license_scan, merkle_audit, mixing, packing, quality_classifier, quality_rules, secret_scan

Query = Callable[[SparkSession, str], DataFrame]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def damaged(pages: DataFrame) -> DataFrame:
    """A replica of pages with known damage by page_id modulo 97: 3 changed, 5 lost, 7 cut short, 9 renamed."""
    i = F.pmod("page_id", F.lit(97))
    html = F.when(i == 3, F.concat(F.lit("x"), "html")).when(i == 7, F.substring("html", 1, 100)).otherwise(F.col("html"))
    return pages.where(i != 5).select(F.when(i == 9, F.col("page_id") + 10**9).otherwise(F.col("page_id")).alias("page_id"), "url", html.alias("html"))


def op1_merkle_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    found = merkle_audit.audit(pages, damaged(pages), "page_id", merkle_audit.warc_record(F.col("url"), F.col("html")))
    return found.select(F.col("key").alias("page_id"), F.col("range").alias("range_no"), F.col("offset").alias("start"), "length", "copies", "sha", "status")


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.license_scan(table(spark, sf_dir, "documents"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.learn_and_identify(table(spark, sf_dir, "documents"))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.quality_rules(table(spark, sf_dir, "documents"))


def op5_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.jaccard_join(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id", "class_id")


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_classifier.learn_and_score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.secret_scan(table(spark, sf_dir, "documents"))


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.best_fit_packing(table(spark, sf_dir, "documents"))


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(table(spark, sf_dir, "documents"))


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


LOW = "translate(coalesce({0}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
WORDS = r"list_filter(regexp_split_to_array({0}, '[\x20\x09-\x0D]+'), lambda x: x <> '')"

OP1 = f"""
WITH rec AS (SELECT page_id, 'WARC/1.1' || chr(13) || chr(10) || 'WARC-Type: resource' || chr(13) || chr(10) || 'WARC-Target-URI: ' || coalesce(url, '') AS head, html FROM pages),
a AS (SELECT page_id, head || chr(13) || chr(10) || 'Content-Length: ' || CAST(strlen(coalesce(html, '')) AS VARCHAR) || chr(13) || chr(10) || chr(13) || chr(10) || coalesce(html, '') || chr(13) || chr(10) || chr(13) || chr(10) AS r FROM rec),
dmg AS (SELECT CASE WHEN page_id % 97 = 9 THEN page_id + 1000000000 ELSE page_id END AS page_id, head,
  CASE WHEN page_id % 97 = 3 THEN 'x' || html WHEN page_id % 97 = 7 THEN substring(html, 1, 100) ELSE html END AS html FROM rec WHERE page_id % 97 <> 5),
b AS (SELECT page_id, head || chr(13) || chr(10) || 'Content-Length: ' || CAST(strlen(coalesce(html, '')) AS VARCHAR) || chr(13) || chr(10) || chr(13) || chr(10) || coalesce(html, '') || chr(13) || chr(10) || chr(13) || chr(10) AS r FROM dmg),
x AS (SELECT page_id, sha256(r) AS sha, CAST(strlen(r) AS BIGINT) AS length, count(*) AS copies FROM a GROUP BY ALL),
y AS (SELECT page_id, sha256(r) AS sha, CAST(strlen(r) AS BIGINT) AS length, count(*) AS copies FROM b GROUP BY ALL),
o AS (SELECT *, CAST(coalesce(sum(length * copies) OVER (ORDER BY page_id, sha ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start FROM x),
g AS (SELECT *, start // {merkle_audit.RANGE_BYTES} AS range_no FROM o),
f AS (SELECT range_no, min((page_id, sha)) AS first FROM g GROUP BY range_no),
z AS (SELECT y.*, coalesce((SELECT max(range_no) FROM f WHERE f.first <= (y.page_id, y.sha)), 0) AS range_no FROM y)
SELECT coalesce(g.page_id, z.page_id) AS page_id, CAST(coalesce(g.range_no, z.range_no) AS BIGINT) AS range_no, g.start, coalesce(g.length, z.length) AS length,
  CAST(coalesce(g.copies, z.copies) AS BIGINT) AS copies, coalesce(g.sha, z.sha) AS sha,
  CASE WHEN g.sha IS NOT NULL AND z.sha IS NOT NULL THEN CASE WHEN g.copies > z.copies THEN 'missing' WHEN g.copies < z.copies THEN 'extra' ELSE 'ok' END
    WHEN g.sha IS NOT NULL THEN CASE WHEN g.page_id IN (SELECT page_id FROM y) THEN 'corrupt' ELSE 'missing' END
    WHEN z.page_id IN (SELECT page_id FROM x) THEN 'damaged copy' ELSE 'extra' END AS status
FROM g FULL JOIN z ON g.page_id = z.page_id AND g.sha = z.sha"""

OP4 = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, {WORDS.format("coalesce(text, '')")} AS w FROM documents),
win AS (SELECT doc_id, unnest(range(1, greatest(len(w) - 6, 1))) AS i, unnest([array_to_string(w[i : i + 7], ' ') for i in range(1, greatest(len(w) - 6, 1))]) AS s FROM d),
rep AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, s) AS c FROM win) WHERE c > 1),
cov AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM rep, range(0, 8) AS r(k) GROUP BY doc_id),
ln AS (SELECT doc_id, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS x FROM d),
st AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars,
  CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
  CAST(len(x) - len(list_distinct(x)) AS BIGINT) AS n_dup_lines, CAST(coalesce(n, 0) AS BIGINT) AS n_repeat_words,
  greatest(len(w), 1) AS nw, greatest(len(x), 1) AS nl,
  len(list_filter(w, lambda x: list_contains([{", ".join(f"'{x}'" for x in dict.fromkeys(" ".join(quality_rules.STOP_WORDS.values()).split()))}], x))) AS stops,
  len(list_filter(w, lambda x: ends_with(x, '!!'))) AS shouts,
  len(list_filter(x, lambda y: regexp_matches(y, '^[\\x20\\x09]*[-*•]'))) AS bullets,
  len(list_filter(x, lambda y: regexp_matches(y, '(\\.\\.\\.|…)[\\x20\\x09\\x0D]*$'))) AS dots
  FROM d JOIN ln USING (doc_id) LEFT JOIN cov USING (doc_id)),
v AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed, concat_ws(',',
  CASE WHEN n_words < 20 THEN 'few_words' END, CASE WHEN word_chars / nw < 2 THEN 'short_words' END, CASE WHEN word_chars / nw > 14 THEN 'long_words' END,
  CASE WHEN n_symbols / nw > 0.1 THEN 'symbols' END, CASE WHEN shouts / nw > 0.3 THEN 'shouting' END, CASE WHEN stops / nw < 0.02 THEN 'no_stop_words' END,
  CASE WHEN n_dup_lines / nl > 0.5 THEN 'repeated_lines' END, CASE WHEN bullets / nl > 0.9 THEN 'bullet_lines' END, CASE WHEN dots / nl > 0.3 THEN 'ellipsis_lines' END) AS broken_rules FROM st)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND broken_rules = '' AS kept, broken_rules FROM v"""

OP5 = f"""
WITH RECURSIVE d AS (SELECT doc_id, {WORDS.format(LOW.format("text"))} AS w FROM documents),
sh AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')] ELSE [array_to_string(w[i : i + 2], ' ') for i in range(1, len(w) - 1)] END) AS s FROM d),
n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM sh x JOIN sh y ON x.s = y.s AND x.doc_id <> y.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * c >= 90 * (na.n + nb.n - c)),
r AS (SELECT doc_id AS a, doc_id AS b FROM d UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a),
same AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN doc_id ELSE min(doc_id) OVER (PARTITION BY CASE WHEN len(w) = 0 THEN 'id ' || doc_id ELSE (SELECT string_agg(s, chr(10) ORDER BY s) FROM sh WHERE sh.doc_id = d.doc_id) END) END AS class_id FROM d)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, min(r.b) AS component_id, any_value(same.class_id) AS class_id
FROM d LEFT JOIN n USING (doc_id) JOIN r ON r.a = d.doc_id JOIN same USING (doc_id) GROUP BY d.doc_id, n.n"""

OP9 = f"""
WITH d AS (SELECT doc_id, {LOW.format("text")} AS t FROM documents),
g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY t)
SELECT doc_id, keep_id, CAST(group_size AS BIGINT) AS group_size, doc_id = keep_id AS kept, sha256(t) AS text_sha256 FROM d JOIN g USING (t)"""


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in (op1_merkle_audit, op2_license_scan, op3_language_id, op4_quality_rules, op5_jaccard_join, op6_quality_classifier, op7_secret_scan, op8_best_fit_packing, op9_exact_dedup, op10_mixing)}


def oracle_sql() -> dict[str, str]:
    return {"op1_merkle_audit": OP1, "op2_license_scan": license_scan.sql(), "op4_quality_rules": OP4, "op5_jaccard_join": OP5, "op9_exact_dedup": OP9}
