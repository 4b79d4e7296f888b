"""Queries over the given tables, one for each operator, and their DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, decontam, html_extract, license_scan, line_dedup, mixing, quality, simhash, toxicity, url_filter
from .common import table

Query = Callable[[SparkSession, str], DataFrame]
ASCII = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'"


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score_toxicity(docs, toxicity.fit_lexicon(docs, table(spark, sf_dir, "labels")))


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(table(spark, sf_dir, "documents"))


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(table(spark, sf_dir, "pages"), url_filter.HOST_RULES + url_filter.PATTERN_RULES)


def op4_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.score_quality(docs, quality.fit_quality(docs, table(spark, sf_dir, "labels")))


def op6_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract(table(spark, sf_dir, "pages"))


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A row for each benchmark item found in a document."""
    return decontam.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, text without repeated lines, how many went."""
    return line_dedup.dedup_lines(table(spark, sf_dir, "documents"), line_dedup.EVERY_LINE).select("doc_id", "deduped.text", "deduped.n_removed")


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sampled documents, with their cell and its probability."""
    return mixing.sample(table(spark, sf_dir, "documents")).select("doc_id", "source", "lang", "mix.*")


def op10_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def sql_text(s: str) -> str:
    return "'" + s.replace("'", "''") + "'"


def _op2_sql() -> str:
    """Brute force: every window of lines with every template."""
    word = r"'[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'"
    rows = ", ".join(
        f"({sql_text(label)}, [{', '.join(sql_text(w) for w in dict.fromkeys(text.split(' ')))}], {sql_text(t) if (t := license_scan.TELLING.get(label)) in text.split(' ') else 'NULL'})"
        for label, text in license_scan.TEMPLATES
    )
    ahead = [f"lead(w, {k}) OVER (PARTITION BY doc_id ORDER BY i) AS w{k}" for k in range(1, license_scan.SPAN)]
    window = ["w"] + [f"CASE WHEN {' AND '.join(f'len(w{j}) > 0' for j in range(1, k + 1))} THEN w{k} ELSE [] END" for k in range(1, license_scan.SPAN)]
    places, labels = [], []
    for i, (phrase, label) in enumerate(license_scan.PHRASES):
        parts = phrase.split(" ")
        cond = " AND ".join(f"w[i + {k}] = {sql_text(p)}" for k, p in enumerate(parts))
        places.append(f"list_filter(range(1, len(w) - {len(parts) - 2}), lambda i: {cond}) AS p{i}")
        labels.append(f"CASE WHEN len(p{i}) > 0 THEN {sql_text(label)} END")
    return f"""
WITH low AS (SELECT doc_id, translate(coalesce(text, ''), {ASCII}) AS t FROM documents),
tok AS (SELECT doc_id, t, regexp_extract_all(t, {word}) AS w FROM low),
pl AS (SELECT doc_id, w, {', '.join(places)} FROM tok),
base AS (SELECT doc_id, w, list_concat(list_concat(p0, p1), p2) AS places,
  list_filter([{', '.join(labels)}], lambda x: x IS NOT NULL) AS base FROM pl),
lines AS (SELECT doc_id, generate_subscripts(string_split(t, chr(10)), 1) AS i, regexp_extract_all(unnest(string_split(t, chr(10))), {word}) AS w FROM low),
near AS (SELECT doc_id, w, {', '.join(ahead)} FROM lines),
sets AS (SELECT doc_id, list_distinct(flatten([{', '.join(window)}])) AS s FROM near WHERE len(w) > 0),
tpl(label, words, telling) AS (VALUES {rows}),
met AS (SELECT doc_id, label, len(list_intersect(s, words)) / len(words) AS c FROM sets, tpl
  WHERE len(list_intersect(s, words)) >= ceil(0.8 * len(words) - 1e-9) AND (telling IS NULL OR list_contains(s, telling))),
best AS (SELECT doc_id, list(DISTINCT label) AS more, max(c) AS c FROM met GROUP BY doc_id)
SELECT b.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(places) AS BIGINT) AS n_base,
  CAST(list_min(places) - 1 AS BIGINT) AS first_word, CAST(list_max(places) - 1 AS BIGINT) AS last_word,
  array_to_string(list_sort(base), ',') AS base_labels,
  array_to_string(list_sort(list_distinct(list_concat(base, coalesce(more, [])))), ',') AS labels,
  CASE WHEN len(places) > 0 THEN 1.0::DOUBLE ELSE coalesce(c, 0.0)::DOUBLE END AS score
FROM base b LEFT JOIN best m ON b.doc_id = m.doc_id"""


def _op3_sql() -> str:
    hosts = ", ".join(f"({sql_text(r.name)}, {sql_text(r.verdict)}, {sql_text(r.name.partition('/')[0])}, {sql_text('/' + r.name.partition('/')[2])})" for r in url_filter.HOST_RULES)
    patterns = ", ".join(f"({sql_text(r.regex)}, {sql_text(r.verdict)})" for r in url_filter.PATTERN_RULES)
    form = r"'(?s)^.*?://([^/?#]*)([^?#]*)'"
    return f"""
WITH u AS (SELECT page_id, translate(coalesce(url, ''), {ASCII}) AS low,
  translate(coalesce(regexp_extract(url, {form}, 1), ''), {ASCII}) AS host,
  coalesce(regexp_extract(url, {form}, 2), '') AS path FROM pages),
hr(rule, verdict, h, p) AS (VALUES {hosts}),
pr(regex, verdict) AS (VALUES {patterns}),
a AS (SELECT page_id, max({{'n': length(rule), 'rule': rule, 'verdict': hr.verdict}}) AS b FROM u, hr
  WHERE (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p) GROUP BY page_id),
m AS (SELECT page_id, max({{'n': length(regex), 'regex': regex, 'verdict': pr.verdict}}) AS b FROM u, pr
  WHERE regexp_matches(low, regex) GROUP BY page_id)
SELECT u.page_id, host, path, a.b.rule AS rule, coalesce(a.b.verdict, m.b.verdict, 'allow') AS verdict
FROM u LEFT JOIN a ON u.page_id = a.page_id LEFT JOIN m ON u.page_id = m.page_id"""


OP10_SQL = """
WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda e: e IS NULL OR NOT isfinite(e))) = 0
    AND len(list_filter(embedding, lambda e: e <> 0)) > 0),
p AS (SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.x, c.x) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM p)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 20"""


QUERIES = [op1_toxicity, op2_license_scan, op3_url_filter, op4_simhash_near_dedup, op5_quality, op6_html_extraction, op7_decontamination, op8_line_dedup, op9_mixing, op10_nearest_neighbours]


def queries() -> dict[str, Query]:
    return {q.__name__: q for q in QUERIES}


def oracle_sql() -> dict[str, str]:
    return {"op2_license_scan": _op2_sql(), "op3_url_filter": _op3_sql(), "op10_nearest_neighbours": OP10_SQL}
