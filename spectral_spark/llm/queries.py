"""Driver queries of the training-data operators, and SQL where it can state them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import mixing, near_dedup, packing, quality, substring_dedup, tokens, toxicity, url_filter, vp_search, warc

RULES = [("block", "com/en/"), ("allow", "example.com/en/7"), ("allow", "net/de/"), ("block", "example.net/de/8"), ("block", "org/es/")]


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(spark, _t(spark, sf_dir, "documents"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.token_counts(_t(spark, sf_dir, "documents"))


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per removed run: the document, where the run lies in its words, and the document in which the passage stays."""
    spans = substring_dedup.repeated_spans(spark, _t(spark, sf_dir, "documents"))
    return spans.select("doc_id", F.explode("spans").alias("s")).select("doc_id", F.col("s.first").alias("first_word"), F.col("s.size").alias("n_words"), F.col("s.home").alias("kept_in_doc_id"))


def op4_warc_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = warc.archive(spark, _t(spark, sf_dir, "pages"))
    return out.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "sound")


def op5_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.filter_urls(spark, _t(spark, sf_dir, "pages"), RULES)


def op6_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = quality.line_first_cleaning(_t(spark, sf_dir, "documents"), with_text=False)
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "words_kept")


def op7_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixing.mix_sources(_t(spark, sf_dir, "documents").select("doc_id", "source", "text"))
    return out.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


def op8_toxicity_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _t(spark, sf_dir, "documents").select("doc_id", "text")
    scored = toxicity.score_toxicity(spark, docs, toxicity.fit_toxicity(docs, _t(spark, sf_dir, "labels")))
    return scored.drop("text")


def op9_vp_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = _t(spark, sf_dir, "embeddings")
    return vp_search.nearest(spark, vectors, vectors.where("vec_id % 100 = 0"))


def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(spark, _t(spark, sf_dir, "documents"))


QUERIES = {
    f.__name__: f
    for f in (
        op1_minhash_near_dedup,
        op2_token_counts,
        op3_substring_dedup,
        op4_warc_archive,
        op5_url_filter,
        op6_line_quality,
        op7_mix_sources,
        op8_toxicity_chain,
        op9_vp_nearest,
        op10_best_fit_packing,
    )
}

_URL_SQL = r"""
WITH u AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
p AS (SELECT page_id, translate(regexp_extract(coalesce(rest, ''), '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
        regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) AS path FROM u),
r(rh, rp, rule, rv) AS (VALUES ('com', '/en/', 'com/en/', 'block'), ('example.com', '/en/7', 'example.com/en/7', 'allow'), ('net', '/de/', 'net/de/', 'block'),
        ('example.net', '/de/8', 'example.net/de/8', 'block'), ('org', '/es/', 'org/es/', 'block'))
SELECT page_id, host, path,
  (SELECT max_by(rule, length(rule)) FROM r WHERE (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp)) AS rule,
  coalesce((SELECT max_by(rv, length(rule)) FROM r WHERE (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp)), 'allow') AS verdict
FROM p
"""

_NEAR_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(ws[i:i + 2], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 2, 1) + 1)) AS i FROM w WHERE len(ws) > 0) q),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id),
e AS MATERIALIZED (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * k >= 85 * (x.n + y.n - k)),
reach(a, b) AS (SELECT a, b FROM e UNION SELECT reach.a, e.b FROM reach JOIN e ON reach.b = e.a),
c AS (SELECT a, min(b) AS least_id FROM reach GROUP BY a)
SELECT w.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, least(w.doc_id, coalesce(c.least_id, w.doc_id)) AS component_id, w.doc_id <= coalesce(c.least_id, w.doc_id) AS kept
FROM w LEFT JOIN n USING (doc_id) LEFT JOIN c ON c.a = w.doc_id
"""

_WARC_SQL = r"""
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS body FROM pages),
d AS (SELECT page_id, octet_length(body) AS payload_bytes, sha1(body) AS hex, max(page_id) OVER (PARTITION BY body) AS latest FROM p)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes,
  array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST(((CAST('0x' || substr(hex, CAST(i * 5 // 4 + 1 AS INT), 2) AS INT) >> CAST(3 - (i * 5) % 4 AS INT)) & 31) + 1 AS INT), 1)), '') AS payload_digest,
  CASE WHEN page_id = latest THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id = latest THEN NULL ELSE latest END AS refers_to, true AS sound
FROM d
"""

_QUALITY_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT r, i, ws[i] AS w FROM (SELECT r, ws, unnest(range(1, len(ws) + 1)) AS i FROM (SELECT r, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws FROM d) a) b),
n AS (SELECT r, count(*) AS n_words, sum(length(w)) AS word_chars FROM w GROUP BY r),
g AS (SELECT r, i, w || ' ' || lead(w, 1) OVER v || ' ' || lead(w, 2) OVER v || ' ' || lead(w, 3) OVER v || ' ' || lead(w, 4) OVER v AS g FROM w WINDOW v AS (PARTITION BY r ORDER BY i)),
m AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, g) AS c FROM g WHERE g IS NOT NULL) q WHERE c > 1),
rep AS (SELECT r, count(DISTINCT i + k) AS n_repeat_words FROM m CROSS JOIN range(0, 5) o(k) GROUP BY r),
l AS (SELECT r, s, len(regexp_extract_all(s, '[^\x20\x09-\x0D]+')) AS n FROM (SELECT r, unnest(string_split(t, chr(10))) AS s FROM d) q),
judged AS (SELECT r, s, n, NOT (
    (n >= 3 AND (len(string_split(s, ' | ')) + len(string_split(s, ' » ')) + len(string_split(s, ' > ')) - 3) >= 0.25 * n)
    OR (n <= 30 AND regexp_matches(s, 'lorem ipsum|all rights reserved|terms of (use|service)|privacy policy|cookie policy|accept (all )?cookies|enable javascript'
        || '|sign up for our newsletter|click here to|skip to (main )?content'
        || '|alle rechte vorbehalten|datenschutzerklärung|tous droits réservés|politique de confidentialité|todos los derechos reservados|política de privacidad', 'i'))
    OR NOT regexp_matches(s, '[.!?…。！？]["''”’»)\]]*([\x20\x09-\x0D]|$)')) AS good FROM l WHERE n > 0),
k AS (SELECT r, count(*) - count(DISTINCT s) AS n_dup_lines, sum(CASE WHEN good THEN n ELSE 0 END) AS words_kept FROM judged GROUP BY r),
f AS (SELECT doc_id, CAST(coalesce(n_words, 0) AS BIGINT) AS n_words, CAST(coalesce(word_chars, 0) AS BIGINT) AS word_chars, CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
    CAST(coalesce(n_dup_lines, 0) AS BIGINT) AS n_dup_lines, CAST(coalesce(n_repeat_words, 0) AS BIGINT) AS n_repeat_words, CAST(coalesce(words_kept, 0) AS BIGINT) AS words_kept
  FROM d LEFT JOIN n USING (r) LEFT JOIN rep USING (r) LEFT JOIN k USING (r)),
b AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM f)
SELECT *, NOT base_failed AND words_kept >= 0.3 * n_words AS kept FROM b
"""

SQL: dict[str, str] = {
    "op1_minhash_near_dedup": _NEAR_SQL,
    "op4_warc_archive": _WARC_SQL,
    "op5_url_filter": _URL_SQL,
    "op6_line_quality": _QUALITY_SQL,
    "op7_mix_sources": mixing.SQL,
}
