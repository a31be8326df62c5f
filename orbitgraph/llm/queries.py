"""The thin registered queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, html, linededup, lm, neardup, packing, quality, substring, toxicity, warc
from .common import spread


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    scan = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return spread(scan) if name in ("documents", "pages") else scan


def op1_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    held_out = F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8")) % 7 == 2
    return lm.score_documents(table(spark, sf_dir, "documents").select("doc_id", "text"), held_out)


def op2_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"), width=5, percent=85)


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents").select("doc_id", "text"), window=2048)


def op4_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(table(spark, sf_dir, "pages").select("page_id", "url", "html"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    fold = lambda c: F.crc32(F.encode(c.cast("string"), "UTF-8")) % 3
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = toxicity.toxicity(docs, table(spark, sf_dir, "labels"), learn=lambda c: fold(c) != 1)
    return scored.select("doc_id", F.coalesce(fold(F.col("doc_id")) == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = substring.remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"), width=20)
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.encode("kept_text", "UTF-8"), 256).alias("kept_sha256"))


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = linededup.drop_lines(docs)
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.encode("kept_text", "UTF-8"), 256).alias("kept_sha256"))


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    q = quality.quality_rules(docs, columns=["doc_id"])
    return q.select("doc_id", *(F.col(f"quality.{c}").alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "char_distance", "word_distance", "base_failed", "kept")))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return warc.read_warc(warc.convert(warc.write_arc(pages))).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return decontam.contamination(docs, table(spark, sf_dir, "benchmark"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if name.startswith("op") and callable(f)}


def quality_sql() -> str:
    """DuckDB's version of the quality rules, from the same fixed values."""
    q = quality
    langs = ", ".join(f"('{c}', [{', '.join(repr(w) for w in words)}])" for c, words in q.COMMON_WORDS.items())
    counts = ", ".join("length(text) - length(regexp_replace(text, '{}', '', 'g'))".format(p.replace("'", "''")) for p in ("[a-z]", "[A-Z]", "[0-9]", r"[\x20\x09-\x0D]", "[.,;:!?'\"()\\-]", "[#*$%&|<>]"))
    js = lambda a, b: f"sqrt(greatest(list_sum(list_transform(range(1, len({a}) + 1), lambda i: (CASE WHEN {a}[i] > 0 THEN {a}[i]*log2({a}[i]/(({a}[i]+{b}[i])/2)) ELSE 0 END + CASE WHEN {b}[i] > 0 THEN {b}[i]*log2({b}[i]/(({a}[i]+{b}[i])/2)) ELSE 0 END)/2)), 0))"
    mean = lambda c, k: "[" + ", ".join(f"round(sum({c}[{i}])/count(*), 9)" for i in range(1, k + 1)) + "]"
    return rf"""
WITH listed(code, commons) AS (VALUES {langs}),
t AS (SELECT doc_id, coalesce(text, '') AS text, coalesce(code, '*') AS lang, coalesce(commons, [{', '.join(repr(w) for w in q.COMMON_WORDS['en'])}]) AS commons FROM documents LEFT JOIN listed ON code = lower(lang)),
w AS (SELECT *, list_filter(string_split_regex(text, '[ 	-
]+'), lambda x: x <> '') AS w, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^ 	-
]')) AS l, [{counts}] AS c FROM t),
f AS (SELECT *, len(w) AS n, length(text) AS m FROM w),
h AS (SELECT doc_id, lang, n, m - c[4] AS word_chars, c[6] AS n_symbols, len(l) - len(list_distinct(l)) AS n_dup_lines,
  list_transform(list_append(c, m - list_sum(c)), lambda x: CASE WHEN m > 0 THEN x/m ELSE 0 END) AS p,
  list_transform(commons, lambda k: len(list_filter(w, lambda x: x = k))/greatest(n, 1)) AS r FROM f),
s AS (SELECT *, list_append(r, (1 - list_sum(r))) AS v FROM h),
tri AS (SELECT doc_id, i, w[i] || chr(32) || w[i+1] || chr(32) || w[i+2] AS x FROM f, LATERAL (SELECT unnest(range(1, n - 1)) AS i)),
rep AS (SELECT doc_id, count(DISTINCT i + k) AS n_repeat FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, x) AS c FROM tri) z, (SELECT unnest(range(3)) AS k) WHERE c > 1 GROUP BY doc_id),
refs AS (SELECT lang AS ref, {mean('p', 7)} AS rp, {mean('v', 9)} AS rv FROM s WHERE n >= {q.GUARD_WORDS} AND lang <> '*' GROUP BY lang UNION ALL SELECT '*', {mean('p', 7)}, {mean('v', 9)} FROM s WHERE n >= {q.GUARD_WORDS}),
d AS (SELECT s.*, coalesce(n_repeat, 0) AS n_repeat_words,
  round(CASE WHEN n < {q.GUARD_WORDS} THEN 0 ELSE {js('p', 'rp')} END, 6) AS cd, round(CASE WHEN n < {q.GUARD_JOINT} OR lang = '*' THEN 0 ELSE {js('v', 'rv')} END, 6) AS wd FROM s LEFT JOIN rep USING (doc_id) JOIN refs ON ref = lang)
SELECT doc_id, n AS n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, cd AS char_distance, wd AS word_distance,
  n < {q.GUARD_WORDS} OR 100*n_repeat_words > 50*n AS base_failed,
  NOT (n < {q.GUARD_WORDS} OR 100*n_repeat_words > 50*n) AND cd <= {q.MAX_CHAR_DISTANCE} AND (wd = 0 OR cd*cd + wd*wd <= {q.MAX_JOINT_DISTANCE**2}) AS kept FROM d
"""


ORACLES: dict[str, str] = {
    "op7_line_dedup": r"""
WITH lines AS (
  SELECT doc_id, generate_subscripts(l, 1) AS pos, unnest(l) AS line
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents)
), keyed AS (
  SELECT *, translate(regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM lines
), repeated AS (
  SELECT key, max(doc_id) AS keeper FROM keyed WHERE length(key) >= 40 GROUP BY key HAVING count(DISTINCT doc_id) >= 5
), marked AS (
  SELECT doc_id, pos, line, keeper IS NOT NULL AND keeper <> doc_id AS gone FROM keyed LEFT JOIN repeated USING (key)
)
SELECT doc_id, count(*) AS n_lines, CAST(sum(CASE WHEN gone THEN 1 ELSE 0 END) AS BIGINT) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
""",
    "op2_near_duplicates": r"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents
), shingles AS MATERIALIZED (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 5 THEN list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' ')) WHEN len(w) > 0 THEN [array_to_string(w, ' ') || chr(10)] ELSE [] END) AS s FROM words
), sizes AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id
), links AS MATERIALIZED (
  SELECT a, b FROM (SELECT p.doc_id AS a, q.doc_id AS b, count(*) AS k FROM shingles p JOIN shingles q USING (s) WHERE p.doc_id <> q.doc_id GROUP BY ALL)
  JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b WHERE 100 * k >= 85 * (x.n + y.n - k)
), reach AS (SELECT doc_id AS d, doc_id AS r FROM documents UNION SELECT reach.d, links.b FROM reach JOIN links ON links.a = reach.r)
SELECT doc_id, coalesce(n, 0) AS n_shingles, component_id, doc_id = component_id AS kept
FROM (SELECT d AS doc_id, min(r) AS component_id FROM reach GROUP BY d) LEFT JOIN sizes USING (doc_id)
""",
    "op6_substring_dedup": r"""
WITH words AS (
  SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents
), windows AS (
  SELECT doc_id, i, md5(array_to_string(w[i:i+19], ' ')) AS h FROM words, LATERAL (SELECT unnest(range(1, len(w) - 18)) AS i)
), later AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY h ORDER BY doc_id, i) AS k FROM windows) WHERE k > 1
), gone AS (SELECT DISTINCT doc_id, i + k AS i FROM later, (SELECT unnest(range(20)) AS k)
), placed AS (SELECT doc_id, i, w[i] AS word FROM words, LATERAL (SELECT unnest(range(1, len(w) + 1)) AS i)
), kept AS (
  SELECT p.doc_id, count(*) AS n_words, count(g.i) AS n_removed, string_agg(word, ' ' ORDER BY p.i) FILTER (WHERE g.i IS NULL) AS t
  FROM placed p LEFT JOIN gone g ON g.doc_id = p.doc_id AND g.i = p.i GROUP BY p.doc_id
)
SELECT d.doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM documents d LEFT JOIN kept USING (doc_id)
""",
    "op9_warc": r"""
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS b, sha1(encode(coalesce(html, ''))) AS hex FROM pages
), g AS (SELECT page_id, octet_length(b) AS n, max(page_id) OVER (PARTITION BY hex) AS first, list_transform(range(8), lambda k: CAST('0x' || substr(hex, CAST(5*k+1 AS BIGINT), 5) AS BIGINT)) AS five FROM p)
SELECT page_id, n AS payload_bytes,
  array_to_string(list_transform(five, lambda v: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (v >> 15) % 32 + 1, 1) || substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (v >> 10) % 32 + 1, 1) || substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (v >> 5) % 32 + 1, 1) || substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', v % 32 + 1, 1)), '') AS payload_digest,
  CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> first THEN first END AS refers_to
FROM g
""",
    "op8_quality_rules": quality_sql(),
}
