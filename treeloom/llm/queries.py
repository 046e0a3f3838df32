"""Queries of the training-data operators with their production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treeloom.llm.bpe import encode_documents
from treeloom.llm.language import fit, identify
from treeloom.llm.lines import drop_recurring_lines
from treeloom.llm.mixing import mix_index
from treeloom.llm.near import near_duplicates
from treeloom.llm.quality import judge_quality
from treeloom.llm.repeats import remove_repeats
from treeloom.llm.sharding import shard_digest
from treeloom.llm.topk import exact_top_k
from treeloom.llm.urls import judge_urls

#: Host, path prefix and verdict of the URL rules (fixed values).
URL_RULES = [
    ("com", "/", "allow"),
    ("example.com", "/en/", "block"),
    ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"),
    ("net", "/fr/", "block"),
]
VOCABULARY = public_tokenizers.path("word_bpe_49k.json")
#: No source is read more than twice as often as another.
MIX_REPETITION = 2.0


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_line_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = drop_recurring_lines(_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return kept.select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op2_hypergeometric_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_digest(_table(spark, sf_dir, "documents"))


def op3_quality_cascade(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_quality(_table(spark, sf_dir, "documents"))


def op4_temperature_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_index(_table(spark, sf_dir, "documents"), max_repetition=MIX_REPETITION)


def op5_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = _table(spark, sf_dir, "embeddings")
    return exact_top_k(vectors, vectors.filter(F.col("vec_id") % 100 == 0)).drop("query_no")


def op6_rank_array_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(_table(spark, sf_dir, "documents"), VOCABULARY)


def op7_url_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(_table(spark, sf_dir, "pages"), URL_RULES)


def op8_language_viterbi(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text", "lang", (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2).alias("held_out"))
    docs = docs.withColumn("held_out", F.coalesce("held_out", F.lit(False)))
    model = fit(docs.filter("not held_out and doc_id is not null"))
    return identify(docs.select("doc_id", "held_out", "text"), model).select("doc_id", "held_out", "lang_pred", "score", F.size("spans").cast("long").alias("n_spans"))


def op9_suffix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(_table(spark, sf_dir, "documents")).drop("kept")


def op10_hyperminhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(_table(spark, sf_dir, "documents"), k=2)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_line_templates, op2_hypergeometric_shards, op3_quality_cascade, op4_temperature_mix, op5_exact_topk, op6_rank_array_bpe, op7_url_digests, op8_language_viterbi, op9_suffix_repeats, op10_hyperminhash)}


_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

_BLANK = r"\x20\x09-\x0D"

ORACLE_SQL = {
    "op1_line_templates": rf"""
WITH d AS (SELECT doc_id, text, string_split(text, chr(10)) AS lines FROM documents),
l AS (SELECT doc_id, unnest(range(1, len(lines) + 1)) AS i, unnest(lines) AS raw FROM d),
n AS (SELECT doc_id, i, trim(regexp_replace(regexp_replace(raw, '[^{_BLANK}]*[0-9][^{_BLANK}]*', '<*>', 'g'), '[{_BLANK}]+', ' ', 'g')) AS s FROM l),
t AS (SELECT doc_id, i, s, string_split(s, ' ') AS w FROM n WHERE s <> ''),
c AS (SELECT *, len(w) AS n, least(3, greatest(1, len(w) // 3)) AS lead FROM t),
m AS (SELECT *, n - lead AS rest, least(6, n - lead) AS parts, array_to_string(w[1:lead], ' ') AS leaf FROM c),
p AS (SELECT x, y FROM (SELECT unnest(range(6)) AS x), (SELECT unnest(range(6)) AS y)),
v AS (
  SELECT doc_id, i, 'line' AS kind, s AS t FROM m
  UNION ALL SELECT doc_id, i, x || ' ' || y, n || '|' || array_to_string(list_transform(w, lambda a, q: CASE WHEN q > lead AND ((q - 1 - lead) * parts // rest) IN (x, y) THEN '<*>' ELSE a END), ' ')
    FROM m JOIN p ON n >= 4 AND x < parts AND (CASE WHEN n >= 12 THEN x < y ELSE x = y END)),
r AS (SELECT kind, t, min(doc_id) AS keeper FROM v GROUP BY kind, t HAVING count(DISTINCT doc_id) >= 5),
g AS (SELECT DISTINCT doc_id, i FROM v JOIN r USING (kind, t) WHERE doc_id <> keeper),
k AS (
  SELECT l.doc_id, count(g.i)::BIGINT AS n_dropped, count(*)::BIGINT AS n_lines,
    coalesce(string_agg(l.raw, chr(10) ORDER BY l.i) FILTER (WHERE g.i IS NULL), '') AS kept
  FROM l LEFT JOIN g ON l.doc_id = g.doc_id AND l.i = g.i GROUP BY l.doc_id)
SELECT d.doc_id, coalesce(n_lines, 0)::BIGINT AS n_lines, coalesce(n_dropped, 0)::BIGINT AS n_dropped, sha256(coalesce(kept, '')) AS kept_sha256
FROM d LEFT JOIN k ON d.doc_id = k.doc_id""",
    "op3_quality_cascade": rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, {_WORDS} AS w FROM documents),
b AS (
  SELECT doc_id, t, w, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
    length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
    length(regexp_replace(t, '[^!?]', '', 'g'))::BIGINT AS n_marks,
    list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines,
    len(list_filter(w, lambda x: NOT regexp_matches(x, '[A-Za-z]|[^\x00-\x7F]')))::BIGINT AS n_letterless
  FROM d),
g AS (SELECT doc_id, i, w[i] || chr(32) || w[i + 1] || chr(32) || w[i + 2] AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) >= 3)),
r AS (SELECT doc_id, i FROM g QUALIFY count(*) OVER (PARTITION BY doc_id, g) > 1),
c AS (SELECT doc_id, count(DISTINCT i + k)::BIGINT AS n FROM r, (SELECT unnest([0, 1, 2]) AS k) GROUP BY doc_id),
m AS (
  SELECT b.doc_id, n_words, word_chars, n_symbols, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
    coalesce(c.n, 0)::BIGINT AS n_repeat_words, len(lines) AS n_lines, n_marks, n_letterless
  FROM b LEFT JOIN c ON b.doc_id = c.doc_id),
f AS (SELECT *, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  (NOT base_failed AND NOT (10 * n_symbols > n_words OR word_chars < 3 * n_words OR word_chars > 12 * n_words
    OR 10 * n_marks > 3 * n_words OR 10 * n_dup_lines > 3 * n_lines OR 10 * n_letterless > 3 * n_words)) AS kept
FROM f""",
    "op5_exact_topk": """
WITH v AS MATERIALIZED (SELECT row_number() OVER () AS no, vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.no, q.vec_id AS query_id, c.vec_id, list_dot_product(q.e, c.e)::BIGINT AS score
  FROM v q JOIN v c ON q.no <> c.no AND len(q.e) = len(c.e) WHERE q.vec_id % 100 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY no ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10""",
    "op7_url_digests": r"""
WITH p AS (
  SELECT page_id, CASE WHEN strpos(coalesce(url, ''), '://') = 0 THEN '' ELSE substr(url, strpos(url, '://') + 3) END AS rest FROM pages),
h AS (
  SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(substr(rest, length(regexp_extract(rest, '^[^/?#]*')) + 1), '^[^?#]*') AS path FROM p),
r AS (
  SELECT *, CASE
    WHEN (host = 'www.example.com' OR host LIKE '%.www.example.com') AND path LIKE '/en/%' THEN 'www.example.com/en/'
    WHEN (host = 'example.com' OR host LIKE '%.example.com') AND path LIKE '/en/%' THEN 'example.com/en/'
    WHEN (host = 'net' OR host LIKE '%.net') AND path LIKE '/es/%' THEN 'net/es/'
    WHEN (host = 'net' OR host LIKE '%.net') AND path LIKE '/fr/%' THEN 'net/fr/'
    WHEN (host = 'com' OR host LIKE '%.com') AND path LIKE '/%' THEN 'com/' END AS rule FROM h)
SELECT page_id, host, path, rule, CASE WHEN rule IN ('example.com/en/', 'net/es/', 'net/fr/') THEN 'block' ELSE 'allow' END AS verdict FROM r""",
}


def oracle_sql() -> dict[str, str]:
    return dict(ORACLE_SQL)
