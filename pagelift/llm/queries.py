"""Queries of the corpus operators over the whole given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.llm import decontaminate, licenses, line_dedup, lm_score, ngram_join, packing, quality, substring, token_spans, topk
from pagelift.llm.common import table
from pagelift.session import ship

Query = Callable[[SparkSession, str], DataFrame]


def op1_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return lm_score.score(spark, table(spark, sf_dir, "documents"), lm_score.held_out_column(), order=2)


def op2_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return quality.score(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), max_rows=20_000)


def op3_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.overlaps(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return ngram_join.near_duplicates(spark, table(spark, sf_dir, "documents"), n=3, percent=90)


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    ship(spark)
    return token_spans.by_section(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op6_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return topk.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0, k=20)


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    docs = table(spark, sf_dir, "documents")
    return licenses.scan(spark, docs.withColumn("path", licenses.tree_path(F.col("doc_id"))))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return line_dedup.dedup(spark, table(spark, sf_dir, "documents"), least=10, min_chars=1, digest=True)


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return packing.pack_documents(spark, table(spark, sf_dir, "documents"), capacity=2048)


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return substring.remove_repeats(table(spark, sf_dir, "documents"), window=20, digest=True)


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in (op1_lm_scoring, op2_quality_classifier, op3_benchmark_decontamination, op4_ngram_jaccard_join, op5_token_counts, op6_exact_top_k, op7_license_scan, op8_line_dedup, op9_best_fit_packing, op10_substring_dedup)}


OP3_SQL = r"""
WITH doc_words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM documents
), items AS (
  SELECT min(item_id) AS item_id, w FROM (SELECT item_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM benchmark) WHERE len(w) > 0 GROUP BY w
), d AS (
  SELECT doc_id, len(w) AS doc_words, unnest(range(len(w))) AS i, unnest(w) AS word FROM doc_words
), b AS (
  SELECT item_id, len(w) AS n, unnest(range(len(w))) AS p, unnest(w) AS word FROM items
), agree AS (
  SELECT doc_id, item_id, i - p AS shift, doc_words, n, p FROM d JOIN b USING (word)
), diagonal AS (
  SELECT doc_id, item_id, shift, any_value(doc_words) AS doc_words, any_value(n) AS n, count(*) AS c, list_sort(list(p)) AS spots
  FROM agree GROUP BY ALL HAVING 1000 * count(*) >= 800 * least(any_value(n), 10)
), region AS (
  SELECT doc_id, item_id, shift, n, c AS matched, 0 AS lead, n AS length FROM diagonal WHERE shift >= 0 AND shift + n <= doc_words AND 1000 * c >= 800 * n
  UNION ALL
  SELECT doc_id, item_id, shift, n, j - i + 1, spots[i], spots[j] - spots[i] + 1
  FROM (SELECT *, unnest(range(1, c + 1)) AS i FROM diagonal WHERE NOT (shift >= 0 AND shift + n <= doc_words AND 1000 * c >= 800 * n)), LATERAL (SELECT unnest(range(i, c + 1)) AS j)
  WHERE 1000 * (j - i + 1) >= 800 * (spots[j] - spots[i] + 1) AND (spots[j] - spots[i] + 1 >= 10 OR (spots[i] = 0 AND spots[j] = n - 1))
), best AS (
  SELECT doc_id, item_id, max((matched, -(shift + lead), length, n)) AS m
  FROM (SELECT * FROM region QUALIFY row_number() OVER (PARTITION BY doc_id, item_id, shift ORDER BY matched DESC, lead, length DESC) = 1) GROUP BY 1, 2
)
SELECT doc_id, item_id, CAST(-m[2] AS BIGINT) AS start, CAST(m[3] AS BIGINT) AS length, CAST(m[1] AS BIGINT) AS matched, CAST(m[4] AS BIGINT) AS item_words FROM best
"""

OP4_SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents
), sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
    ELSE list_distinct(list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i:i + 2], ' '))) END AS s FROM words
), classed AS (
  SELECT doc_id, len(s) AS n, s, CASE WHEN len(s) = 0 THEN doc_id ELSE min(doc_id) OVER (PARTITION BY md5(array_to_string(list_sort(s), chr(10)))) END AS class_id FROM sets
), grams AS (
  SELECT doc_id, n, unnest(s) AS g FROM classed WHERE doc_id = class_id
), counted AS (
  SELECT a.doc_id AS x, b.doc_id AS y, any_value(a.n) AS nx, any_value(b.n) AS ny, count(*) AS c FROM grams a JOIN grams b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2
), links AS (
  SELECT x, y FROM counted WHERE 100 * c >= 90 * (nx + ny - c)
), both_ways AS (
  SELECT x, y FROM links UNION ALL SELECT y, x FROM links
), reach AS (
  SELECT class_id AS a, class_id AS b FROM classed UNION SELECT r.a, e.y FROM reach r JOIN both_ways e ON e.x = r.b
), component AS (
  SELECT a, min(b) AS component_id FROM reach GROUP BY a
), degree AS (
  SELECT x, count(*) AS n FROM both_ways GROUP BY x
)
SELECT c.doc_id, CAST(c.n AS BIGINT) AS n_shingles, c.class_id, CAST(coalesce(d.n, 0) AS BIGINT) AS n_links, k.component_id
FROM classed c JOIN component k ON k.a = c.class_id LEFT JOIN degree d ON d.x = c.class_id
"""

OP6_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS q FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT a.vec_id AS query_id, b.vec_id, CAST(list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v a JOIN v b ON a.vec_id % 20 = 0 AND a.vec_id <> b.vec_id
), ranked AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM scored
)
SELECT * FROM ranked WHERE rank <= 20
"""

OP8_SQL = r"""
WITH lines AS (
  SELECT doc_id, unnest(range(1, len(l) + 1)) AS i, unnest(l) AS line
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents)
), keyed AS (
  SELECT doc_id, i, line, translate(regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines
), hot AS (
  SELECT k FROM keyed WHERE length(k) >= 1 GROUP BY k HAVING count(DISTINCT doc_id) >= 10
)
SELECT doc_id, CAST(count(*) AS BIGINT) AS n_lines, CAST(count(h.k) AS BIGINT) AS n_dropped,
  sha256(coalesce(string_agg(CASE WHEN h.k IS NULL THEN line END, chr(10) ORDER BY i), '')) AS kept_sha256
FROM keyed LEFT JOIN hot h USING (k) GROUP BY doc_id
"""

OP10_SQL = r"""
WITH words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents
), starts AS (
  SELECT doc_id, unnest(range(1, len(w) - 18)) AS s, w FROM words WHERE len(w) >= 20
), hashed AS (
  SELECT doc_id, s, md5(array_to_string(w[s:s + 19], ' ')) AS h FROM starts
), ranked AS (
  SELECT doc_id, s, row_number() OVER (PARTITION BY h ORDER BY doc_id, s) AS k FROM hashed
), gone AS (
  SELECT DISTINCT doc_id, unnest(range(s, s + 20)) AS i FROM ranked WHERE k > 1
), places AS (
  SELECT doc_id, unnest(range(1, len(w) + 1)) AS i, unnest(w) AS word FROM words
), kept AS (
  SELECT p.doc_id, string_agg(p.word, ' ' ORDER BY p.i) AS t, count(*) AS n
  FROM places p LEFT JOIN gone g ON g.doc_id = p.doc_id AND g.i = p.i WHERE g.i IS NULL GROUP BY p.doc_id
)
SELECT w.doc_id, CAST(len(w.w) AS BIGINT) AS n_words, CAST(len(w.w) - coalesce(k.n, 0) AS BIGINT) AS n_removed,
  sha256(coalesce(k.t, '')) AS kept_sha256
FROM words w LEFT JOIN kept k ON k.doc_id = w.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_benchmark_decontamination": OP3_SQL, "op4_ngram_jaccard_join": OP4_SQL, "op6_exact_top_k": OP6_SQL, "op8_line_dedup": OP8_SQL, "op10_substring_dedup": OP10_SQL}
