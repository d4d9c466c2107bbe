"""Queries and DuckDB SQL of the ten operators; ``__spark_entry__`` adds them if this subpackage is there."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from waypoint.llm import decontaminate, html_text, language_model, mixing, near_dup, quality, search, secrets, suffix_dedup, toxicity
from waypoint.llm.store import table


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of repeated 400-byte strings of every document."""
    return suffix_dedup.repeated_spans(table(spark, sf_dir, "documents")).drop("starts", "ends")


def op2_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of documents whose 3-word shingle sets are alike by 85 percent or more."""
    return near_dup.near_duplicates(table(spark, sf_dir, "documents"), k=3, percent=85)


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity of every document."""
    return toxicity.scored(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten best documents for the whole text of every document whose id is divisible by 20."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return search.search(docs, docs.filter("doc_id % 20 = 0").select(F.col("doc_id").alias("query_id"), "text"), k=10)


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality of every document."""
    return quality.scored(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page."""
    return html_text.extracted(table(spark, sf_dir, "pages"))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Taken words of every document under the production weights."""
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "copies", "rate")


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents with a benchmark passage."""
    return decontaminate.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secret spans of every document."""
    return secrets.scanned(table(spark, sf_dir, "documents"))


def op10_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language-model scores of every document."""
    return language_model.scored(table(spark, sf_dir, "documents"))


QUERIES = {"op1_suffix_dedup": op1_suffix_dedup, "op2_near_dup": op2_near_dup, "op3_toxicity": op3_toxicity, "op4_search": op4_search, "op5_quality": op5_quality, "op6_html_text": op6_html_text, "op7_mixing": op7_mixing, "op8_decontaminate": op8_decontaminate, "op9_secrets": op9_secrets, "op10_language_model": op10_language_model}
NEAR_DUP_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
sh AS (
  SELECT DISTINCT doc_id, s FROM (
    SELECT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 3 THEN [array_to_string(ws, ' ')]
      ELSE list_transform(range(1, len(ws) - 1), lambda i: array_to_string(ws[i:i + 2], ' ')) END) AS s FROM w)),
n AS (SELECT d.doc_id, count(s) AS n FROM documents d LEFT JOIN sh USING (doc_id) GROUP BY d.doc_id),
i AS (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS c FROM sh a JOIN sh b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS (SELECT u, v FROM i JOIN n x ON x.doc_id = u JOIN n y ON y.doc_id = v WHERE 100 * c >= 85 * (x.n + y.n - c)),
r(doc_id, root) AS (SELECT doc_id, doc_id FROM documents UNION SELECT e.v, r.root FROM r JOIN e ON e.u = r.doc_id)
SELECT r.doc_id, any_value(n.n)::BIGINT AS n_shingles, min(root) AS component_id, r.doc_id = min(root) AS kept
FROM r JOIN n USING (doc_id) GROUP BY r.doc_id
"""
SEARCH_SQL = r"""
WITH w AS (
  SELECT doc_id, rowid_ AS id, unnest(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+')) AS t
  FROM (SELECT doc_id, text, row_number() OVER () AS rowid_ FROM documents)),
p AS (SELECT doc_id, id, t, count(*)::DOUBLE AS tf FROM w GROUP BY ALL),
len AS (SELECT id, count(*)::DOUBLE AS words FROM w GROUP BY id),
s AS (SELECT (SELECT count(*) FROM documents)::DOUBLE AS n, (SELECT count(*) FROM w)::DOUBLE / (SELECT count(*) FROM documents)::DOUBLE AS average),
idf AS (SELECT t, ln(1e0 + (any_value(n) - count(*)::DOUBLE + 5e-1) / (count(*)::DOUBLE + 5e-1)) AS idf FROM p, s GROUP BY t),
c AS (
  SELECT doc_id, id, t, floor(idf * (tf * (12e-1 + 1e0) / (tf + 12e-1 * (1e0 - 75e-2 + 75e-2 * words / average))) * 1048576e0 + 5e-1)::BIGINT AS part
  FROM p JOIN len USING (id) JOIN idf USING (t), s),
q AS (SELECT DISTINCT doc_id AS query_id, t FROM w WHERE doc_id % 20 = 0),
h AS (SELECT query_id, doc_id, id, sum(part)::BIGINT AS score FROM q JOIN c USING (t) GROUP BY ALL)
SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INTEGER AS rank, doc_id, score / 1048576e0 AS score
FROM h QUALIFY rank <= 10
"""
ORACLES: dict[str, str] = {"op2_near_dup": NEAR_DUP_SQL, "op4_search": SEARCH_SQL}
