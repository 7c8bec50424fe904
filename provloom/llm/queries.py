"""The operators applied to whole tables, and the SQL of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provloom.llm import decontaminate, html_extract, jaccard_join, kneser_ney, licenses, line_dedup, packing, quality_rules, suffix_dedup, token_shards
from provloom.llm.common import read


def op1_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract(read(spark, sf_dir, "pages"))


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(read(spark, sf_dir, "documents"))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = line_dedup.dedup(read(spark, sf_dir, "documents").select("doc_id", "text"))
    return d.select("doc_id", F.col("__n_removed").alias("n_removed"), "text")


def op4_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.join(read(spark, sf_dir, "documents"), n=3, percent=90)


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.dedup(read(spark, sf_dir, "documents"), 50).drop("kept")


def op6_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_shards.read_digest(token_shards.write_shards(read(spark, sf_dir, "documents")))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = quality_rules.judge(read(spark, sf_dir, "documents"))
    return d.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.col("removed_words").cast("long").alias("removed_words"))


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.scan(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark")).drop("spans")


def op9_kneser_ney(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kneser_ney.score(read(spark, sf_dir, "documents"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(read(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    f.__name__: f
    for f in (op1_html_extraction, op2_license_scan, op3_line_dedup, op4_ngram_jaccard_join, op5_suffix_dedup, op6_token_shards, op7_quality_rules, op8_decontamination, op9_kneser_ney, op10_packing, pipeline)
}

_WS = "[ \\x09-\\x0D]+"
_AZ = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

OP4 = f"""
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(regexp_split_to_array({_AZ}, '{_WS}'), lambda x: x <> '') AS ws FROM documents),
g AS (
  SELECT doc_id, list_distinct(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 3 THEN [array_to_string(ws, ' ')]
         ELSE list_transform(range(1, len(ws) - 1), lambda i: ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2]) END) AS gs FROM w),
u AS (SELECT doc_id, len(gs) AS n, unnest(gs) AS x FROM g),
o AS (SELECT a.doc_id AS p, b.doc_id AS q, a.n AS np, b.n AS nq, count(*) AS c FROM u a JOIN u b ON a.x = b.x AND a.doc_id < b.doc_id
      AND 100 * least(a.n, b.n) >= 90 * greatest(a.n, b.n) GROUP BY ALL),
e AS (SELECT p, q FROM o WHERE 100 * c >= 90 * (np + nq - c)),
s AS (SELECT p, q FROM e UNION ALL SELECT q, p FROM e),
r AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, s.q FROM r JOIN s ON r.b = s.p)
SELECT g.doc_id, len(g.gs)::BIGINT AS n_shingles, m.component_id FROM g JOIN (SELECT a, min(b) AS component_id FROM r GROUP BY a) m ON g.doc_id = m.a
"""

OP8 = f"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array({_AZ}, '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'), lambda x: x <> '') AS ws FROM documents),
b AS (SELECT item_id, list_filter(regexp_split_to_array({_AZ}, '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'), lambda x: x <> '') AS ws FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(len(ws), 13) AS n, array_to_string(ws[i : i + least(len(ws), 13) - 1], ' ') AS x
       FROM b, unnest(range(1, greatest(len(ws) - 11, 2))) AS t(i) WHERE len(ws) > 0),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, n, i, array_to_string(ws[i : i + n - 1], ' ') AS x FROM d, sizes, unnest(range(1, len(ws) - n + 2)) AS t(i)),
hit AS (SELECT dw.doc_id, dw.i, bw.n, bw.item_id FROM dw JOIN bw ON dw.n = bw.n AND dw.x = bw.x),
marked AS (SELECT doc_id, count(DISTINCT j) AS n_hit FROM hit, unnest(range(i, i + n)) AS t(j) GROUP BY doc_id),
named AS (SELECT doc_id, count(*) AS n_items, string_agg(k, ',' ORDER BY k) AS ks FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS k FROM hit) GROUP BY doc_id)
SELECT d.doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(ks, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated
FROM d LEFT JOIN marked USING (doc_id) LEFT JOIN named USING (doc_id)
"""

ORACLE_SQL = {"op4_ngram_jaccard_join": OP4, "op8_decontamination": OP8}
