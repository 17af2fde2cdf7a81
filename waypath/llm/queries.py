"""The contract queries of the ten operators and the pipeline's SQL where there is any."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import embed_dedup, html_extract, id_output, mixing, packing, quality, simhash, token_counts, toxicity, winnowing
from .common import ship, table


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    docs = table(spark, sf_dir, "documents")
    return toxicity.scored(docs, toxicity.trained(docs, table(spark, sf_dir, "labels")))


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return packing.pack(table(spark, sf_dir, "documents"))


def op3_winnowing(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return winnowing.edited_fingerprints(table(spark, sf_dir, "documents"))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return token_counts.token_counts(table(spark, sf_dir, "documents"))


def op5_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return html_extract.main_text(table(spark, sf_dir, "pages"))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    docs = table(spark, sf_dir, "documents")
    return quality.scored(docs, quality.trained(docs, table(spark, sf_dir, "labels")))


def op7_id_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return id_output.id_report(table(spark, sf_dir, "documents"))


def op8_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return embed_dedup.near_vectors(table(spark, sf_dir, "embeddings"))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_report(table(spark, sf_dir, "documents"))


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def queries():
    return {f.__name__: f for f in (op1_toxicity, op2_packing, op3_winnowing, op4_token_counts, op5_html_extraction, op6_quality, op7_id_output, op8_embedding_dedup, op9_mixing, op10_simhash)}


OP8_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, embedding::DOUBLE[] AS e,
         (label IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
          AND len([x FOR x IN embedding IF x IS NULL OR NOT isfinite(x)]) = 0
          AND len([x FOR x IN embedding IF x <> 0]) > 0) AS ok
  FROM embeddings),
g AS (SELECT * FROM v WHERE ok),
l AS (SELECT a.vec_id AS u, b.vec_id AS w FROM g a JOIN g b
      ON a.label = b.label AND len(a.e) = len(b.e) AND a.vec_id <> b.vec_id AND list_cosine_similarity(a.e, b.e) >= 0.93),
r(u, c) AS (SELECT vec_id, vec_id FROM v UNION SELECT l.w, r.c FROM r JOIN l ON l.u = r.u)
SELECT v.vec_id, (SELECT count(*) FROM l WHERE l.u = v.vec_id) AS n_links, min(r.c) AS component_id, v.vec_id = min(r.c) AS kept
FROM v JOIN r ON r.u = v.vec_id GROUP BY v.vec_id
"""

OP9_SQL = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, [5.0::DOUBLE, 2.0::DOUBLE, 1.0::DOUBLE][(row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3 + 1] AS wt FROM s),
o AS (SELECT *, source_size * 2.0::DOUBLE AS cap, row_number() OVER (ORDER BY source_size * 2.0::DOUBLE / wt, source IS NULL, source) AS k FROM w),
p AS (SELECT *, coalesce(sum(cap) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS used,
             sum(wt) OVER () - coalesce(sum(wt) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS rest,
             sum(source_size) OVER () * 1.5::DOUBLE AS total FROM o),
f AS (SELECT *, (total - used) / rest AS level FROM p),
c AS (SELECT min(k) AS k0, min_by(level, k) AS level0 FROM f WHERE level * wt <= cap),
t AS (SELECT source, source_size, CASE WHEN c.k0 IS NULL OR f.k < c.k0 THEN f.cap ELSE c.level0 * f.wt END AS target,
             ('0x' || substr(md5('7:' || coalesce('s' || source, 'null')), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS u FROM f, c),
n AS (SELECT d.doc_id, d.size, t.source_size, t.target, t.u, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0 END AS rate,
             (row_number() OVER (PARTITION BY d.source ORDER BY floor(log2(d.size + 1.0::DOUBLE) * 4),
                ('0x' || substr(md5(coalesce(d.doc_id::VARCHAR, 'null')), 1, 8))::BIGINT, d.doc_id NULLS LAST, d.size) - 1)::DOUBLE AS r
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target, ((floor((r + 1.0) * rate + u) - floor(r * rate + u)) * size)::BIGINT AS taken FROM n
"""


def oracle_sql() -> dict[str, str]:
    return {"op8_embedding_dedup": OP8_SQL, "op9_mixing": OP9_SQL}
