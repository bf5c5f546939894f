"""Queries over the training-data tables and, where SQL can say the same, their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bwt_dedup, decontaminate, fm_dedup, license_scan, line_dedup, ngram_join, packing, quality_rules, stages, suffix_lm, toxicity


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(_docs(spark, sf_dir))


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.leaks(_docs(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op3_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.join(_docs(spark, sf_dir), ngram_join.JoinSpec(n=3, percent=90))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = line_dedup.dedup(_docs(spark, sf_dir).select("doc_id", "text"))
    return done.select("doc_id", "n_lines", "n_removed", F.md5(F.coalesce("text", F.lit(""))).alias("kept_md5"))


def op5_toxicity_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score(_docs(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op6_suffix_tree_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_lm.score(_docs(spark, sf_dir))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(_docs(spark, sf_dir)).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "p_good"
    )


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_docs(spark, sf_dir))


def op9_fm_index_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fm_dedup.dedup(_docs(spark, sf_dir))


def op10_bwt_merge_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bwt_dedup.dedup(_docs(spark, sf_dir))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stages.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_license_scan, op2_decontamination, op3_ngram_jaccard_join, op4_line_dedup, op5_toxicity_crf, op6_suffix_tree_lm, op7_quality_rules, op8_packing, op9_fm_index_dedup, op10_bwt_merge_dedup, pipeline)
}

OP4_SQL = r"""
WITH line AS (
  SELECT doc_id, u.i AS pos, u.x AS line
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents) d,
       LATERAL (SELECT unnest(range(len(d.l))) AS i, unnest(d.l) AS x) u
), solid AS (
  SELECT doc_id, pos, line, row_number() OVER (PARTITION BY doc_id ORDER BY pos) AS k
  FROM line WHERE regexp_matches(line, '[^\x20\x09-\x0D]')
), win AS (
  SELECT a.doc_id, a.k, a.pos, a.line AS l1, b.line AS l2, c.line AS l3
  FROM solid a JOIN solid b ON b.doc_id = a.doc_id AND b.k = a.k + 1
               JOIN solid c ON c.doc_id = a.doc_id AND c.k = a.k + 2
), later AS (
  SELECT doc_id, k FROM (SELECT doc_id, k, row_number() OVER (PARTITION BY l1, l2, l3 ORDER BY doc_id, pos) AS r FROM win) WHERE r > 1
), gone AS (
  SELECT DISTINCT s.doc_id, s.pos FROM later JOIN solid s ON s.doc_id = later.doc_id AND s.k BETWEEN later.k AND later.k + 2
), kept AS (
  SELECT l.doc_id, string_agg(l.line, chr(10) ORDER BY l.pos) AS text
  FROM line l LEFT JOIN gone g ON g.doc_id = l.doc_id AND g.pos = l.pos WHERE g.pos IS NULL GROUP BY l.doc_id
), n AS (SELECT doc_id, count(*) AS n_lines FROM solid GROUP BY doc_id),
g AS (SELECT doc_id, count(*) AS n_removed FROM gone GROUP BY doc_id)
SELECT d.doc_id, coalesce(n.n_lines, 0)::BIGINT AS n_lines, coalesce(g.n_removed, 0)::BIGINT AS n_removed, md5(coalesce(k.text, '')) AS kept_md5
FROM documents d LEFT JOIN kept k ON k.doc_id = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN g ON g.doc_id = d.doc_id
"""

ORACLES: dict[str, str] = {"op4_line_dedup": OP4_SQL}
