"""From raw documents to packed training sequences.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before it kept; the
result of each is written as Parquet and read again before the next. ``run`` returns the
packed pieces of the documents that are left.

Edge cases: a stage keeps the columns of documents only, so others, whatever their names, are
dropped; null texts count as empty; an empty table gives an empty result. Rows with a null id
are judged, cleaned and packed but are nobody's copy; rows that repeat an id share its fate.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, line_dedup, ngram_join, packing, quality_rules, store

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules reject go. Rows with a null id are judged alike."""
    verdict = quality_rules.judge(docs).groupBy("doc_id").agg(F.bool_and("kept").alias("kept")).where("kept").select(F.col("doc_id").alias("_id"))
    return docs.join(verdict, docs["doc_id"].eqNullSafe(verdict["_id"]), "left_semi").select(*COLUMNS)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of three-line windows go; ``n_chars`` follows the text that is left."""
    return line_dedup.dedup(docs.select(*COLUMNS)).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents joined by five-word shingle sets of similarity 0.8 or more, one stays."""
    return ngram_join.one_of_each(docs, ngram_join.JoinSpec(n=5, percent=80)).select(*COLUMNS)


def leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select(*COLUMNS)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document's pieces and their places in sequences of 1024 tokens."""
    return packing.pack(docs)


STAGES = [("quality", quality), ("lines", lines), ("near_copies", near_copies), ("leaks", leaks), ("pack", pack)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = store.settle(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)


#: Expectation-maximisation, alignment and least squares have no SQL; tests/llm checks them.
ORACLE_SQL = None
