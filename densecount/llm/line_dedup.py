"""Line dedup by overlapping windows of consecutive lines.

Every run of three consecutive lines is hashed (128 bits); the first place of each hash in
the whole table, by (doc_id, line), stays and every later one marks its three lines. Marked
lines go, overlapping windows being merged.

Lines are what stands between newlines; blank ones (space characters only) are in no
window and stay. A document of fewer than three lines has no window and stays whole.

Edge cases: null text counts as empty; a null doc_id can't be ordered, so such a row is in
no window and stays whole; rows that repeat a doc_id are one document to the windows and
each keep their own row; extra columns are carried by ``dedup`` unchanged.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import store

WINDOW = 3


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _blank(line: Column) -> Column:
    return ~line.rlike(r"[^\x20\x09-\x0D]")


def windows(docs: DataFrame, size: int = WINDOW) -> DataFrame:
    """doc_id, the original numbers of a window's lines, and the window's hash."""
    lines = store.documents(docs, "doc_id", "text").where("doc_id is not null").select("doc_id", _lines(F.col("text")).alias("line"))
    numbered = lines.select("doc_id", F.filter(F.transform("line", lambda x, i: F.struct(i.alias("at"), x.alias("line"))), lambda x: ~_blank(x["line"])).alias("line"))
    runs = numbered.where(F.size("line") >= size).select(
        "doc_id",
        F.explode(
            F.transform(
                F.sequence(F.lit(0), F.size("line") - size),
                lambda i: F.struct(
                    F.array(*[F.get("line", i + j)["at"] for j in range(size)]).alias("at"),
                    F.xxhash64(*[F.get("line", i + j)["line"] for j in range(size)]).alias("h1"),
                    F.xxhash64(F.lit(size), *[F.get("line", i + j)["line"] for j in reversed(range(size))]).alias("h2"),
                ),
            )
        ).alias("w"),
    )
    return runs.select("doc_id", "w.at", "w.h1", "w.h2")


def covered(docs: DataFrame, size: int = WINDOW) -> DataFrame:
    """doc_id and the sorted numbers of its lines that later windows cover."""
    found = store.settle(windows(docs, size), "lines")
    first = found.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", F.get("at", F.lit(0)).alias("at"))).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("h1", "h2", "first")
    later = found.join(first, ["h1", "h2"]).where(F.struct("doc_id", F.get("at", F.lit(0)).alias("at")) != F.col("first"))
    return later.groupBy("doc_id").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_set("at")))).alias("_gone_lines"))


def dedup(docs: DataFrame, size: int = WINDOW) -> DataFrame:
    """The documents with their covered lines removed, plus n_lines and n_removed.

    Column names of the input that clash with these two are replaced."""
    gone = covered(docs, size).withColumnRenamed("doc_id", "_gone_id")
    lines = _lines(F.col("text"))
    joined = docs.join(gone, docs["doc_id"] == gone["_gone_id"], "left").drop("_gone_id")
    # the lines as a column of their own: inlined below, they would be split once per line
    joined = joined.withColumn("_all_lines", F.when(F.spark_partition_id() < 0, None).otherwise(lines))
    lines = F.col("_all_lines")
    stay = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), "_gone_lines")  # by hashing
    kept = F.concat_ws("\n", F.transform(stay, lambda i: F.get(lines, i)))
    return joined.withColumns(
        {
            "n_lines": F.size(F.filter(lines, lambda x: ~_blank(x))).cast("long"),
            "n_removed": F.coalesce(F.size("_gone_lines"), F.lit(0)).cast("long"),
            "text": F.when(F.col("_gone_lines").isNull(), F.col("text")).otherwise(kept),
        }
    ).drop("_gone_lines", "_all_lines")
