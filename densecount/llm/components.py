"""Connected components of a link table by alternating star steps.

Each step replaces links by links to the least neighbour, once for larger neighbours and
once for smaller ones; the least id of a component reaches all its members in a number of
steps that grows with the logarithm of the component's size. All of it is joins and
partial aggregates on (id, id) rows; links never leave the cluster.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import store


def _to_least(pairs: DataFrame, larger: bool) -> DataFrame:
    """Link each neighbour of a node (the larger ones, or the node and its smaller ones)
    to the node's least neighbour."""
    if larger:
        both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        out = both.join(least, "a").where("b > a").select(F.col("b").alias("x"), "m")
    else:
        down = pairs.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        least = down.groupBy("a").agg(F.min("b").alias("m"))
        out = down.join(least, "a").select(F.col("b").alias("x"), "m").unionByName(least.select(F.col("a").alias("x"), "m"))
    return out.where("x <> m").select(F.col("x").alias("a"), F.col("m").alias("b")).distinct()


def components(links: DataFrame) -> DataFrame:
    """(node, least) for every node of ``links`` (columns a, b): the least id it reaches."""
    pairs = store.settle(links.select("a", "b").where("a <> b").distinct(), "links")
    mark = None
    while True:  # each step that changes anything makes some node's least neighbour smaller, so this ends
        before, pairs = pairs, store.settle(_to_least(_to_least(pairs, True), False), "links")
        store.drop(before)
        now = pairs.agg(F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("a", "b")).alias("x")).first()
        if mark == now:
            break
        mark = now
    stars = pairs.groupBy("a").agg(F.min("b").alias("least"))
    return stars.select(F.col("a").alias("node"), "least").unionByName(stars.select(F.col("least").alias("node"), "least").distinct())
