"""Connected components of an undirected edge list, by rounds of joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of every node of edges (a, b): root is the smallest node that can be reached.

    Each round joins every node's larger neighbours to its smallest one, then its smaller
    neighbours, so a path shortens by about half; rounds end when no edge changes. Both sides
    stay distributed, each round is written to the shared folder, and the rows never exceed
    the edges of the round before. Loops and repeated edges do no harm; no edges give no rows.
    """
    now = durable(edges.select("a", "b").where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    mark = None
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        small_least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(small_least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        own = small_least.select("a", F.col("m").alias("b"))
        now = durable(small.unionByName(own).where("a <> b").distinct())
        sums = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if tuple(sums) == mark:
            break
        mark = tuple(sums)
    nodes = now.groupBy("a").agg(F.min("b").alias("root"))
    return nodes.select(F.col("a").alias("node"), "root").unionByName(nodes.select(F.col("root").alias("node"), "root").distinct())
