"""Connected components of a graph too large for one machine: alternating large-star and small-star rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from .common import discard, materialise


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a != b")
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    joined = down.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a != b")
    return joined.union(least.select("a", F.col("m").alias("b")))


def connected_components(edges: DataFrame) -> DataFrame:
    """edges(a, b) of orderable ids -> (node, root): every node of an edge with the least node of its component.

    Each round is a table in the shared folder; only a count and a checksum reach the driver. Loops and repeated edges do
    no harm, null ends are dropped, no edges give no rows. The rounds grow with the logarithm of a component's width.
    """
    now = materialise(edges.select("a", "b").filter("a IS NOT NULL AND b IS NOT NULL AND a != b").dropDuplicates(), "edges")
    seen = None
    while True:
        large = _large_star(now).filter("a != b").dropDuplicates()
        after = materialise(_small_star(large).dropDuplicates(), "edges")
        discard(now)
        now = after
        state = tuple(now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)"))).first())
        if state == seen:
            break
        seen = state
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("root")).dropDuplicates()
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(roots)
