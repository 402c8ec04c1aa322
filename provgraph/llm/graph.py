"""Connected components of a stored edge table, by alternating stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import Stage


def _stars(pairs: DataFrame) -> DataFrame:
    """One step: each node's larger neighbours, then its smaller ones and itself, point to the least of them."""
    both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("x"), F.least("a", "m").alias("m"))
    large = both.where("b > a").join(least, F.col("a") == F.col("x")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    large = large.where("a <> b").distinct()
    low = large.groupBy("a").agg(F.min("b").alias("m"))
    small = large.join(low.select(F.col("a").alias("x"), "m"), F.col("a") == F.col("x")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    return small.unionByName(low.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def components(pairs: DataFrame, stage: Stage) -> DataFrame:
    """(node, root) of all nodes of the pairs (a, b) but the roots; the root is the least node of its component.

    Every round writes a table, so lineage stays short; rounds grow with the logarithm of the longest path.
    """
    now = stage.table(pairs.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "edges")
    mark = None
    while True:
        seen = now.agg(F.count("*").alias("n"), F.coalesce(F.bit_xor(F.xxhash64("a", "b")), F.lit(0)).alias("x")).first()
        if tuple(seen) == mark or not seen["n"]:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
        mark, before = tuple(seen), now
        now = stage.table(_stars(now), "stars")
        stage.drop(before)
