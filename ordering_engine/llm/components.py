"""Connected components of a graph given as an edge table, by alternating large-star and small-star rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import remove
from .shared import settled


def _stars(edges: DataFrame, center: str, leaf: str) -> DataFrame:
    """Each node's neighbours beside the least of them and of itself; the least is found by a combining aggregation."""
    least = edges.groupBy(center).agg(F.min(leaf).alias("_m")).select(F.col(center).alias("_c"), F.least("_m", F.col(center)).alias("_m"))
    return edges.join(least, F.col(center) == F.col("_c")).drop("_c")


def components(edges: DataFrame, label: str = "components") -> DataFrame:
    """From rows (``a``, ``b``): one row per node that has an edge to another, ``node`` and ``root`` (the least node of its component).

    The root itself has no row. Rounds go on until one changes nothing; each is written to shared storage, so lineage stays
    short, and takes the place of the one before it. The number of rounds grows with the logarithm of the longest chain.
    """
    spark = edges.sparkSession
    start = edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    now, before = settled(spark, lambda: start, label), None
    while (sums := tuple(now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())) != before:
        before = sums
        last, now = now, settled(spark, lambda now=now: _round(now), label)
        remove(last.staged_at)
    return now.select(F.col("a").alias("node"), F.col("b").alias("root"))


def _round(now: DataFrame) -> DataFrame:
    both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
    large = _stars(both, "a", "b").where("b > a").select(F.col("b").alias("a"), F.col("_m").alias("b")).where("a <> b").distinct()
    small = _stars(large, "a", "b").select("a", "b", "_m")
    small = small.select(F.col("b").alias("a"), F.col("_m").alias("b")).unionByName(small.select("a", F.col("_m").alias("b")))
    return small.where("a <> b").distinct()
