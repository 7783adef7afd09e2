"""Joins that Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, on: str, keys: list[str], value: str, into: str, strict: bool = True) -> DataFrame:
    """Each left row with ``value`` of the latest right row of its keys whose ``on`` is before it (or equal, if not ``strict``).

    One union and one window: a single exchange on the keys, no pairs.
    """
    names = [c for c in left.columns]
    a = left.select(*names, F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(0 if strict else 1).alias("_side"))
    b = right.select(*[F.col(c) if c in (*keys, on) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in names], F.col(value).alias("_v"), F.lit(1 if strict else 0).alias("_side"))
    latest = F.last("_v", ignorenulls=True).over(Window.partitionBy(*keys).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    out = a.withColumn("_left", F.lit(True)).unionByName(b.withColumn("_left", F.lit(False))).withColumn(into, latest)
    return out.where("_left").select(*names, into)


def range_join(left: DataFrame, point: str, right: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """left.point in [right.low, right.high), by bins of ``width``: an equi-join on the bin, then the exact test."""
    a = left.withColumn("_bin", F.floor(F.col(point) / width))
    b = right.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return a.join(b, "_bin").where((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("_bin")


def theta_band(rows: DataFrame, point: str, value: str, width: float) -> DataFrame:
    """All pairs (a, b) of ``value`` whose points are ``a < b < a + width``, a join on two inequalities.

    Distinct points meet in bins, so equal ones cost no pairs that the test throws away; the rows then join the points they hold.
    """
    points = rows.select(F.col(point).alias("_low")).distinct()
    near = range_join(points.withColumnRenamed("_low", "_point"), "_point", points.withColumn("_high", F.col("_low") + width), "_low", "_high", width).where("_point > _low")
    a, b = rows.select(F.col(point).alias("_low"), F.col(value).alias("a")), rows.select(F.col(point).alias("_point"), F.col(value).alias("b"))
    # Merge joins spread the pairs over tasks by point; a broadcast would leave them where the few points are.
    return near.select("_low", "_point").join(a.hint("merge"), "_low").join(b.hint("merge"), "_point").select("a", "b")


def salted(left: DataFrame, right: DataFrame, key: str, salts: int, salt: Column) -> DataFrame:
    """Equi-join whose left rows of one key go to ``salts`` tasks; the right side is repeated for each salt."""
    a = left.withColumn("_salt", salt % salts)
    b = right.withColumn("_salt", F.explode(F.expr(f"sequence(0L, {salts - 1}L)")))
    return a.join(b, [key, "_salt"]).drop("_salt")


def with_counts(p: int, counts: DataFrame, key: str = "pe") -> DataFrame:
    """All PEs 0..p-1, those without rows included."""
    every = counts.sparkSession.range(p).select(F.col("id").cast("int").alias(key))
    return every.join(counts, key, "left")
