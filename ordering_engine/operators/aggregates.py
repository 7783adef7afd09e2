"""Aggregations over sorted data and against splitters."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.search import count_below


def runs_of_equal(df: DataFrame, column: str) -> DataFrame:
    """Value and length of each run of equal values in sorted order: the sort-based form of grouping.

    Equal values are counted in every task before they move, so a hot value is one row a task; the runs are then put in order.
    """
    runs = df.groupBy(column).agg(F.count(F.lit(1)).alias("run_length"))
    return runs.repartitionByRange(column).sortWithinPartitions(column)


def bucket_of(column: str, splitters: list[float]) -> Column:
    """Number of splitters below the value: nested conditions for few, a binary search for many."""
    if len(splitters) <= 16:
        out = F.lit(0)
        for s in sorted(splitters):
            out = out + (F.col(column) > s).cast("int")
        return out
    return count_below(f"array({', '.join(f'{float(s)!r}D' for s in sorted(splitters))})", column)


def bucket_counts(df: DataFrame, column: str, splitters: list[float]) -> DataFrame:
    return df.groupBy(bucket_of(column, splitters).cast("int").alias("bucket")).agg(F.count(F.lit(1)).alias("cnt"))


def bottom_sample(df: DataFrame, hashed: Column, size: int, tie: str) -> DataFrame:
    """The ``size`` rows of smallest hash: a uniform sample that reruns agree on (TakeOrderedAndProject)."""
    return df.orderBy(hashed, tie).limit(size)


def equal_weight_cuts(ranked: DataFrame, p: int, n: int) -> DataFrame:
    """Rows per part when ranks 0..n-1 are cut into p even parts, with each part's first and last key."""
    return ranked.groupBy(F.expr(f"cast(rank * {p} div {n} AS int)").alias("part")).agg(F.count(F.lit(1)).alias("cnt"), F.min("key").alias("low"), F.max("key").alias("high"))
