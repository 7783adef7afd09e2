"""Policies for equal keys: naive ids, local splits, implied grid order and splitter origins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def with_uid(key: Column, uid: Column) -> Column:
    """The naive unique key: the id travels with every element and every comparison."""
    return F.struct(key.alias("key"), uid.alias("uid"))


def local_split(state: DataFrame, splitter: str = "s") -> DataFrame:
    """``state`` (pe, pos, m, key, splitter) with ``left``: equal keys are cut where the PE's halves are most equal.

    The PE keeps the order of its elements, so with lt smaller and eq equal ones the left part has
    lt + x elements, x in 0..eq nearest to m / 2 - lt.
    """
    # Counts by a combining aggregation, one row per PE, so no element moves for them.
    lt, eq = (F.sum(test.cast("int")) for test in (F.col("key") < F.col(splitter), F.col("key") == F.col(splitter)))
    counts = state.groupBy(F.col("pe").alias("_pe")).agg(F.coalesce(lt, F.lit(0)).alias("lt"), F.coalesce(eq, F.lit(0)).alias("eq"))
    x = F.least(F.greatest(F.expr("(m + 1) div 2") - F.col("lt"), F.lit(0)), F.col("eq"))
    return state.join(F.broadcast(counts), F.col("pe") == F.col("_pe")).drop("_pe").withColumn("left", F.col("pos") <= F.col("lt") + x)


def keys_only(state: DataFrame, splitter: str = "s") -> DataFrame:
    """Without a policy: all keys equal to the splitter go left together."""
    return state.withColumn("left", F.col("key") <= F.col(splitter))


def grid_order(columns: int) -> list[Column]:
    """Sort columns of the implied total order (key, row, column, position): the last three follow from placement."""
    return [F.col("key"), F.expr(f"pe div {columns}"), F.expr(f"pe % {columns}"), F.col("pos")]
