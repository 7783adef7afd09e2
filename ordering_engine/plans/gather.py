"""Sorting while gathering: everything on one PE, or everything on every PE. For sparse inputs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import costs, cube
from .placement import SortResult, log2, ranked


def gather_merge_sort(state: DataFrame, p: int, cubes: int = 1) -> SortResult:
    """Along a binomial tree: in round j the PEs with bit j as their lowest set bit send all they hold to the PE without it."""
    ledger: list[DataFrame] = []
    for j in range(log2(p)):
        low = F.col("pe").bitwiseAND(F.lit((1 << (j + 1)) - 1)) == (1 << j)
        state = cube.exchange(state, F.when(low, F.col("pe") - (1 << j)).otherwise(F.col("pe")), "gather_merge_sort", j, p * cubes, ledger)
    return SortResult(ranked(state), costs.union(ledger, state.sparkSession))


def all_gather_merge(state: DataFrame, p: int, tagged: bool = False) -> DataFrame:
    """Per PE the whole sorted input (pe, rank, key, uid), built round by round along the cube's dimensions.

    ``tagged`` adds ``side``: whether the element came from a lower PE (-1), the PE itself (0) or a higher one (1).
    """
    d = log2(p)
    held = state.withColumnRenamed("pe", "origin").withColumn("pe", F.col("origin"))
    for j in range(d):
        held = held.unionByName(held.withColumn("pe", cube.partner(F.col("pe"), j).cast("int")))
    from pyspark.sql import Window

    out = held.select("pe", (F.row_number().over(Window.partitionBy("pe").orderBy("key", "uid")) - 1).alias("rank"), "key", "uid", "origin")
    side = F.signum(F.col("origin") - F.col("pe")).cast("int")
    return out.withColumn("side", side).drop("origin") if tagged else out.drop("origin")


def all_gather_merge_sort(state: DataFrame, p: int, cubes: int = 1) -> SortResult:
    """Every PE ends with all elements; the ledger has each round's doubling volume."""
    spark, ledger, d = state.sparkSession, [], log2(p)
    loads = state.groupBy("pe").count()
    every = spark.range(p * cubes).select(F.col("id").cast("int").alias("pe")).join(loads, "pe", "left").na.fill(0)
    for j in range(d):
        groups = every.groupBy(F.shiftright("pe", j).alias("g")).agg(F.sum("count").alias("own"))
        own = every.select("pe", F.shiftright("pe", j).alias("g")).join(F.broadcast(groups), "g")
        other = groups.select(F.col("g").bitwiseXOR(F.lit(1)).alias("g"), F.col("own").alias("other"))
        ledger.append(own.join(F.broadcast(other), "g").select(F.lit("all_gather_merge_sort").alias("method"), F.lit(j).alias("step"), "pe", F.lit(2).cast("long").alias("startups"), F.col("own").alias("words_out"), F.col("other").alias("words_in"), (F.col("own") + F.col("other")).alias("held_after")))
    return SortResult(all_gather_merge(state, p), costs.union(ledger, spark))
