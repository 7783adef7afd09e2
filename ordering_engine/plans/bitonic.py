"""Bitonic sort with compare-split blocks: d (d + 1) / 2 rounds, each pairing all PEs and moving half of what they hold."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import staged
from . import costs
from .placement import SortResult, cube_of, log2, per_cube, ranked


def bitonic_sort(state: DataFrame, p: int, cubes: int = 1) -> SortResult:
    """Blocks are filled up to equal size with sentinels above all keys, which are dropped at the end."""
    d, ledger, spark = log2(p), [], state.sparkSession
    loads = state.groupBy("pe").count()
    top = {r.cube: r.m for r in loads.groupBy(cube_of(p).alias("cube")).agg(F.max("count").alias("m")).collect()}
    m = per_cube([top.get(c, 0) for c in range(cubes)], p).cast("long")
    kind = state.schema["key"].dataType
    every = spark.range(p * cubes).select(F.col("id").cast("int").alias("pe")).join(loads, "pe", "left").na.fill(0).withColumn("_m", m)
    missing = every.where("count < _m").withColumn("i", F.explode(F.expr("sequence(1L, _m - count)")))
    fill = missing.select("pe", F.lit(1).alias("cls"), F.lit(None).cast(kind).alias("key"), (-(F.col("pe").cast("long") * F.col("_m") + F.col("i"))).alias("uid"))
    now = staged(state.select("pe", F.lit(0).alias("cls"), "key", "uid").unionByName(fill), "bitonic")
    step = 0
    for s in range(d):
        for j in range(s, -1, -1):
            pair = F.col("pe").bitwiseAND(F.lit(~(1 << j)))
            up = F.shiftright("pe", s + 1).bitwiseAND(F.lit(1)) == 0
            place = F.row_number().over(Window.partitionBy(pair).orderBy("cls", "key", "uid"))
            low = (place <= m) == up
            moved = staged(now.withColumn("src", F.col("pe")).withColumn("pe", F.when(low, pair).otherwise(pair.bitwiseOR(F.lit(1 << j))).cast("int")), f"bitonic-{step}")
            notes = costs.exchange_rows(moved, "bitonic_sort", step, p * cubes)
            # Compare-split sends the whole block, whatever part of it stays.
            ledger.append(notes.withColumn("words_out", m).withColumn("words_in", m).withColumn("startups", F.lit(2).cast("long")))
            now = moved.drop("src")
            step += 1
    return SortResult(ranked(now.where("cls = 0").select("pe", "key", "uid")), costs.union(ledger, spark))
