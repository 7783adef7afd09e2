"""Checks of what a sorting method promises, and measures of balance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def order(data: DataFrame) -> bool:
    """Ranks are 0..n-1 without gaps, keys follow them, and PEs hold consecutive ranks. Each element meets its successor by a join on the rank."""
    n, distinct, low, high = data.agg(F.count(F.lit(1)), F.countDistinct("rank"), F.min("rank"), F.max("rank")).first()
    if n and (distinct, low, high) != (n, 0, n - 1):
        return False
    own = data.select(F.col("rank").cast("long").alias("rank"), "key", "pe")
    after = own.select((F.col("rank") - 1).alias("rank"), F.col("key").alias("_key"), F.col("pe").alias("_pe"))
    return own.join(after, "rank").where("_key < key or _pe < pe").isEmpty()


def permutation(data: DataFrame, source: DataFrame) -> bool:
    """Both hold the same (key, uid) rows, counted."""
    a, b = data.select("key", "uid"), source.select("key", "uid")
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def loads(data: DataFrame, p: int) -> DataFrame:
    """Rows on every PE, empty ones included."""
    every = data.sparkSession.range(p).select(F.col("id").cast("int").alias("pe"))
    return every.join(data.groupBy("pe").agg(F.count(F.lit(1)).alias("held")), "pe", "left").na.fill(0, ["held"])


def imbalance(data: DataFrame, p: int) -> float:
    """Largest load over the mean, less one."""
    top, n = loads(data, p).agg(F.max("held"), F.sum("held")).first()
    return top * p / n - 1 if n else 0.0


def imbalance_trace(ledger: DataFrame, n: int, p: int) -> DataFrame:
    """Largest load over the mean after each step that moved data."""
    steps = ledger.where("held_after is not null").groupBy("step").agg(F.max("held_after").alias("held"))
    return steps.select("step", (F.col("held") * p / F.lit(max(n, 1))).alias("factor"))


def delivery_bound(ledger: DataFrame, n: int, p: int) -> DataFrame:
    """Per round of a delivery down the columns of the grid: the words of the busiest PE and the bound n / (sqrt(p) * 2^round)."""
    first = ledger.agg(F.min("step")).first()[0]
    rounds = ledger.groupBy("step").agg(F.max(F.greatest("words_out", "words_in")).alias("words"))
    rounds = rounds.withColumn("bound", F.lit(n / p**0.5) / F.pow(F.lit(2.0), F.col("step") - first))
    return rounds.withColumn("within", F.col("words") <= F.col("bound"))


def pe_load_in_subcube(ledger: DataFrame, dims: int) -> DataFrame:
    """Largest over mean load of the PEs in each subcube of ``dims`` dimensions, by step."""
    inside = ledger.where("held_after is not null").withColumn("subcube", F.shiftright("pe", dims))
    return inside.groupBy("step", "subcube").agg((F.max("held_after") / F.greatest(F.avg("held_after"), F.lit(1e-9))).alias("max_over_mean"))


def verdict(ledger: DataFrame, n: int, p: int, capacity_factor: float = 8.0, stalled: bool = False) -> str:
    """ok, imbalanced, overflow (a PE would hold over ``capacity_factor`` times the mean) or no_progress."""
    if stalled:
        return "no_progress"
    top = imbalance_trace(ledger, n, p).agg(F.max("factor")).first()[0] or 0.0
    return "overflow" if top > capacity_factor else "imbalanced" if top > 2.0 else "ok"
