"""Multiway mergesort with exact splitting: perfect balance from the elements of rank i * n / p."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import uid_hash
from ..functions.search import count_below
from ..storage import staged
from . import costs, cube
from .placement import SortResult, ranked

OWN = "struct(key, uid)"


def exact_splitters(state: DataFrame, p: int, oversample: int = 16, few: int = 4096, seed: int = 1) -> tuple[DataFrame, int]:
    """key, uid of the first element of every PE but the first, by multiway selection, and the number of rounds.

    The order is (key, uid). A round draws candidates in the ranges that still hold a wanted rank, and counts all elements
    between candidates by binary search and a combining aggregation, so no element moves. Once such a range holds only ``few`` elements, these are
    ranked. The driver sees one count per candidate, p * oversample a round.
    """
    spark, n = state.sparkSession, state.count()
    wanted = sorted({-(-i * n // p) for i in range(1, p)} - {n})
    kind = state.schema["key"].dataType.simpleString()
    candidates = spark.createDataFrame([], f"c struct<key:{kind},uid:bigint>")
    rounds = 0
    while True:
        arrays = candidates.agg(F.sort_array(F.collect_list("c")).alias("cs"))
        placed = state.withColumn("own", F.expr(OWN)).join(F.broadcast(arrays)).withColumn("range", count_below("cs", "own")).drop("cs")
        sizes = dict(sorted((r.range, r.c) for r in placed.groupBy("range").agg(F.count(F.lit(1)).alias("c")).collect()))
        first, before = {}, 0
        for at, size in sizes.items():
            first[at], before = before, before + size
        open_ranges = {at for at in sizes for rank in wanted if first[at] <= rank < first[at] + sizes[at]}
        inside = placed.where(F.col("range").isin(sorted(open_ranges)))
        if all(sizes[at] <= few for at in open_ranges):
            break
        draw = F.row_number().over(Window.partitionBy("range").orderBy(uid_hash("uid", seed + rounds), "uid"))
        share = max(2, oversample * p // len(open_ranges))
        more = inside.withColumn("_r", draw).where(F.col("_r") <= share).select(F.expr("struct(key, uid)").alias("c"))
        candidates = staged(candidates.unionByName(more).distinct(), "candidates")
        rounds += 1
    bases = spark.createDataFrame([(at, first[at]) for at in open_ranges] or [(-1, 0)], "range int, first bigint")
    place = F.row_number().over(Window.partitionBy("range").orderBy("key", "uid")) - 1
    ranks = inside.withColumn("_in", place).join(F.broadcast(bases), "range").withColumn("rank", F.col("first") + F.col("_in"))
    return staged(ranks.where(F.col("rank").isin(wanted)).select("key", "uid"), "splitters"), rounds


def exact_split_mergesort(state: DataFrame, p: int) -> SortResult:
    """Every PE finds its part by the exact splitters, sends the runs in one exchange and merges what it receives: loads differ by one at most."""
    method, ledger, n = "exact_split_mergesort", [], state.count()
    splitters, rounds = exact_splitters(state, p)
    ledger.append(costs.collective_rows(state.sparkSession, method, 0, p, max(1, rounds) * max(1, p.bit_length() - 1), p))
    # p - 1 splitters; an element belongs after those that aren't above it.
    arrays = splitters.agg(F.sort_array(F.collect_list(F.expr(OWN))).alias("ss"))
    cut = state.withColumn("own", F.expr("struct(key, uid + 1 AS uid)")).join(F.broadcast(arrays)).withColumn("part", count_below("ss", "own"))
    # With fewer elements than PEs the parts are those of the elements' ranks.
    to = F.col("part") if n >= p else F.expr(f"cast(part * {p} div {max(n, 1)} AS int)")
    now = cube.exchange(cut.select("pe", "key", "uid", to.alias("to")), F.col("to"), method, 1, p, ledger, positions=True).drop("to")
    return SortResult(ranked(now), costs.union(ledger, state.sparkSession), splitters, notes={"rounds": rounds})
