"""The k-way generalisation of hypercube quicksort: good on large uniform inputs, not robust to repeated keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.search import with_count_below
from ..storage import staged
from . import costs, cube
from .placement import SortResult, ranked
from .samplesort import fan_outs, smallest_hashes
from .verify import imbalance_trace


def histogram_splitters(at: DataFrame, k: int, candidates: int, seed: int, tolerance: float = 0.02, most_rounds: int = 4) -> DataFrame:
    """group, i, s: the sampled keys whose global ranks are nearest to i * n / k; candidates are drawn again between the brackets.

    Ranks of candidates come from counts between them, by a combining aggregation: no element is shuffled for a histogram.
    """
    n = at.groupBy("group").agg(F.count(F.lit(1)).alias("n"))
    targets = n.withColumn("i", F.explode(F.expr(f"sequence(1, {max(k - 1, 1)})"))).withColumn("want", F.col("n") * F.col("i") / k)
    drawn = at.select("group", "key").where(F.lit(False))
    best, still = None, at
    for r in range(most_rounds):
        more = smallest_hashes(still, "group", candidates * k, seed + r, "key").select("group", "key")
        drawn = staged(drawn.unionByName(more).distinct(), "candidates")
        # At most candidates * k a round for each group of PEs.
        arrays = drawn.groupBy("group").agg(F.sort_array(F.collect_list("key")).alias("_cs"))
        between = with_count_below(at.select("group", "key").join(F.broadcast(arrays), "group"), "_cs", "key", "_b", candidates * k * (r + 1))
        between = between.groupBy("group", "_b").agg(F.count(F.lit(1)).alias("_c"))
        # The first candidate not below a key counts it, so a candidate's rank takes its equals in.
        named = arrays.select("group", F.posexplode("_cs").alias("_b", "key")).join(between, ["group", "_b"], "left")
        upto = Window.partitionBy("group").orderBy("_b").rowsBetween(Window.unboundedPreceding, Window.currentRow)
        placed = named.withColumn("rank", F.sum(F.coalesce("_c", F.lit(0))).over(upto)).select("group", "key", "rank")
        away = F.abs(F.col("rank") - F.col("want"))
        best = staged(targets.join(placed, "group").groupBy("group", "i", "n").agg(F.min_by("key", F.struct(away, "key")).alias("s"), F.min(away).alias("_away")), "nearest")
        away = best.where(F.col("_away") > tolerance * F.col("n") / k).select("group").distinct()
        if away.isEmpty():
            break
        still = at.join(F.broadcast(away), "group", "left_semi")  # a group that is near enough draws no more
    return best.select("group", "i", "s")


def kway_cube_sort(state: DataFrame, p: int, k: int = 4, candidates: int = 16, capacity_factor: float = 8.0, seed: int = 1, cubes: int = 1) -> SortResult:
    """Per level k - 1 splitters by global histogramming; bucket i of PE q of a group goes to the PE of the same offset in subgroup i.

    Equal keys are never split, so they meet on one PE: the verdict is ``overflow`` where a PE would hold
    more than ``capacity_factor`` times the mean.
    """
    spark, method, ledger = state.sparkSession, "kway_cube_sort", []
    levels = max(1, -(-(p.bit_length() - 1) // max(1, k.bit_length() - 1)))
    now, size = staged(state.select("pe", "key", "uid"), "kway"), p
    for level, fan in enumerate(fan_outs(p, levels)):
        at = now.withColumn("group", F.expr(f"pe div {size}"))
        s = histogram_splitters(at, fan, candidates, seed + 31 * level) if fan > 1 else None
        if s is not None:
            # k - 1 splitters a group: p at most.
            arrays = s.groupBy("group").agg(F.sort_array(F.collect_list("s")).alias("ss"))
            cut = with_count_below(at.join(F.broadcast(arrays), "group", "left"), "ss", "key", "part", fan)
            sub = size // fan
            to = F.col("group") * size + F.col("part") * sub + (F.col("pe") % sub)
            # Splitting the communicator costs time in its size: charged as one word per PE of the group.
            ledger.append(costs.collective_rows(spark, method, 2 * level, p * cubes, max(1, size.bit_length() - 1), size + candidates * fan))
            now = cube.exchange(cut.select("pe", "key", "uid", to.alias("to")), F.col("to"), method, 2 * level + 1, p * cubes, ledger).drop("to")
        size //= fan
    book = costs.union(ledger, spark)
    top = imbalance_trace(book, state.count(), p).agg(F.max("factor")).first()[0] or 0.0
    return SortResult(ranked(now), book, verdict="overflow" if top > capacity_factor else "ok")
