"""Quicksort on the hypercube, with its pivots, shuffles and tie policies as options, and two relatives."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import uid_hash
from ..storage import staged
from . import costs, cube, medians, shuffling, ties
from .placement import SortResult, local_positions, log2, ranked


def cube_quicksort(state: DataFrame, p: int, pivot: str = "first_pe", shuffle: str = "none", tie: str = "none", k: int = 2, seed: int = 1, method: str = "cube_quicksort", cubes: int = 1) -> SortResult:
    """Halve the elements of every subcube at a pivot, highest dimension first.

    In each round a PE's elements up to the pivot go to the side whose bit is 0, the others to the
    other side. ``pivot``: see ``medians.pivots``; ``shuffle``: none, direct or cube; ``tie``: none or local.
    A subcube without elements has no pivot and takes no part. A round shuffles and writes the elements once: they arrive sorted,
    and pivots and splits come from summaries of a row per PE. ``cubes`` machines of p PEs sort side by side.
    """
    spark, d, ledger, splitters = state.sparkSession, log2(p), [], []
    if shuffle == "direct":
        at = shuffling.direct(state, p, seed, ledger, 0, method, cubes, positions=True)
    else:
        if shuffle == "cube":
            state = shuffling.by_dimension(state, p, seed, ledger, 0, method, cubes=cubes)
        at = staged(local_positions(state), "local")
    base = len(ledger)

    def halve(at: DataFrame, j: int, number: int) -> DataFrame:
        s = medians.pivots(at, pivot, p * cubes, j + 1, k, seed + 101 * (j + 1), p)
        s = staged(s.select(F.col("subcube").cast("int").alias("subcube"), "s"), "pivots")
        splitters.append(s.withColumn("dims", F.lit(j + 1)))
        # One row per subcube, never more than p / 2; without a pivot the elements keep together.
        held = at.withColumn("subcube", cube.subcube(F.col("pe"), j + 1)).join(F.broadcast(s), "subcube", "left")
        sided = (ties.local_split if tie == "local" else ties.keys_only)(held)
        words = {"median_of_medians": 1 << (j + 1)}.get(pivot, k)
        ledger.append(costs.collective_rows(spark, method, base + 2 * number, p * cubes, j + 1, words))
        to = cube.with_bit(F.col("pe"), j, ~F.coalesce("left", F.lit(True)))
        return cube.exchange(sided.select("pe", "key", "uid", "left"), to, method, base + 2 * number + 1, p * cubes, ledger, positions=True).drop("left")

    at = cube.run(at, p, halve)
    return SortResult(ranked(at), costs.union(ledger, spark), costs.union(splitters, spark) if splitters else None)


def robust_cube_quicksort(state: DataFrame, p: int, k: int = 2, seed: int = 1, shuffle: str = "direct", cubes: int = 1) -> SortResult:
    return cube_quicksort(state, p, "binary_tree", shuffle, "local", k, seed, "robust_cube_quicksort", cubes)


def plain_cube_quicksort(state: DataFrame, p: int, k: int = 2, seed: int = 1, shuffle: str = "none", tie: str = "none", cubes: int = 1) -> SortResult:
    """The robust method less its measures; the two switches also give the mixed forms."""
    return cube_quicksort(state, p, "binary_tree", shuffle, tie, k, seed, "plain_cube_quicksort", cubes)


def one_per_pe_quicksort(state: DataFrame, permute: bool = False, seed: int = 1, most_levels: int = 200) -> SortResult:
    """Quicksort with exactly one element per PE: segments of slots are partitioned around a median from a tree of threes.

    Ties are split by slot against the pivot's, so every level makes progress. A finished segment has one slot.
    """
    n = state.count()
    spark, method, ledger = state.sparkSession, "one_per_pe_quicksort", []
    now = state.select(F.col("pe").cast("long").alias("slot"), F.lit(0).cast("long").alias("seg"), F.lit(n).cast("long").alias("len"), "key", "uid")
    now = staged(now.withColumn("slot", F.row_number().over(Window.orderBy("slot", "uid")) - 1), "slots")
    for level in range(most_levels):
        open_segments = now.where("len > 1")
        if open_segments.isEmpty():
            break
        leaf = F.row_number().over(Window.partitionBy("seg").orderBy(*([uid_hash("uid", seed)] if permute else []), "slot")) - 1
        trees = open_segments.select("seg", leaf.alias("leaf"), F.struct("key", "slot").alias("v"))
        while True:
            trees = trees.groupBy("seg", F.expr("leaf div 3").alias("leaf")).agg(F.sort_array(F.collect_list("v")).alias("_v"))
            trees = trees.select("seg", "leaf", F.expr("_v[cast(size(_v) div 2 AS int)]").alias("v"))
            if not trees.agg(F.max("leaf")).first()[0]:
                break
        placed = now.join(F.broadcast(trees.select("seg", F.col("v").alias("s"))), "seg", "left")
        small = F.struct("key", "slot") <= F.col("s")
        per = Window.partitionBy("seg")
        placed = placed.withColumn("_small", F.when(F.col("s").isNotNull(), small.cast("int")))
        placed = placed.withColumn("_n", F.sum("_small").over(per)).withColumn("_at", F.row_number().over(Window.partitionBy("seg", "_small").orderBy("slot")) - 1)
        # A pivot that is the largest of its segment would leave it whole: then its own element is set apart.
        top = F.col("_n") == F.col("len")
        alone = top & (F.struct("key", "slot") == F.col("s"))
        less = F.when(top, F.col("len") - 1).otherwise(F.col("_n"))
        is_small = F.when(top, ~alone).otherwise(F.col("_small") == 1)
        placed = placed.withColumn("_less", less).withColumn("_is", is_small)
        place = F.row_number().over(Window.partitionBy("seg", "_is").orderBy("slot")) - 1
        placed = placed.withColumn("_place", place)
        done = F.col("s").isNull()
        moved = placed.select(
            F.col("slot").alias("src"),
            F.when(done, F.col("slot")).when(F.col("_is"), F.col("seg") + F.col("_place")).otherwise(F.col("seg") + F.col("_less") + F.col("_place")).alias("slot"),
            F.when(done | F.col("_is"), F.col("seg")).otherwise(F.col("seg") + F.col("_less")).alias("_seg"),
            F.when(done, F.col("len")).when(F.col("_is"), F.col("_less")).otherwise(F.col("len") - F.col("_less")).alias("_len"), "key", "uid",
        )
        moved = staged(moved.withColumnRenamed("_seg", "seg").withColumnRenamed("_len", "len"), f"slots-{level}")
        ledger.append(costs.exchange_rows(moved.select(F.col("src").cast("int"), F.col("slot").cast("int").alias("pe")), method, level, n))
        now = moved.drop("src")
    return SortResult(now.select(F.col("slot").cast("int").alias("pe"), F.col("slot").alias("rank"), "key", "uid"), costs.union(ledger, spark))


def irregular_quicksort(state: DataFrame, p: int, k: int = 2, seed: int = 1, most_levels: int = 64) -> SortResult:
    """Quicksort whose PE groups are shared out in proportion to the parts; any p. Each part is spread evenly over its group."""
    spark, method, ledger = state.sparkSession, "irregular_quicksort", []
    now = staged(state.select("pe", "key", "uid", F.lit(0).alias("lo"), F.lit(p).alias("hi")), "irregular")
    for level in range(most_levels):
        busy = now.where("hi - lo > 1")
        if busy.isEmpty():
            break
        per = Window.partitionBy("lo", "hi")
        # The pivot is the median of a bounded hash sample of the group, with its uid: a total order, so both parts are proper.
        sample = busy.withColumn("_r", F.row_number().over(per.orderBy(uid_hash("uid", seed + level), "uid"))).where("_r <= 64")
        mid = sample.groupBy("lo", "hi").agg(F.sort_array(F.collect_list(F.struct("key", "uid"))).alias("_v")).select("lo", "hi", F.expr("_v[cast((size(_v) - 1) div 2 AS int)]").alias("s"))
        cut = busy.join(F.broadcast(mid), ["lo", "hi"]).withColumn("left", F.struct("key", "uid") <= F.col("s"))
        sizes = cut.groupBy("lo", "hi").agg(F.sum(F.col("left").cast("long")).alias("nl"), F.count(F.lit(1)).alias("n"))
        share = F.least(F.greatest(F.round(F.col("nl") / F.col("n") * (F.col("hi") - F.col("lo"))).cast("int"), F.lit(1)), F.col("hi") - F.col("lo") - 1)
        cut = cut.join(F.broadcast(sizes.withColumn("cutpe", F.col("lo") + share)), ["lo", "hi"])
        lo, hi = F.when(F.col("left"), F.col("lo")).otherwise(F.col("cutpe")), F.when(F.col("left"), F.col("cutpe")).otherwise(F.col("hi"))
        cut = cut.select("pe", "key", "uid", lo.alias("_lo"), hi.alias("_hi"), F.when(F.col("left"), F.col("nl")).otherwise(F.col("n") - F.col("nl")).alias("size"))
        place = F.row_number().over(Window.partitionBy("_lo", "_hi").orderBy("pe", "key", "uid")) - 1
        cut = cut.withColumn("_to", (F.col("_lo") + F.expr("0") + (place * (F.col("_hi") - F.col("_lo")) / F.col("size")).cast("int")))
        moved = cube.exchange(cut.select("pe", "key", "uid", F.col("_lo").alias("lo"), F.col("_hi").alias("hi"), "_to"), F.col("_to"), method, level, p, ledger).drop("_to")
        now = staged(moved.unionByName(now.where("hi - lo <= 1")), "irregular")
    return SortResult(ranked(now.select("pe", "key", "uid")), costs.union(ledger, spark))
