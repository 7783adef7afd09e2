"""Approximate medians of the elements of each subcube, and how good they are.

The trees work on windows: arrays of (cls, key) with cls -1 and +1 for the sentinels below and above
all keys. A shuffle folds ``ROUNDS`` levels of a tree at a time, so p PEs need log(p) / ROUNDS small shuffles.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import SPARK, uid_hash
from ..functions.keys import global_rank
from .placement import local_positions

ROUNDS = 4


def _sentinel(kind: str, cls: int) -> str:
    return f"named_struct('cls', {cls}, 'key', cast(null AS {kind}))"


def leaf_windows(state: DataFrame, p: int, k: int, seed: int, machine: int | None = None) -> DataFrame:
    """pe, w: the k elements around each PE's median, padded; every PE has a row. An odd load flips a coin between the two middles."""
    kind = state.schema["key"].dataType.simpleString()
    at = local_positions(state) if "pos" not in state.columns else state
    coin = f"({SPARK.hash(f'pe % {machine or p}', seed)} % 2)"
    middle = f"(m div 2 + (m % 2) * {coin})"
    near = at.withColumn("_mid", F.expr(middle)).where(f"pos > _mid - {k // 2} and pos <= _mid + {k // 2}")
    real = near.groupBy("pe").agg(
        F.max("_mid").alias("_mid"), F.max("m").alias("m"), F.sort_array(F.collect_list(F.struct(F.lit(0).alias("cls"), F.col("key").alias("key")))).alias("_real")
    )
    every = state.sparkSession.range(p).select(F.col("id").cast("int").alias("pe"))
    padded = every.join(real, "pe", "left").withColumn("_low", F.expr(f"greatest(0, {k // 2} - coalesce(_mid, 0))"))
    low = f"array_repeat({_sentinel(kind, -1)}, cast(_low AS int))"
    high = f"array_repeat({_sentinel(kind, 1)}, {k})"
    real_or_none = f"coalesce(_real, array_repeat({_sentinel(kind, 0)}, 0))"
    return padded.select("pe", F.expr(f"slice(concat({low}, {real_or_none}, {high}), 1, {k})").alias("w"))


def _fold(windows: DataFrame, levels: int, arity: int, keep: int) -> DataFrame:
    """Fold ``levels`` levels: groups of arity^levels neighbours become one window of ``keep`` middle elements."""
    group = arity**levels
    packed = windows.groupBy(F.expr(f"pe div {group}").alias("pe")).agg(F.array_sort(F.collect_list(F.struct("pe", "w"))).alias("_l"))
    ws = "transform(_l, x -> x.w)"
    for level in range(levels):
        packed = packed.withColumn(f"_w{level}", F.expr(ws))
        source = f"_w{level}"
        take = ", ".join(f"coalesce(try_element_at({source}, i * {arity} + {a + 1}), slice({source}[0], 1, 0))" for a in range(arity))
        merged = f"array_sort(concat({take}))"
        ws = f"transform(sequence(0, cast(ceil(size({source}) / {float(arity)}) AS int) - 1), i -> transform(array({merged}), s -> slice(s, cast(1 + (size(s) - least({keep}, size(s))) div 2 AS int), {keep}))[0])"
    return packed.select("pe", F.expr(f"({ws})[0]").alias("w"))


def _tree(windows: DataFrame, depth: int, arity: int, keep: int) -> DataFrame:
    while depth > 0:
        levels = min(depth, ROUNDS)
        windows, depth = _fold(windows, levels, arity, keep), depth - levels
    return windows


def binary_tree(state: DataFrame, p: int, dims: int, k: int = 2, seed: int = 1, machine: int | None = None) -> DataFrame:
    """subcube, s: an estimate of the median of every non-empty subcube of ``dims`` dimensions.

    The root flips a coin between the two middle elements; if the coin meets a sentinel while the
    subcube holds elements, the real neighbour is taken. With machines of ``machine`` PEs side by side, each draws as it would alone.
    """
    w = _tree(leaf_windows(state, p, k, seed, machine), dims, 2, k)
    coin = f"({SPARK.hash(f'pe % {max(1, (machine or p) >> dims)}', seed + 1)} % 2)"
    chosen = f"coalesce(nullif(w[{k // 2 - 1} + {coin}].cls, 0), 0)"
    real = "filter(w, x -> x.cls = 0)"
    pick = f"if({chosen} = 0, w[{k // 2 - 1} + {coin}].key, if({chosen} < 0, {real}[0].key, element_at({real}, -1).key))"
    return w.where(F.expr(f"size({real}) > 0")).select(F.col("pe").alias("subcube"), F.expr(pick).alias("s"))


def ternary_tree(state: DataFrame, p: int, dims: int | None = None, permute: bool = True, seed: int = 1) -> DataFrame:
    """subcube, s: medians of three, passed up from single elements. ``dims`` None: one tree over everything.

    Elements are the leaves, randomly permuted, as the bound on the error asks for; ``permute=False`` leaves them in PE and local
    order. A tree whose size is no power of three is unbalanced; of two elements the smaller goes up.
    """
    subcubed = state.withColumn("subcube", (F.lit(0) if dims is None else F.shiftright("pe", dims)).cast("long"))
    subcubed = subcubed.withColumn("_mix", uid_hash("uid", seed))
    numbered = global_rank(subcubed.select("subcube", "pe", "key", "uid", "_mix"), ["subcube", "_mix"] if permute else ["subcube", "pe", "key"], tie="uid")
    per = numbered.groupBy("subcube").agg(F.min("rank").alias("_first"), F.count(F.lit(1)).alias("_n"))
    most = per.agg(F.max("_n")).first()[0] or 1
    depth = next(d for d in range(64) if 3**d >= most)
    leaves = numbered.join(F.broadcast(per), "subcube").select((F.col("subcube") * 3**depth + F.col("rank") - F.col("_first")).alias("pe"), F.array(F.struct(F.lit(0).alias("cls"), "key")).alias("w"))
    return _tree(leaves, depth, 3, 1).select(F.col("pe").cast("int").alias("subcube"), F.col("w")[0]["key"].alias("s"))


def _local_medians(state: DataFrame) -> DataFrame:
    at = local_positions(state) if "pos" not in state.columns else state
    return at.where("pos = (m + 1) div 2").select("pe", "key")


def first_pe(state: DataFrame, dims: int) -> DataFrame:
    """The local median of the first PE of the subcube that holds anything."""
    own = _local_medians(state)
    return own.groupBy(F.shiftright("pe", dims).alias("subcube")).agg(F.min_by("key", "pe").alias("s"))


def random_pe(state: DataFrame, dims: int, seed: int = 1, machine: int = 1 << 30) -> DataFrame:
    """The local median of a random non-empty PE of the subcube."""
    own = _local_medians(state)
    return own.groupBy(F.shiftright("pe", dims).alias("subcube")).agg(F.min_by("key", uid_hash(f"pe % {machine}", seed)).alias("s"))


def median_of_medians(state: DataFrame, dims: int) -> DataFrame:
    """The median of the PEs' local medians, gathered: one row per PE enters the window."""
    own = _local_medians(state).withColumn("subcube", F.shiftright("pe", dims))
    per = Window.partitionBy("subcube")
    place = own.withColumn("_r", F.row_number().over(per.orderBy("key", "pe"))).withColumn("_n", F.count(F.lit(1)).over(per))
    return place.where("_r = (_n + 1) div 2").select("subcube", F.col("key").alias("s"))


def exact(state: DataFrame, dims: int) -> DataFrame:
    """The lower median itself, by ranks in the order of subcubes and keys."""
    ranks = global_rank(state.select(F.shiftright("pe", dims).alias("subcube"), "key", "uid"), ["subcube", "key"], tie="uid")
    per = ranks.groupBy("subcube").agg(F.min("rank").alias("_first"), F.count(F.lit(1)).alias("_n"))
    return ranks.join(F.broadcast(per), "subcube").where("rank = _first + (_n + 1) div 2 - 1").select("subcube", F.col("key").alias("s"))


def pivots(state: DataFrame, how: str, p: int, dims: int, k: int, seed: int, machine: int | None = None) -> DataFrame:
    return {
        "binary_tree": lambda: binary_tree(state, p, dims, k, seed, machine), "ternary_tree": lambda: ternary_tree(state, p, dims, seed=seed), "first_pe": lambda: first_pe(state, dims),
        "random_pe": lambda: random_pe(state, dims, seed, machine or p), "median_of_medians": lambda: median_of_medians(state, dims), "exact": lambda: exact(state, dims),
    }[how]()


def rank_error(rank: Column, n: Column) -> Column:
    return F.abs(rank / (n / 2) - 1)


def fit(errors: DataFrame) -> DataFrame:
    """c and gamma of error = c * n^-gamma, from rows (n, error), by regression of the logarithms."""
    logs = errors.where("error > 0").select(F.ln("n").alias("x"), F.ln("error").alias("y"))
    return logs.agg(F.exp(F.regr_intercept("y", "x")).alias("c"), (-F.regr_slope("y", "x")).alias("gamma"))


def bias(ranks: DataFrame) -> DataFrame:
    """Mean rank over n / 2 (over m / 2 of rows with ``m``), from rows (rank, n); 1 for a truthful estimator."""
    return ranks.groupBy("n").agg(F.avg(F.col("rank") / (F.col("m" if "m" in ranks.columns else "n") / 2)).alias("mean_over_half"))


def study(spark, sizes: list[int], seeds: int = 100, k: int = 2, tree: str = "binary") -> DataFrame:
    """(n, seed, rank, error) of tree medians over random permutations of 1..n, one element per leaf, in one plan.

    The permutation is the order of a hash of (element, seed); each size is a separate set of groups.
    """
    cells = [(n, s) for n in sizes for s in range(seeds)]
    base = spark.createDataFrame(cells, "n int, seed int").repartition(max(1, min(64, len(cells) // 8)))
    leaves = base.select("n", "seed", F.explode(F.expr("sequence(1, n)")).alias("v"))
    mixed = F.expr(SPARK.hash("v + 1000003L * seed + 17L * n", 5))
    leaf = F.row_number().over(Window.partitionBy("n", "seed").orderBy(mixed, "v")) - 1
    ranks = _tree_ranks(leaves.select("n", "seed", leaf.alias("leaf"), "v"), max(sizes), k, tree)
    return ranks.withColumn("error", rank_error(F.col("rank"), F.col("n")))


def study_of(held: DataFrame, sizes: list[int], k: int = 2, tree: str = "binary") -> DataFrame:
    """(n, seed, m, rank, error) of tree medians over the elements of a table, whose dense uids are cut into blocks for each size n.

    Every element is in one block of each size: as few blocks (``seed``) as hold no more than n each, as even as they can be,
    so a block has m elements, n or a few less. An element is a leaf, ordered by a hash of its uid; its rank is that of its key in the block.
    """
    total = held.count()
    parts = [F.struct(F.lit(n).alias("n"), F.expr(f"cast(uid * {-(-total // n)} div {max(1, total)} AS int)").alias("seed")) for n in sizes]
    blocks = held.select("key", "uid", F.inline(F.array(*parts)))
    per = Window.partitionBy("n", "seed")
    leaf, rank = F.row_number().over(per.orderBy(uid_hash("uid", 5), "uid")) - 1, F.row_number().over(per.orderBy("key", "uid"))
    leaves = blocks.select("n", "seed", leaf.alias("leaf"), rank.alias("v"))
    load = leaves.groupBy("n", "seed").agg(F.count(F.lit(1)).alias("m"))
    found = _tree_ranks(leaves, max(sizes), k, tree).join(load, ["n", "seed"])
    return found.select("n", "seed", "m", "rank", rank_error(F.col("rank"), F.col("m")).alias("error"))


def _tree_ranks(level: DataFrame, widest: int, k: int, tree: str) -> DataFrame:
    """(n, seed, rank): what the tree over the leaves (n, seed, leaf, v) of each (n, seed), ``widest`` at most, takes for the median."""
    arity = 2 if tree == "binary" else 3
    depth = max(1, math.ceil(round(math.log(widest, arity), 9)))
    if tree == "binary":
        # Single elements: an odd load of one, so a coin puts the element in the lower or the upper half of the window.
        coin = F.expr(f"{SPARK.hash('leaf + 31 * seed + 7 * n', 3)} % 2")
        low, high = F.lit(-1), F.lit(1 << 30)
        pad = lambda value, times: F.array_repeat(value, times)
        w = F.when(coin == 1, F.concat(pad(low, k // 2 - 1), F.array("v"), pad(high, k // 2))).otherwise(F.concat(pad(low, k // 2), F.array("v"), pad(high, k // 2 - 1)))
        level = level.select("n", "seed", "leaf", w.alias("w"))
        for _ in range(depth):
            level = level.groupBy("n", "seed", F.expr("leaf div 2").alias("leaf")).agg(F.array_sort(F.flatten(F.collect_list("w"))).alias("w"))
            level = level.withColumn("w", F.expr(f"slice(w, cast(1 + (size(w) - least({k}, size(w))) div 2 AS int), {k})"))
        coin = F.expr(f"{SPARK.hash('seed + 7 * n', 9)} % 2")
        chosen = F.expr(f"w[{k // 2 - 1} + cast({SPARK.hash('seed + 7 * n', 9)} % 2 AS int)]")
        real = F.expr("filter(w, x -> x > 0 and x < 1073741824)")
        rank = F.when(chosen < 0, real[0]).when(chosen >= 1 << 30, F.element_at(real, -1)).otherwise(chosen)
    else:
        for _ in range(depth):
            level = level.groupBy("n", "seed", F.expr("leaf div 3").alias("leaf")).agg(F.sort_array(F.collect_list("v")).alias("w"))
            level = level.select("n", "seed", "leaf", F.expr("w[cast(size(w) div 2 AS int)]").alias("v"))
        rank = F.col("v")
    return level.select("n", "seed", rank.alias("rank"))
