"""Sample sorts: with l levels and bounded imbalance, and the direct one with a single exchange."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import PRIME, uid_hash
from ..functions.search import count_below, with_count_below
from ..storage import remove, staged
from . import costs, cube, delivery, shuffling
from .gridrank import grid_rank
from .placement import SortResult, cube_of, local_positions, ranked


def fan_outs(p: int, levels: int) -> list[int]:
    """Fan-out of each level: powers of two near the levels-th root of p, whose product is p."""
    d = p.bit_length() - 1
    if p != 1 << d:
        raise ValueError(f"p must be a power of two, not {p}")
    levels = max(1, min(levels, max(d, 1)))
    return [1 << (d // levels + (1 if i < d % levels else 0)) for i in range(levels)]


def default_levels(p: int) -> int:
    return 1 if p <= 16 else 2 if p <= 4096 else 3


def assign(counts: list[int], k: int) -> list[int]:
    """Group of each bucket: contiguous buckets to at most k groups, with the least possible largest load."""

    def groups(limit: int) -> list[int] | None:
        out, g, load = [], 0, 0
        for c in counts:
            if load + c > limit and load:
                g, load = g + 1, 0
            load += c
            if g >= k or load > limit:
                return None
            out.append(g)
        return out

    low, high = max([*counts, -(-sum(counts) // k), 0]), sum(counts)
    while low < high:
        mid = (low + high) // 2
        low, high = (low, mid) if groups(mid) is not None else (mid + 1, high)
    return groups(low) or [0] * len(counts)


def smallest_hashes(state: DataFrame, group: str, size: int, seed: int, *columns: str) -> DataFrame:
    """``columns`` of each group's ``size`` elements of smallest hash, or of all where it has fewer.

    A group's size tells how low its hashes must be for a few more than ``size`` of them, so the elements are filtered, not sorted.
    A group where fewer than it should have pass, which a bad hash would bring, is taken whole instead. What passes is ranked.
    """
    hashed = state.select(*dict.fromkeys([group, "uid", *columns]), uid_hash("uid", seed).alias("_h"))
    enough = size + 8 * math.isqrt(size) + 16
    sizes = state.groupBy(F.col(group).alias("_g")).agg(F.count(F.lit(1)).alias("_m"))  # one row per group, as below
    low = F.broadcast(sizes.withColumn("_most", F.least(F.lit(float(PRIME)), F.lit(float(PRIME * enough)) / F.col("_m"))))
    few = staged(hashed.join(low, F.col(group) == F.col("_g")).where("_h <= _most").drop("_g", "_m", "_most"), "low-hashes")
    short = sizes.join(few.groupBy(F.col(group).alias("_f")).agg(F.count(F.lit(1)).alias("_n")), F.col("_g") == F.col("_f"), "left")
    short = [r._g for r in short.where(f"coalesce(_n, 0) < least(_m, {size})").select("_g").collect()]
    if short:
        few = few.where(~F.col(group).isin(short)).unionByName(hashed.where(F.col(group).isin(short)))
    return few.withColumn("_r", F.row_number().over(Window.partitionBy(group).orderBy("_h", "uid"))).where(F.col("_r") <= size).drop("_r", "_h")


def splitter_table(state: DataFrame, group: str, k: int, oversample: int, overpartition: int, seed: int, tie: bool) -> DataFrame:
    """group, i, s: b*k - 1 splitters per group, every a-th of a*b*k sampled elements with their origins.

    The sample is the elements of smallest hash: at most a*b*k per group, which the windows sort.
    """
    drawn = smallest_hashes(state, group, oversample * overpartition * k, seed, "key", "pe", "pos")
    origin = F.struct("key", "pe", "pos") if tie else F.struct("key", F.lit(0).alias("pe"), F.lit(0).alias("pos"))
    per = Window.partitionBy(group)
    placed = drawn.select(group, origin.alias("s"), F.row_number().over(per.orderBy(origin)).alias("_i"), F.count(F.lit(1)).over(per).alias("_n"))
    buckets = overpartition * k
    chosen = placed.withColumn("i", F.expr(f"_i * {buckets} div _n")).withColumn("_b", F.expr(f"(_i - 1) * {buckets} div _n"))
    return chosen.where(f"i > _b and i < {buckets}").select(group, "i", "s")


def ranked_sample(sample: DataFrame, p: int = 16) -> DataFrame:
    """Ranks of a small sample (pe, key, uid) by the grid method, as its splitters are found."""
    return grid_rank(sample.withColumn("pe", F.col("pe") % p), p, unique=True)


def multilevel_samplesort(state: DataFrame, p: int, levels: int | None = None, oversample: int = 16, overpartition: int = 4, eps: float = 0.1, ties: bool = True, plan: str = "auto", exchange: str = "sparse", seed: int = 1, method: str = "multilevel_samplesort", cubes: int = 1) -> SortResult:
    """Each level splits every group of PEs k ways and moves the elements once.

    Per level: sampled splitters with origins, b*k buckets found by binary search, contiguous buckets to k groups with least
    largest load, a message plan (``prefix``, ``bounded`` or by need), the exchange. ``ties=False`` compares
    keys only: a level that leaves some group as it was is reported as ``no_progress``. ``exchange="dense"``
    charges a startup for every peer, as in the bulk-synchronous model. ``cubes`` machines of p PEs sort side by side.
    """
    spark, ledger, notes, stalled = state.sparkSession, [], {}, set()
    at, size = staged(local_positions(state.select("pe", "key", "uid")).drop("m"), "levels"), p
    where = at.staged_at
    splitters = None
    for level, k in enumerate(fan_outs(p, levels or default_levels(p))):
        at = at.withColumn("group", F.expr(f"pe div {size}"))
        splitters = staged(splitter_table(at, "group", k, oversample, overpartition, seed + level, ties), "splitters")
        # b * k splitters per group as one sorted array: p * b at most in all, bounded by the machine, not the data.
        arrays = splitters.groupBy("group").agg(F.sort_array(F.collect_list("s")).alias("ss"))
        own = F.struct("key", "pe", "pos") if ties else F.struct("key", F.lit(0).alias("pe"), F.lit(0).alias("pos"))
        cut = with_count_below(at.withColumn("_own", own).join(F.broadcast(arrays), "group", "left"), "ss", "_own", "bucket", overpartition * k)
        # The one pass that searches buckets: a row per PE and bucket it has.
        cells = staged(cut.groupBy("pe", "group", "bucket").agg(F.count(F.lit(1)).alias("cnt"), F.min("pos").alias("first")), "cells")
        sizes = {}
        for g, b, c in cells.groupBy("group", "bucket").agg(F.sum("cnt").alias("c")).orderBy("group", "bucket").collect():
            sizes.setdefault(g, {})[b] = c
        rows = []
        for g, counts in sizes.items():
            dense = [counts.get(b, 0) for b in range(max(counts) + 1)]
            rows += [(g, b, g * k + t) for b, t in enumerate(assign(dense, k))]
            if not ties and k > 1 and sum(1 for c in dense if c) == 1 and dense and sum(dense) > size:
                stalled.add(g * size // p)
        assigned = spark.createDataFrame(rows or [(0, 0, 0)], "group int, bucket int, grp int")
        # A PE's buckets are ranges of its order, so the groups are too: a place in the piece is the place on the PE less that of the piece's first.
        pieces = staged(cells.join(F.broadcast(assigned), ["group", "bucket"]).groupBy(F.col("pe").alias("src_pe"), "grp").agg(F.sum("cnt").alias("cnt"), F.min("first").alias("first")), "pieces")
        parts = p * cubes // size * k
        if plan == "auto":
            name, transfers = delivery.choose(pieces.drop("first"), p * cubes, parts, k, cubes)
        else:
            name, transfers = plan, delivery.bounded_messages(pieces.drop("first"), p * cubes, parts, k) if plan == "bounded" else delivery.prefix(pieces.drop("first"), p * cubes, parts)
        notes[level] = name
        found = transfers.join(pieces.select("src_pe", "grp", "first"), ["src_pe", "grp"])
        found = staged(found.select(F.col("src_pe").alias("_s"), F.col("dst_pe").alias("to"), (F.col("lo") + F.col("first")).alias("lo"), (F.col("hi") + F.col("first")).alias("hi")), "transfers")
        # Transfers are at most a few k per PE: p * k rows. Those of a PE are ranges of its order, so a place alone tells an element's.
        routed = at.join(F.broadcast(found), (F.col("pe") == F.col("_s")) & (F.col("pos") >= F.col("lo")) & (F.col("pos") < F.col("hi")))
        ledger.append(costs.collective_rows(spark, method, 2 * level, p * cubes, max(1, size.bit_length() - 1), oversample * overpartition * k))
        now = cube.exchange(routed.select("pe", "key", "uid", "to"), F.col("to"), method, 2 * level + 1, p * cubes, ledger, dense=exchange == "dense", positions=True, loads=False)
        ledger[-1] = staged(ledger[-1], "ledger")  # a row per PE: with it nothing reads the level before any more
        remove(where)
        at, where = now.drop("to"), now.staged_at
        size //= k
    notes["stalled"] = sorted(stalled)
    return SortResult(ranked(at), costs.union(ledger, spark), splitters, "no_progress" if stalled else "ok", notes)


def direct_samplesort(state: DataFrame, p: int, shuffle_first: bool = False, splitters: list | None = None, oversample: int = 16, seed: int = 1, method: str = "direct_samplesort", cubes: int = 1) -> SortResult:
    """One exchange: p - 1 splitters from a sample, or given ones, and every element to its final PE. Any p."""
    spark, ledger = state.sparkSession, []
    if shuffle_first:
        state = shuffling.direct(state, p, seed, ledger, 0, method, cubes)
    cut = state.withColumn("group", cube_of(p))
    if splitters is None:
        s = staged(splitter_table(cut.withColumn("pos", F.col("uid")), "group", p, oversample, 1, seed, True), "splitters")
        arrays = s.groupBy("group").agg(F.sort_array(F.collect_list("s.key")).alias("ss"))
        ledger.append(costs.collective_rows(spark, method, len(ledger), p * cubes, p - 1, oversample * p))
    else:
        kind = state.schema["key"].dataType.simpleString()
        arrays = spark.createDataFrame([(c, sorted(splitters)) for c in range(cubes)], f"group int, ss array<{kind}>")
    # p - 1 splitters, on every PE.
    cut = with_count_below(cut.join(F.broadcast(arrays), "group", "left"), "ss", "key", "part", p if splitters is None else max(p, len(splitters)))
    to = F.col("group") * p + F.col("part")
    now = cube.exchange(cut.select("pe", "key", "uid", to.alias("to")), F.col("to"), method, len(ledger), p * cubes, ledger).drop("to")
    return SortResult(ranked(now), costs.union(ledger, spark))


def planned_sort(df: DataFrame, *by: str, partitions: int, tie: str | None = None) -> DataFrame:
    """The direct sort for use: one range exchange on sampled bounds and a local sort. With ``tie`` equal keys spread by its hash, which is evaluated at the exchange and never stored."""
    from ..functions.hashing import uid_hash as h

    dealt = df.repartitionByRange(partitions, *[F.col(b) for b in by], *([h(tie, 7)] if tie else []))
    return dealt.sortWithinPartitions(*by)


def two_level_sort(df: DataFrame, key: str, uid: str, groups: int, partitions: int, path: str, sample: int = 64) -> DataFrame:
    """For sizes where one exchange has too many blocks: key ranges to staged group folders, then each group sorted on its own.

    The group bounds are those of a bounded sample, ``sample`` rows of smallest hash per group, in the order of key and
    hash of the id, so a key held by many rows is spread over groups as well. The first exchange has ``groups`` targets of a few tasks; then
    every group is a pruned scan of its folder with an exchange of its own, and the groups follow each other in the result.
    """
    spark, share = df.sparkSession, max(1, partitions // groups)
    drawn = df.select(F.struct(F.col(key).alias("key"), uid_hash(uid, 7).alias("h")).alias("b"), uid_hash(uid, 11).alias("_draw")).orderBy("_draw", "b").limit(sample * groups)
    arrays = drawn.agg(F.sort_array(F.collect_list("b")).alias("_all")).select(F.expr(f"transform(sequence(1, {groups}), i -> _all[cast(i * size(_all) div {groups} AS int) - 1])").alias("_bs"))
    arrays = arrays.select(F.expr(f"slice(filter(_bs, x -> x IS NOT NULL), 1, {groups - 1})").alias("_bs"))  # one row of at most ``groups`` bounds
    keyed = df.withColumn("_own", F.struct(F.col(key).alias("key"), uid_hash(uid, 7).alias("h"))).join(F.broadcast(arrays)).withColumn("sort_group", count_below("_bs", "_own")).drop("_bs", "_own")
    keyed.repartition(F.col("sort_group"), F.pmod(uid_hash(uid, 13), F.lit(share))).write.partitionBy("sort_group").parquet(path)
    whole = spark.read.schema(T.StructType([*df.schema.fields, T.StructField("sort_group", T.IntegerType())])).parquet(path)
    each = [whole.where(F.col("sort_group") == g).drop("sort_group").repartitionByRange(share, key, uid_hash(uid, 7)).sortWithinPartitions(key, uid) for g in range(groups)]
    return reduce(DataFrame.unionAll, each)
