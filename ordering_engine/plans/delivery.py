"""Who sends which elements to whom: by rank, by running sums, or with a bounded number of messages.

Plans work on pieces (src_pe, grp, cnt): how many elements of each group every PE holds. A transfer
(grp, src_pe, dst_pe, lo, hi) sends the elements lo..hi-1 of a piece.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

TRANSFER = ("grp", "src_pe", "dst_pe", "lo", "hi")


def by_rank(ranked: DataFrame, p: int, n: int) -> DataFrame:
    """Rank i to PE i * p div n."""
    return ranked.withColumn("pe", F.expr(f"cast(rank * {p} div {max(n, 1)} AS int)"))


def _overlaps(left: DataFrame, right: DataFrame) -> DataFrame:
    """Transfers from intervals [lo, hi) of senders and receivers on one line per group."""
    pairs = left.alias("a").join(right.alias("b"), (F.col("a.grp") == F.col("b.grp")) & (F.col("a.lo") < F.col("b.hi")) & (F.col("b.lo") < F.col("a.hi")))
    start, end = F.greatest("a.lo", "b.lo"), F.least("a.hi", "b.hi")
    return pairs.select(F.col("a.grp").alias("grp"), F.col("a.src_pe").alias("src_pe"), F.col("b.dst_pe").alias("dst_pe"), (start - F.col("a.lo")).alias("lo"), (end - F.col("a.lo")).alias("hi"))


def _line(rows: DataFrame, size: str, order: str) -> DataFrame:
    w = Window.partitionBy("grp").orderBy(order)
    end = F.sum(size).over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return rows.withColumn("hi", end).withColumn("lo", F.col("hi") - F.col(size))


def _receivers(pieces: DataFrame, p: int, k: int) -> DataFrame:
    """grp, dst_pe, quota for the p / k PEs of each group that has elements; a quota is an even share, rounded up."""
    each = p // k
    totals = pieces.groupBy("grp").agg(F.sum("cnt").alias("total"))
    spread = totals.withColumn("i", F.explode(F.expr(f"sequence(0, {each - 1})")))
    return spread.select("grp", (F.col("grp") * each + F.col("i")).cast("int").alias("dst_pe"), F.expr(f"(total + {each - 1}) div {each}").alias("quota"), "total")


def prefix(pieces: DataFrame, p: int, k: int) -> DataFrame:
    """Elements of a group are laid end to end in the order of their PEs and cut into even shares; no bound on messages."""
    each = p // k
    senders = _line(pieces.where("cnt > 0"), "cnt", "src_pe")
    totals = pieces.groupBy("grp").agg(F.sum("cnt").alias("total"))
    cuts = totals.withColumn("i", F.explode(F.expr(f"sequence(0, {each - 1})")))
    receivers = cuts.select("grp", (F.col("grp") * each + F.col("i")).cast("int").alias("dst_pe"), F.expr(f"(total * i + {each - 1}) div {each}").alias("lo"), F.expr(f"(total * (i + 1) + {each - 1}) div {each}").alias("hi")).where("lo < hi")
    return _overlaps(senders, receivers)


def bounded_messages(pieces: DataFrame, p: int, k: int, fan_out: int | None = None) -> DataFrame:
    """At most k small and 2k + 2 large messages to any receiver, and no more than its quota of elements; k is the fan-out.

    ``k`` groups share the p PEs; a level splits each set of PEs into ``fan_out`` of them (all, if not given).
    Pieces of at most quota / 2k elements are small: k consecutive ones go whole to each receiver,
    half its quota at most. The large ones and the rooms that are left are laid on one line, and
    where a piece and a room overlap there is a message.
    """
    groups, k = k, fan_out or k
    rooms = _receivers(pieces, p, groups)
    quota = rooms.select("grp", "quota").distinct()
    sized = pieces.where("cnt > 0").join(F.broadcast(quota), "grp")
    small = sized.where(F.col("cnt") * (2 * k) <= F.col("quota"))
    number = F.row_number().over(Window.partitionBy("grp").orderBy("src_pe")) - 1
    small = small.withColumn("dst_pe", (F.col("grp") * (p // groups) + F.floor(number / k)).cast("int"))
    used = small.groupBy("grp", "dst_pe").agg(F.sum("cnt").alias("used"))
    left = rooms.join(used, ["grp", "dst_pe"], "left").withColumn("room", F.col("quota") - F.coalesce("used", F.lit(0)))
    large = _line(sized.where(F.col("cnt") * (2 * k) > F.col("quota")), "cnt", "src_pe")
    shares = _overlaps(large, _line(left.where("room > 0"), "room", "dst_pe"))
    return small.select("grp", "src_pe", "dst_pe", F.lit(0).cast("long").alias("lo"), F.col("cnt").alias("hi")).unionByName(shares)


def fan_in(transfers: DataFrame) -> DataFrame:
    """dst_pe, senders, received."""
    return transfers.groupBy("dst_pe").agg(F.countDistinct("src_pe").alias("senders"), F.sum(F.col("hi") - F.col("lo")).alias("received"))


def choose(pieces: DataFrame, p: int, k: int, fan_out: int | None = None, cubes: int = 1) -> tuple[str, DataFrame]:
    """The bounded plan for the machines where it helps, else the prefix plan.

    It helps where the prefix plan gives some PE more messages than the bounded plan ever would, 3k + 2, and messages are
    worth saving: from 8k elements a PE on, k being the fan-out.
    """
    fan, plan = fan_out or k, prefix(pieces, p, k)
    per, groups = p // cubes, k // cubes
    busiest = fan_in(plan).groupBy(F.expr(f"cast(dst_pe div {per} AS int)").alias("cube")).agg(F.max("senders").alias("c"))
    sent = plan.groupBy("src_pe").agg(F.countDistinct("dst_pe").alias("c")).groupBy(F.expr(f"cast(src_pe div {per} AS int)").alias("cube")).agg(F.max("c").alias("c"))
    load = pieces.groupBy(F.expr(f"cast(src_pe div {per} AS int)").alias("cube")).agg((F.sum("cnt") / per).alias("load"))
    most = busiest.unionByName(sent).groupBy("cube").agg(F.max("c").alias("c")).join(load, "cube")
    helped = [r.cube for r in most.where((F.col("c") > 3 * fan + 2) & (F.col("load") > 8 * fan)).select("cube").collect()]
    if not helped:
        return "prefix", plan
    bounded = bounded_messages(pieces, p, k, fan_out)
    if len(helped) == cubes:
        return "bounded", bounded
    inside = F.expr(f"cast(grp div {groups} AS int)").isin(helped)
    return "mixed", bounded.where(inside).unionByName(plan.where(~inside))


def apply(state: DataFrame, transfers: DataFrame) -> DataFrame:
    """``state`` (pe, grp, gpos 0-based within the piece) with ``to``: the PE its transfer names. Equal positions are found by interval."""
    t = transfers.select(F.col("grp").alias("_g"), F.col("src_pe").alias("_s"), F.col("dst_pe").alias("to"), "lo", "hi")
    match = (F.col("grp") == F.col("_g")) & (F.col("pe") == F.col("_s")) & (F.col("gpos") >= F.col("lo")) & (F.col("gpos") < F.col("hi"))
    return state.join(t, match).drop("_g", "_s", "lo", "hi")
