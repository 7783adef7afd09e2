"""Logical PEs: who holds which element. A held sequence has the columns pe, key, uid."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.keys import comparable, global_rank
from ..storage import staged


@dataclass
class SortResult:
    """``data``: pe, rank, key, uid. ``ledger``: one row per step and PE. ``splitters``: where the method has any."""

    data: DataFrame
    ledger: DataFrame
    splitters: DataFrame | None = None
    verdict: str = "ok"
    notes: dict = field(default_factory=dict)


def log2(p: int) -> int:
    d = p.bit_length() - 1
    if p != 1 << d:
        raise ValueError(f"p must be a power of two, not {p}")
    return d


def dense_uid(df: DataFrame, id_columns: list[str]) -> DataFrame:
    """``df`` with ``uid`` 0..n-1 in the order of its unique columns."""
    return global_rank(df, id_columns, "uid")


def held(df: DataFrame, order, p: int, uid: str = "uid", sparse: bool = False) -> DataFrame:
    """Block placement of elements with dense uids: pe = uid * p div n; a sparse input is spread over the PEs."""
    keyed = df.select(comparable(df, order).alias("key"), F.col(uid).cast("long").alias("uid"))
    n = keyed.count()
    pe = F.expr(f"uid * {max(1, p // max(n, 1))}") if sparse and n < p else F.expr(f"uid * {p} div {max(n, 1)}")
    return staged(keyed.select(pe.cast("int").alias("pe"), "key", "uid"), "held")


def cube_of(p: int, pe: str = "pe") -> Column:
    """Which of several machines of p PEs a PE is in; they work side by side in one plan, numbered one after the other."""
    return F.expr(f"cast({pe} div {p} AS int)")


def per_cube(values: list, p: int, pe: str = "pe") -> Column:
    """The entry of a PE's machine in a list of one value each."""
    return F.lit(values[0]) if len(values) == 1 else F.element_at(F.array(*map(F.lit, values)), cube_of(p, pe) + 1)


def cube_sizes(state: DataFrame, p: int, cubes: int) -> list[int]:
    """Number of elements of every machine."""
    found = {r.cube: r.n for r in state.groupBy(cube_of(p).alias("cube")).agg(F.count(F.lit(1)).alias("n")).collect()}
    return [found.get(c, 0) for c in range(cubes)]


def local_positions(state: DataFrame, *tie: str) -> DataFrame:
    """1-based ``pos`` and ``m``, the sorted place of each element on its PE and the PE's load."""
    per = Window.partitionBy("pe")
    return state.withColumn("pos", F.row_number().over(per.orderBy("key", *(tie or ("uid",))))).withColumn("m", F.count(F.lit(1)).over(per))


def ranked(state: DataFrame) -> DataFrame:
    """pe, rank, key, uid of a state that is sorted across PEs: counts of earlier PEs plus the local place (``pos``, where the state has it)."""
    loads = state.groupBy("pe").agg(F.count(F.lit(1)).alias("m"))
    before = Window.orderBy("pe").rowsBetween(Window.unboundedPreceding, -1)
    offsets = loads.select("pe", F.coalesce(F.sum("m").over(before), F.lit(0)).alias("before"))
    placed = state if "pos" in state.columns else state.withColumn("pos", F.row_number().over(Window.partitionBy("pe").orderBy("key", "uid")))
    return placed.join(F.broadcast(offsets), "pe").select("pe", (F.col("before") + F.col("pos") - 1).alias("rank"), "key", "uid")


def grid(p: int) -> tuple[int, int]:
    """Rows and columns of the nearly square array of PEs."""
    if p & (p - 1) == 0:
        d = log2(p)
        return 1 << (d - (d + 1) // 2), 1 << ((d + 1) // 2)
    columns = next(c for c in range(int(p**0.5), p + 1) if p % c == 0)
    return p // columns, columns
