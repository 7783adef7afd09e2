"""The conceptual hypercube: numbering, the round template, collectives and routing."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..storage import staged
from . import costs
from .placement import local_positions, log2


def subcube(pe: Column, dims: int) -> Column:
    """The subcube of ``dims`` dimensions that a PE is in: its high bits."""
    return F.shiftright(pe, dims)


def partner(pe: Column, j: int) -> Column:
    return pe.bitwiseXOR(F.lit(1 << j))


def with_bit(pe: Column, j: int, one: Column) -> Column:
    """``pe`` with bit j set where ``one`` holds and cleared elsewhere."""
    return F.when(one, pe.bitwiseOR(F.lit(1 << j))).otherwise(pe.bitwiseAND(F.lit(~(1 << j))))


def run(state, p: int, step: Callable, descending: bool = True):
    """Apply ``step(state, j, number)`` for every dimension j, highest first unless told otherwise."""
    d = log2(p)
    for number, j in enumerate(range(d - 1, -1, -1) if descending else range(d)):
        state = step(state, j, number)
    return state


def exchange(state: DataFrame, to: Column, method: str, step: int, p: int, ledger: list[DataFrame], dense: bool = False, positions: bool = False, loads: bool = True) -> DataFrame:
    """Move rows to the PE ``to``, note it in the ledger and end the lineage (``staged_at``). Extra columns of ``state`` travel along.

    With ``positions`` rows arrive sorted: ``pos`` and ``m`` are written with them, so the next step needs no shuffle for these.
    Without ``loads`` there is no ``m``, which takes a second window over all rows.
    """
    moved = state.withColumn("src", F.col("pe")).withColumn("pe", to.cast("int"))
    if positions:
        moved = local_positions(moved) if loads else local_positions(moved).drop("m")
    moved = staged(moved, f"{method}-{step}")
    ledger.append(costs.exchange_rows(moved, method, step, p, dense))
    back = moved.drop("src")
    back.staged_at = moved.staged_at
    return back


def reduce(values: DataFrame, total: Column) -> DataFrame:
    """One row: an aggregate over the PEs' values."""
    return values.agg(total.alias("value"))


def bcast(value: DataFrame, p: int) -> DataFrame:
    """The one row on every PE. Broadcasts here carry a row, or one per subcube: never more than p."""
    return value.sparkSession.range(p).select(F.col("id").cast("int").alias("pe")).join(F.broadcast(value))


def all_reduce(values: DataFrame, total: Column, dims: int | None = None) -> DataFrame:
    """Every PE with the aggregate over its subcube (over all PEs if ``dims`` is None). ``values``: pe, value."""
    if dims is None:
        return values.select("pe").join(F.broadcast(reduce(values, total)))
    keyed = values.withColumn("subcube", subcube(F.col("pe"), dims))
    return keyed.select("pe", "subcube").join(F.broadcast(keyed.groupBy("subcube").agg(total.alias("value"))), "subcube").select("pe", "value")


def exclusive_scan(values: DataFrame, column: str = "value") -> DataFrame:
    """Sum over the PEs before each PE; one row per PE enters the window."""
    before = Window.orderBy("pe").rowsBetween(Window.unboundedPreceding, -1)
    return values.select("pe", F.coalesce(F.sum(column).over(before), F.lit(0)).alias("value"))


def all_gather(values: DataFrame, p: int, most_rows: int = 1_000_000) -> DataFrame:
    """Every PE with all rows (``pe``, ``from_pe``, ...). For inputs of a checked size only."""
    if values.limit(most_rows + 1).count() > most_rows:
        raise ValueError(f"all-gather is for at most {most_rows} rows")
    every = values.sparkSession.range(p).select(F.col("id").cast("int").alias("pe"))
    return every.join(F.broadcast(values.withColumnRenamed("pe", "from_pe")))


def route(state: DataFrame, dst: str, p: int, method: str = "route", descending: bool = True, hops: bool = True) -> tuple[DataFrame, DataFrame]:
    """Rows at PE ``dst``: bit by bit with a ledger of every hop, or (``hops=False``) in one exchange."""
    ledger: list[DataFrame] = []
    if not hops:
        return exchange(state, F.col(dst), method, 0, p, ledger), ledger[0]
    state = run(state, p, lambda now, j, step: exchange(now, with_bit(F.col("pe"), j, F.shiftright(dst, j).bitwiseAND(F.lit(1)) == 1), method, step, p, ledger), descending)
    return state, costs.union(ledger, state.sparkSession)


def physical(state: DataFrame, p: int) -> DataFrame:
    """Partition i of the result holds exactly PE i, sorted by key."""
    return state.repartitionById(p, F.col("pe")).sortWithinPartitions("key", "uid")
