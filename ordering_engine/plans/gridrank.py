"""Ranking on a nearly square grid of PEs, and the robust sort built on it.

Every row of PEs gathers its elements, every column gathers its own; in each cell the row's elements
are ranked against the column's; adding up along a row gives global ranks. Each element is copied to
(rows + columns) cells, so this is for inputs of a few elements per PE.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import staged
from . import costs, cube
from .placement import SortResult, cube_of, cube_sizes, grid, local_positions, log2, per_cube
from .ties import grid_order


def _cells(state: DataFrame, p: int) -> DataFrame:
    """Copies of each element: role 0 in all cells of its row, role 1 in all cells of its column."""
    rows, columns = grid(p)
    at = local_positions(state)
    r, c = F.expr(f"pe div {columns}"), F.expr(f"pe % {columns}")  # rows are numbered over all machines, so a cell belongs to one
    as_row = at.withColumn("cr", r).withColumn("cc", F.explode(F.expr(f"sequence(0, {columns - 1})"))).withColumn("role", F.lit(0))
    as_column = at.withColumn("cc", c).withColumn("cr", F.explode(F.expr(f"sequence(cast(pe div {p} AS int) * {rows}, cast(pe div {p} AS int) * {rows} + {rows - 1})"))).withColumn("role", F.lit(1))
    return as_row.select("cr", "cc", "role", "pe", "pos", "key", "uid").unionByName(as_column.select("cr", "cc", "role", "pe", "pos", "key", "uid"))


def grid_rank(state: DataFrame, p: int, unique: bool = False) -> DataFrame:
    """uid, key, rank: 0-based global ranks. Equal keys share the lowest rank, or with ``unique`` follow (key, row, column, position)."""
    _, columns = grid(p)
    cells = _cells(state, p)
    order = grid_order(columns) if unique else [F.col("key")]
    # Smaller column elements in the cell: a running sum, as row elements stand before the column elements that equal them. One sort, one frame.
    before = Window.partitionBy("cr", "cc").orderBy(*order, "role").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    counted = cells.withColumn("_less", F.sum("role").over(before))
    return counted.where("role = 0").groupBy("pe", "uid").agg(F.first("key").alias("key"), F.sum("_less").alias("rank")).select("pe", "uid", "key", "rank")


def grid_rank_sort(state: DataFrame, p: int, deliver: bool = True, cubes: int = 1) -> SortResult:
    """Unique ranks, then delivery: rank i belongs to PE i * p div n.

    Each column holds a copy of all elements and keeps those bound for itself; they then travel down the
    column, bit by bit of the row. Without ``deliver`` elements stay where they are.
    """
    spark, method, ledger = state.sparkSession, "grid_rank_sort", []
    rows, columns = grid(p)
    sizes = per_cube([max(n, 1) for n in cube_sizes(state, p, cubes)], p).cast("long")
    at = staged(grid_rank(state, p, unique=True), "grid")
    d_rows, d_columns = (log2(rows), log2(columns)) if rows & (rows - 1) == 0 and columns & (columns - 1) == 0 else (rows - 1, columns - 1)
    loads = [state.groupBy(cube_of(p).alias("cube"), F.expr(line).alias("g")).count().groupBy("cube").agg(F.max("count").alias("m")).collect() for line in (f"pe div {columns}", f"pe % {columns}")]
    row_load, column_load = ([{r.cube: r.m for r in found}.get(c, 0) for c in range(cubes)] for found in loads)
    ledger.append(costs.collective_rows(spark, method, 0, p * cubes, d_rows + d_columns, [a + b for a, b in zip(row_load, column_load, strict=True)]))
    ledger.append(costs.collective_rows(spark, method, 1, p * cubes, d_columns, row_load))
    placed = at.withColumn("_n", sizes).withColumn("dst", F.expr(f"cast(cast(pe div {p} AS int) * {p} + rank * {p} div _n AS int)")).drop("_n")
    if not deliver:
        return SortResult(placed.select("pe", "rank", "key", "uid", F.col("dst").alias("dst_pe")), costs.union(ledger, spark))
    # The copy kept is the one in the element's own row and its target's column.
    now = placed.select((F.expr(f"pe div {columns}") * columns + F.col("dst") % columns).cast("int").alias("pe"), "rank", "key", "uid", "dst")
    if rows & (rows - 1) == 0:
        shift = log2(columns)
        for step, j in enumerate(range(log2(rows) - 1, -1, -1)):
            bit = j + shift
            now = cube.exchange(now, cube.with_bit(F.col("pe"), bit, F.shiftright("dst", bit).bitwiseAND(F.lit(1)) == 1), method, 2 + step, p * cubes, ledger)
    else:
        now = cube.exchange(now, F.col("dst"), method, 2, p * cubes, ledger)
    return SortResult(now.select("pe", "rank", "key", "uid"), costs.union(ledger, spark))
