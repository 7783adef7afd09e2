"""Random redistribution of elements, as a function of (uid, seed)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import uid_hash
from . import costs, cube
from .placement import cube_of, local_positions, log2


def direct(state: DataFrame, p: int, seed: int = 1, ledger: list[DataFrame] | None = None, step: int = 0, method: str = "shuffle_direct", cubes: int = 1, positions: bool = False) -> DataFrame:
    """Each element to a random PE (of its machine) in one exchange: up to p startups a PE."""
    to = cube_of(p) * p + uid_hash("uid", seed) % p
    return cube.exchange(state, to, method, step, p * cubes, [] if ledger is None else ledger, positions=positions)


def by_dimension(state: DataFrame, p: int, seed: int = 1, ledger: list[DataFrame] | None = None, step: int = 0, method: str = "shuffle_cube", exact_halves: bool = False, cubes: int = 1) -> DataFrame:
    """In each dimension a random half of each PE's elements changes sides: log p startups. For small inputs.

    A coin per element and dimension decides, or with ``exact_halves`` the lower half by hash.
    """
    notes = [] if ledger is None else ledger
    for k, j in enumerate(range(log2(p) - 1, -1, -1)):
        if exact_halves:
            coin = local_positions(state.withColumn("_h", uid_hash("uid", seed + 17 * j)).withColumnRenamed("key", "_key").withColumnRenamed("_h", "key"))
            coin = coin.withColumn("_one", (F.col("pos") * 2 <= F.col("m")) == (F.shiftright("pe", j).bitwiseAND(F.lit(1)) == 0)).withColumnRenamed("key", "_h").withColumnRenamed("_key", "key").drop("_h", "pos", "m")
            state = cube.exchange(coin, cube.with_bit(F.col("pe"), j, F.col("_one")), method, step + k, p * cubes, notes).drop("_one")
        else:
            one = F.shiftright(uid_hash("uid", seed + 17 * j), 7).bitwiseAND(F.lit(1)) == 1
            state = cube.exchange(state, cube.with_bit(F.col("pe"), j, one), method, step + k, p * cubes, notes)
    return state


def ledger_of(state: DataFrame, p: int, seed: int = 1, how: str = "direct") -> DataFrame:
    notes: list[DataFrame] = []
    (direct if how == "direct" else by_dimension)(state, p, seed, notes)
    return costs.union(notes, state.sparkSession)
