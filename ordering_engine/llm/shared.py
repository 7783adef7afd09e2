"""Helpers that several corpus operators use: shared storage and Arrow text access."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import settled, shared_dir  # noqa: F401
from ..storage import staged as materialize  # noqa: F401

#: Odd constants of a public 64-bit mixing function.
MIX_1, MIX_2, STEP = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()

#: What this Python worker keeps from task to task: one thing at most, whichever operator it belongs to.
_kept: dict[tuple, object] = {}


def kept(key: tuple, make: Callable[[], object]) -> object:
    """What ``make`` gives, once per worker process and key. It takes the place of what the worker kept before, which goes first."""
    if key not in _kept:
        _kept.clear()
        _kept[key] = make()
    return _kept[key]


def keep_nothing() -> None:
    """For tasks that keep nothing: Spark uses workers again, and what an operator before kept there would add to this one's memory."""
    _kept.clear()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def lower_ascii(text: Column) -> Column:
    """Lower-case A-Z only. ``lower`` does the same where every character is one byte, and is faster."""
    return F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def raw_texts(column: pa.Array | pa.ChunkedArray) -> Iterator[bytes]:
    """UTF-8 bytes of each text, null as empty, one at a time."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    for value in column.cast(pa.large_binary()):
        yield value.as_py() or b""


def mixed(x: np.ndarray) -> np.ndarray:
    """A public one-to-one mixing of 64-bit numbers."""
    x = (x ^ (x >> np.uint64(30))) * MIX_1
    x = (x ^ (x >> np.uint64(27))) * MIX_2
    return x ^ (x >> np.uint64(31))
