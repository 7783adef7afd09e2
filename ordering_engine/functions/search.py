"""Binary search in a sorted array column, inside generated code and for keys of any ordered type."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def count_below(sorted_array: str, value: str) -> Column:
    """How many elements of ``sorted_array`` are below ``value``: 0 for a null array. One comparison per halving."""
    # The variables' names are this function's own: a column of the same name would be taken for them.
    halved = f"IF({sorted_array}[_within.lo + (_within.hi - _within.lo) div 2] < {value}, named_struct('lo', _within.lo + (_within.hi - _within.lo) div 2 + 1, 'hi', _within.hi), named_struct('lo', _within.lo, 'hi', _within.lo + (_within.hi - _within.lo) div 2))"
    # A constant number of steps, so that no array of steps is made per row; 30 are enough for any array.
    steps = f"slice(array({', '.join('0' * 30)}), 1, greatest(1, cast(ceil(log2(size({sorted_array}) + 1)) AS int)))"
    walk = f"aggregate({steps}, named_struct('lo', 0L, 'hi', cast(size({sorted_array}) AS bigint)), (_within, _step) -> IF(_within.lo < _within.hi, {halved}, _within), _within -> cast(_within.lo AS int))"
    return F.expr(f"IF({sorted_array} IS NULL OR size({sorted_array}) = 0, 0, {walk})")


def with_count_below(df: DataFrame, sorted_array: str, value: str, into: str, most: int) -> DataFrame:
    """``df`` with ``into``, the ``count_below`` for arrays of no more than ``most`` elements: one generated comparison a step, for many rows.

    Every step is a column of its own, which the optimizer leaves alone as the next uses it more than once.
    """
    names, step = ["_at0"], 1 << max(0, most.bit_length() - 1)
    df = df.withColumn("_at0", F.lit(0))
    while step:
        at, names = names[-1], [*names, f"_at{len(names)}"]
        # Beyond the array, and for a null one, the element is null and so not below.
        df = df.withColumn(names[-1], F.expr(f"IF(get({sorted_array}, {at} + {step - 1}) < {value}, {at} + {step}, {at})"))
        step //= 2
    return df.withColumn(into, F.col(names[-1])).drop(*names)
