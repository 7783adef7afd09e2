"""Order specifications, comparable keys for any of them, and dense global ranks."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

NUMERIC = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.DecimalType)
REAL = (T.FloatType, T.DoubleType)
UNORDERED = (T.MapType, T.VariantType)


@dataclass(frozen=True)
class By:
    """One sort column: its name, direction and place of nulls."""

    column: str
    ascending: bool = True
    nulls_first: bool = True


def resolve(df: DataFrame, order) -> list[By]:
    """Validated list of sort columns; ``order`` is a name, a ``By`` or a list of them."""
    specs = [o if isinstance(o, By) else By(o) for o in (order if isinstance(order, (list, tuple)) else [order])]
    if not specs:
        raise ValueError("an order needs a column")
    for s in specs:
        kind = df.select(s.column).schema[0].dataType
        if isinstance(kind, UNORDERED):
            raise TypeError(f"{s.column}: {kind.simpleString()} has no order")
    return specs


def _flipped(c: Column, kind: T.DataType) -> Column:
    """A value whose ascending order is the descending order of ``c``."""
    if isinstance(kind, NUMERIC):
        return -c.cast(T.DecimalType(38, kind.scale if isinstance(kind, T.DecimalType) else 0))
    if isinstance(kind, REAL):
        return F.struct((~F.isnan(c)).alias("real"), F.when(F.isnan(c), F.lit(0.0)).otherwise(-c).alias("value"))
    if isinstance(kind, T.BooleanType):
        return ~c
    if isinstance(kind, T.DateType):
        return -F.unix_date(c)
    if isinstance(kind, T.TimestampType):
        return -F.unix_micros(c)
    if isinstance(kind, T.TimestampNTZType):
        return -F.unix_micros(c.cast("timestamp"))
    if isinstance(kind, (T.StringType, T.BinaryType)):
        # Complemented bytes with a closing 0xFF: longer strings come before their prefixes.
        return F.unhex(F.concat(F.translate(F.hex(c), "0123456789ABCDEF", "FEDCBA9876543210"), F.lit("FF")))
    raise TypeError(f"no descending key for {kind.simpleString()}")


def comparable(df: DataFrame, order) -> Column:
    """One column whose plain ascending order is the given order: the column itself where it is simple, else a struct."""
    specs = resolve(df, order)
    first = specs[0]
    if len(specs) == 1 and first.ascending and first.nulls_first:
        return F.col(first.column)
    parts = []
    for k, s in enumerate(specs):
        c, kind = F.col(s.column), df.select(s.column).schema[0].dataType
        value = c if s.ascending else _flipped(c, kind)
        parts.append(F.struct((c.isNull() if not s.nulls_first else c.isNotNull()).alias("late"), value.alias("value")).alias(f"k{k}"))
    return F.struct(*parts)


def sort_columns(df: DataFrame, order) -> list[Column]:
    out = []
    for s in resolve(df, order):
        c = F.col(s.column)
        out.append((c.asc_nulls_first() if s.nulls_first else c.asc_nulls_last()) if s.ascending else (c.desc_nulls_first() if s.nulls_first else c.desc_nulls_last()))
    return out


def global_rank(df: DataFrame, order, rank: str = "rank", tie: str | None = None, partitions: int | None = None) -> DataFrame:
    """Dense 0-based ranks by one range exchange, without a window.

    Rows are numbered where the exchange puts them, in sorted partitions; the prefix sums of the partitions' sizes (one row per
    partition) go to every row. The tie column, or the row's place in the input where there is none, takes part in the exchange,
    so equal keys spread over partitions.
    """
    from ..storage import staged

    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    keyed = df if tie else df.withColumn("__tie", F.monotonically_increasing_id())
    by = [*sort_columns(df, order), F.col(tie or "__tie").asc()]
    dealt = keyed.repartitionByRange(n, *by).sortWithinPartitions(*by).drop("__tie").withColumn("__at", F.monotonically_increasing_id())
    dealt = staged(dealt, "rank").withColumn("__part", F.shiftright("__at", 33))
    sizes = dealt.groupBy("__part").agg(F.count(F.lit(1)).alias("__n"))
    before = sizes.select("__part", F.coalesce(F.sum("__n").over(Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__before"))
    local = F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))
    return dealt.join(F.broadcast(before), "__part").withColumn(rank, F.col("__before") + local).drop("__part", "__at", "__before")
