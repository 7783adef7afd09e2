"""Event-time operators; a stream is any streaming DataFrame with a timestamp column.

Each takes and returns a DataFrame and works on batches as well. ``replay`` lays a table out as files that arrive one after another, and
``run`` takes a stream over them to its end. Results are Parquet folders by micro-batch: a batch that runs again after a failure
replaces its own folder, so every row is there once, and nothing is held by the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from .. import storage


def files(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def stamped(df: DataFrame, column: str = "ts") -> DataFrame:
    """Zone-less timestamps read as UTC instants."""
    return df.withColumn(column, F.col(column).cast("timestamp"))


def with_lateness(df: DataFrame, delay: str, column: str = "ts") -> DataFrame:
    return df.withWatermark(column, delay)


def tumbling(df: DataFrame, width: str, *aggregates, column: str = "ts", keys: tuple[str, ...] = ()) -> DataFrame:
    return df.groupBy(F.window(column, width).alias("w"), *keys).agg(*aggregates)


def sliding(df: DataFrame, width: str, slide: str, *aggregates, column: str = "ts", keys: tuple[str, ...] = ()) -> DataFrame:
    return df.groupBy(F.window(column, width, slide).alias("w"), *keys).agg(*aggregates)


def session(df: DataFrame, gap: str, *aggregates, column: str = "ts", keys: tuple[str, ...] = ()) -> DataFrame:
    return df.groupBy(F.session_window(column, gap).alias("w"), *keys).agg(*aggregates)


def dedup(df: DataFrame, *keys: str, streaming: bool = True) -> DataFrame:
    return df.dropDuplicatesWithinWatermark(list(keys)) if streaming else df.dropDuplicates(list(keys))


def enrich(stream: DataFrame, static: DataFrame, on) -> DataFrame:
    """Stream with a table; the table is broadcast only if Spark's size check lets it."""
    return stream.join(static, on, "left")


def pair(a: DataFrame, b: DataFrame, key: str, after: str, at_most: str, column: str = "ts") -> DataFrame:
    """Rows of b within ``at_most`` after a row of a with the same key; both sides need a watermark when streaming."""
    x = a.select(*[F.col(c).alias(f"a_{c}") for c in a.columns])
    y = b.select(*[F.col(c).alias(f"b_{c}") for c in b.columns])
    near = F.expr(f"b_{column} > a_{column} + INTERVAL {after} AND b_{column} <= a_{column} + INTERVAL {at_most}")
    return x.join(y, (F.col(f"a_{key}") == F.col(f"b_{key}")) & near)


class _TopK(StatefulProcessor):
    """Keeps each key's k largest values."""

    def __init__(self, k: int):
        self.k = k

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.best = handle.getValueState("best", "values array<double>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        held = list(self.best.get()[0]) if self.best.exists() else []
        for frame in rows:
            held += frame["value"].tolist()
        held = sorted(held, reverse=True)[: self.k]
        self.best.update((held,))
        yield pd.DataFrame({"key": [str(key[0])] * len(held), "place": list(range(1, len(held) + 1)), "value": held})

    def close(self) -> None:
        pass


class _Median(StatefulProcessor):
    """Keeps each key's window of middle values: exact until ``keep`` values have come, then the middle ones and how many lie beyond."""

    def __init__(self, keep: int):
        self.keep = keep

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("window", "low bigint, high bigint, values array<double>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        low, high, held = (self.state.get() if self.state.exists() else (0, 0, []))
        held = list(held)
        for frame in rows:
            for v in frame["value"].tolist():
                if held and low and v < held[0]:
                    low += 1
                elif held and high and v > held[-1]:
                    high += 1
                else:
                    held.append(v)
            held.sort()
            while len(held) > self.keep:
                if low <= high:
                    held.pop(0)
                    low += 1
                else:
                    held.pop()
                    high += 1
        self.state.update((low, high, held))
        at = min(max((low + high + len(held) - 1) // 2 - low, 0), len(held) - 1)
        yield pd.DataFrame({"key": [str(key[0])], "seen": [low + high + len(held)], "median": [held[at]]})

    def close(self) -> None:
        pass


def topk_state(stream: DataFrame, key: str, value: str, k: int) -> DataFrame:
    rows = stream.select(F.col(key).cast("string").alias("key"), F.col(value).cast("double").alias("value"))
    return rows.groupBy("key").transformWithStateInPandas(_TopK(k), "key string, place int, value double", "Update", "None")


def median_state(stream: DataFrame, key: str, value: str, keep: int = 64) -> DataFrame:
    rows = stream.select(F.col(key).cast("string").alias("key"), F.col(value).cast("double").alias("value"))
    return rows.groupBy("key").transformWithStateInPandas(_Median(keep), "key string, seen bigint, median double", "Update", "None")


def sort_batches(stream: DataFrame, order, path: str, p: int = 16):
    """Every micro-batch totally ordered by the method that fits its size and written as one sorted set of files.

    A batch that the published thresholds would gather on one PE is sorted by one task, any other by a range exchange.
    """
    from ..functions.keys import global_rank
    from ..plans import selector

    def each(batch: DataFrame, number: int) -> None:
        few = selector.choose(batch.count(), p) == "gather_merge"
        ranks = global_rank(batch, order, partitions=1 if few else p)
        ranks.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/part={number}")

    return stream.writeStream.foreachBatch(each)


def _to_end(writer, folder: str, trigger: dict | None) -> None:
    query = writer.trigger(**(trigger or {"availableNow": True})).option("checkpointLocation", f"{folder}/checkpoint").start()
    query.awaitTermination()


def run(stream: DataFrame, name: str, mode: str = "append", trigger: dict | None = None, keys: tuple[str, ...] = (), folder: str | None = None) -> DataFrame:
    """Run to the end of what is there; the result read from shared storage.

    In mode ``complete`` the result is that of the last micro-batch; in ``update`` with ``keys``, each key's rows of the last batch
    that had any. With a ``folder`` used before, the stream goes on where it ended there.
    """
    spark, fields = stream.sparkSession, stream.schema
    folder = folder or storage.folder(spark, f"streams/{name}")

    def each(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/batch={number}")

    _to_end(stream.writeStream.outputMode(mode).foreachBatch(each), folder, trigger)
    out = spark.read.schema(T.StructType([*fields.fields, T.StructField("batch", T.LongType())])).parquet(f"{folder}/out")
    if mode == "complete":
        out = out.where(F.col("batch") == (out.agg(F.max("batch")).first()[0] or 0))
    elif mode == "update" and keys:
        last = out.groupBy(*keys).agg(F.max("batch").alias("batch"))
        out = out.join(last, [*keys, "batch"], "left_semi")
    return out.select(*fields.fieldNames())


def with_late_rows(stream: DataFrame, delay: str, name: str, column: str = "ts", trigger: dict | None = None, folder: str | None = None) -> DataFrame:
    """All rows with ``late``: whether their time was more than ``delay`` before the latest of earlier micro-batches when they came.

    These are the rows that a watermark would drop; here they are kept apart and can be counted. The latest time so far is read from
    the batches written before, so a restart finds it.
    """
    spark, fields = stream.sparkSession, stream.schema
    folder = folder or storage.folder(spark, f"streams/{name}")
    schema = T.StructType([*fields.fields, T.StructField("late", T.BooleanType()), T.StructField("batch", T.LongType())])

    def each(batch: DataFrame, number: int) -> None:
        latest = None
        if number:
            latest = spark.read.schema(schema).parquet(f"{folder}/out").where(F.col("batch") < number).agg(F.max(column)).first()[0]
        late = F.lit(False) if latest is None else F.coalesce(F.col(column) < F.lit(latest) - F.expr(f"INTERVAL {delay}"), F.lit(False))
        batch.withColumn("late", late).write.mode("overwrite").parquet(f"{folder}/out/batch={number}")

    _to_end(stream.writeStream.foreachBatch(each), folder, trigger)
    return spark.read.schema(schema).parquet(f"{folder}/out").drop("batch")


def replay(spark: SparkSession, df: DataFrame, parts: int, order) -> str:
    """Write ``df`` as ``parts`` files of equal size in order, one after the other, for ``files`` to stream one by one."""
    from ..functions.keys import global_rank

    path = storage.folder(spark, "replay/files")
    ranked = global_rank(df, order, "__place")
    n = max(ranked.count(), 1)
    for k in range(parts):
        part = ranked.where(f"__place * {parts} div {n} = {k}").orderBy("__place").drop("__place")
        part.coalesce(1).write.mode("append").parquet(path)
    return path
