"""Python functions and table functions where built-ins don't reach, Arrow-batched."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def searchsorted(splitters: list[float]):
    """Scalar function: the bucket of a value, by binary search in the splitters."""
    edges = np.array(sorted(splitters))

    @F.pandas_udf("int")
    def place(values: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(edges, values.to_numpy(), "left").astype(np.int32))

    return place


def merge_runs(df: DataFrame, pe: str, run: str, key: str) -> DataFrame:
    """Per PE the k-way merge of its sorted runs: pe, pos, key. Bounded by what a PE holds."""

    def merge(block: pa.Table) -> pa.Table:
        frame = block.to_pandas()
        runs = [g[key].sort_values().tolist() for _, g in frame.groupby(run)]
        merged = list(heapq.merge(*runs))
        return pa.table({"pe": pa.array([int(frame[pe].iloc[0])] * len(merged), pa.int32()), "pos": pa.array(range(1, len(merged) + 1), pa.int64()), "key": pa.array(merged, pa.float64())})

    return df.groupBy(pe).applyInArrow(merge, "pe int, pos bigint, key double")


def classify_batches(df: DataFrame, key: str, splitters: list[float]) -> DataFrame:
    """Counts per bucket of every batch, so that no row grows; add them up by bucket."""
    edges = np.array(sorted(splitters))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = np.bincount(np.searchsorted(edges, batch.column(0).to_numpy(zero_copy_only=False), "left"), minlength=len(edges) + 1)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(n)), pa.int32()), pa.array(n, pa.int64())], names=["bucket", "cnt"])

    return df.select(key).mapInArrow(count, "bucket int, cnt bigint").groupBy("bucket").agg(F.sum("cnt").alias("cnt"))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def median_window(values: pd.Series) -> list:
    """Aggregate: the two middle values of a group of even size, or the middle one twice."""
    v = np.sort(values.to_numpy(dtype=float))
    return [float(v[(len(v) - 1) // 2]), float(v[len(v) // 2])]


@F.udtf(returnType=T.StructType().add("round", T.IntegerType()).add("pe", T.IntegerType()).add("partner", T.IntegerType()))
class CubeSchedule:
    """Rounds of the hypercube template for 2^d PEs, highest dimension first."""

    def eval(self, d: int):
        for k in range(d):
            for pe in range(1 << d):
                yield k, pe, pe ^ (1 << (d - 1 - k))


@F.udtf(returnType=T.StructType([T.StructField(c, T.IntegerType()) for c in ("phase", "dim", "pe", "partner")]).add("ascending", T.BooleanType()))
class BitonicSchedule:
    """Phases and dimensions of the bitonic network for 2^d PEs."""

    def eval(self, d: int):
        for s in range(d):
            for j in range(s, -1, -1):
                for pe in range(1 << d):
                    yield s, j, pe, pe ^ (1 << j), (pe >> (s + 1)) & 1 == 0


@F.udtf
class SortedBy:
    """``sorted_by(TABLE t PARTITION BY ... ORDER BY ...)``: the rows as they come, with their place in the partition."""

    @staticmethod
    def analyze(rows):
        from pyspark.sql.udtf import AnalyzeResult

        schema = T.StructType().add("place", T.IntegerType())
        for f in rows.dataType.fields:
            schema = schema.add(f.name, f.dataType)
        return AnalyzeResult(schema=schema)

    def __init__(self):
        self.place = 0

    def eval(self, row):
        self.place += 1
        yield (self.place, *row)


def register(spark: SparkSession) -> None:
    spark.udtf.register("cube_schedule", CubeSchedule)
    spark.udtf.register("bitonic_schedule", BitonicSchedule)
    spark.udtf.register("sorted_by", SortedBy)
    spark.udf.register("median_window", median_window)
