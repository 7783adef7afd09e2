"""Readers and writers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def table(spark: SparkSession, path: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A Parquet table, only the columns asked for."""
    df = spark.read.parquet(f"{path}/{name}.parquet")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, fmt: str, path: str, schema: T.StructType | str, **options) -> DataFrame:
    """Files of any built-in format with a stated schema, so that nothing is inferred by a second scan."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def write(df: DataFrame, fmt: str, path: str, mode: str = "overwrite", **options) -> None:
    df.write.format(fmt).mode(mode).options(**options).save(path)


def roundtrip(df: DataFrame, fmt: str, path: str, **options) -> DataFrame:
    write(df, fmt, path, **options)
    return read(df.sparkSession, fmt, path, df.schema, **options)


def stats(spark: SparkSession, path: str, name: str) -> DataFrame:
    """Row count, from footers where the source can push the count down."""
    return spark.read.parquet(f"{path}/{name}.parquet").agg(F.count(F.lit(1)).alias("n"))


def write_sorted(df: DataFrame, path: str, partitions: int, *by: Column | str) -> None:
    """Range-partitioned files, each sorted, file order following key order."""
    df.repartitionByRange(partitions, *by).sortWithinPartitions(*by).write.mode("overwrite").parquet(path)


def save_bucketed(df: DataFrame, name: str, buckets: int, key: str) -> DataFrame:
    """A table bucketed and sorted by key, so that joins on it need no exchange."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)
    return df.sparkSession.table(name)


def zone_map(spark: SparkSession, path: str, column: str) -> DataFrame:
    """Per file its smallest and largest value and number of rows."""
    return spark.read.parquet(path).groupBy(F.input_file_name().alias("file")).agg(F.min(column).alias("low"), F.max(column).alias("high"), F.count(F.lit(1)).alias("rows"))


def drain(df: DataFrame) -> None:
    """Run the plan and keep nothing: the sink for timing."""
    df.write.format("noop").mode("overwrite").save()


def register_instances(spark: SparkSession) -> None:
    """``spark.read.format("order_instance")``: generated inputs as a data source with options name, n, p, seed."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Part(InputPartition):
        def __init__(self, lo: int, hi: int):
            self.lo, self.hi = lo, hi

    class Reader(DataSourceReader):
        def __init__(self, options):
            self.n, self.p, self.seed = int(options.get("n", 1000)), int(options.get("p", 16)), int(options.get("seed", 42))

        def partitions(self):
            step = max(1, -(-self.n // 8))
            return [Part(lo, min(self.n, lo + step)) for lo in range(0, self.n, step)]

        def read(self, part):
            for uid in range(part.lo, part.hi):
                x = uid % 2147483647
                for a, s in ((48271, 13), (69621, 16), (39373, 11)):
                    x = (x * a + self.seed) % 2147483647
                    x ^= x >> s
                yield uid * self.p // self.n, x % 2147483647, uid

    class Source(DataSource):
        @classmethod
        def name(cls):
            return "order_instance"

        def schema(self):
            return "pe int, key bigint, uid bigint"

        def reader(self, schema):
            return Reader(self.options)

    spark.dataSource.register(Source)
