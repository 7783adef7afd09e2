"""The generated data source, late rows, the stateful median, and splitting helpers."""

import numpy as np
from pyspark.sql import functions as F

from ordering_engine.operators import aggregates, joins
from ordering_engine.plans.samplesort import assign, fan_outs
from ordering_engine.sources import inputs, io
from ordering_engine.streaming import events as stream


def test_generated_source_matches_the_formula(spark):
    io.register_instances(spark)
    got = spark.read.format("order_instance").option("n", 500).option("p", 8).load()
    want = inputs.make("uniform", spark.range(500).select(F.col("id").alias("uid")), 8)
    assert got.exceptAll(want).isEmpty() and got.count() == 500


def test_late_rows_are_dropped(spark, tmp_path):
    rows = [(1, "2024-01-01 10:00:00"), (2, "2024-01-01 12:00:00"), (3, "2024-01-01 10:05:00"), (4, "2024-01-01 12:01:00")]
    schema = "id int, ts timestamp"
    for k, r in enumerate(rows):
        spark.createDataFrame([r], "id int, ts string").select("id", F.col("ts").cast("timestamp").alias("ts")).coalesce(1).write.parquet(str(tmp_path / "in" / str(k)))
        counted = None
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    counted = stream.tumbling(stream.with_lateness(source, "10 minutes"), "1 hour", F.count(F.lit(1)).alias("n"))
    out = stream.run(counted, "late_rows", "update").groupBy("w").agg(F.max("n").alias("n")).collect()
    assert sum(r.n for r in out) in (3, 4)  # the row of 10:05 is late if it comes after the one of 12:00 was counted


def test_streaming_median_is_near(spark, small):
    rows = spark.read.parquet(f"{small}/events.parquet").select("event_id", "event_type", "value")
    source = stream.files(spark, stream.replay(spark, rows, 2, "event_id"), rows.schema, per_trigger=2)
    provider = "spark.sql.streaming.stateStore.providerClass"
    spark.conf.set(provider, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        got = {r.key: r for r in stream.run(stream.median_state(source, "event_type", "value", 1000), "medians", "update").collect()}
    finally:
        spark.conf.unset(provider)
    for kind, group in rows.toPandas().groupby("event_type"):
        assert got[kind].seen == len(group) and got[kind].median == sorted(group.value)[(len(group) - 1) // 2]


def test_assignment_is_contiguous_and_least():
    rng = np.random.default_rng(2)
    for _ in range(50):
        counts, k = rng.integers(0, 50, 12).tolist(), int(rng.integers(1, 6))
        to = assign(counts, k)
        loads = [sum(c for c, g in zip(counts, to) if g == i) for i in range(k)]
        assert to == sorted(to) and max(to) < k
        # No smaller bound lets a left-to-right scan finish with k groups.
        bound, groups, load = max(loads) - 1, 1, 0
        for c in counts:
            groups, load = (groups + 1, c) if load + c > bound else (groups, load + c)
        assert groups > k or max(counts) > bound
    assert fan_outs(64, 3) == [4, 4, 4] and fan_outs(32, 2) == [8, 4] and np.prod(fan_outs(512, 3)) == 512


def test_joins_and_buckets(spark):
    left = spark.createDataFrame([(1, 5, "a"), (2, 9, "a"), (3, 1, "b")], "id int, t int, k string")
    right = spark.createDataFrame([(4, "a", 40), (5, "a", 50), (8, "a", 80)], "t int, k string, v int")
    got = {r.id: r.last for r in joins.asof(left, right, "t", ["k"], "v", "last").collect()}
    assert got == {1: 40, 2: 80, 3: None}
    got = {r.id: r.last for r in joins.asof(left, right, "t", ["k"], "v", "last", strict=False).collect()}
    assert got[1] == 50
    many = [float(x) for x in range(0, 100, 5)]
    few = spark.range(100).select(F.col("id").cast("double").alias("x"))
    assert [r.cnt for r in aggregates.bucket_counts(few, "x", many).orderBy("bucket").collect()] == [1] + [5] * 19 + [4]


def test_streams_go_on_after_a_stop_and_batches_are_written_once(spark, small, tmp_path):
    """The second run finds what the first has done; a batch that runs again replaces its own folder."""
    rows = spark.read.parquet(f"{small}/events.parquet").select("event_id", "ts", "event_type").withColumn("ts", F.col("ts").cast("timestamp"))
    first, second = rows.where("event_id % 2 = 0"), rows.where("event_id % 2 = 1")
    path, folder = str(tmp_path / "in"), str(tmp_path / "run")
    first.coalesce(1).write.parquet(path)
    counted = lambda: stream.files(spark, path, rows.schema).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    half = stream.run(counted(), "resumed", "complete", folder=folder).collect()
    assert sum(r.n for r in half) == first.count()
    second.coalesce(1).write.mode("append").parquet(path)
    whole = {r.event_type: r.n for r in stream.run(counted(), "resumed", "complete", folder=folder).collect()}
    assert whole == {r.event_type: r["count"] for r in rows.groupBy("event_type").count().collect()}
    again = stream.run(counted(), "resumed", "complete", folder=folder)
    assert {r.event_type: r.n for r in again.collect()} == whole


def test_late_rows_are_flagged_across_a_restart(spark, tmp_path):
    path, folder = str(tmp_path / "in"), str(tmp_path / "run")
    schema = "id int, ts timestamp"
    for k, rows in enumerate(([(1, "2024-01-01 10:00:00"), (2, "2024-01-01 12:00:00")], [(3, "2024-01-01 10:05:00"), (4, "2024-01-01 11:55:00"), (5, None)])):
        spark.createDataFrame(rows, "id int, ts string").select("id", F.col("ts").cast("timestamp").alias("ts")).coalesce(1).write.mode("append").parquet(path)
        out = stream.with_late_rows(stream.files(spark, path, schema), "10 minutes", "late", folder=folder)
    assert {r.id: r.late for r in out.collect()} == {1: False, 2: False, 3: True, 4: False, 5: False}


def test_intermediates_are_removed(spark, tmp_path):
    import os

    from ordering_engine import storage

    made = []

    def make():
        made.append(storage.staged(spark.range(5)).staged_at)
        return spark.read.parquet(made[0])

    out = storage.settled(spark, make, "out")
    assert out.count() == 5 and not os.path.exists(made[0]) and os.path.exists(out.staged_at)
    storage.remove(out.staged_at)
    assert not os.path.exists(out.staged_at)
