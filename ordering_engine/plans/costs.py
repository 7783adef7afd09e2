"""The cost ledger, its measures, and predicted costs.

A ledger row is (method, step, pe, startups, words_out, words_in, held_after). A PE's startups in a step
are its distinct partners, both ways; words count elements times words per element. Steps follow each
other, so a measure takes the maximum over PEs in each step and adds the steps up.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .placement import per_cube

COLUMNS = "method string, step int, pe int, startups bigint, words_out bigint, words_in bigint, held_after bigint"


def empty(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], COLUMNS)


def exchange_rows(moved: DataFrame, method: str, step: int, p: int, dense: bool = False, words: int = 1) -> DataFrame:
    """Ledger of one exchange from rows with ``src`` and ``pe`` (their destination). ``dense``: every PE pays for all peers."""
    sent = moved.groupBy("src", "pe").agg(F.count(F.lit(1)).alias("c")).withColumn("x", (F.col("src") != F.col("pe")).cast("long"))
    # A pair of PEs counts at both of its ends; PEs without any part have a row of zeros.
    ends = sent.select(F.explode(F.expr("array(struct(src AS pe, x AS n, x * c AS wo, 0L AS wi, 0L AS h), struct(pe AS pe, x AS n, 0L AS wo, x * c AS wi, c AS h))")).alias("e")).select("e.*")
    every = moved.sparkSession.range(p).select(F.col("id").cast("int").alias("pe"), *[F.lit(0).cast("long").alias(c) for c in ("n", "wo", "wi", "h")])
    per = ends.select(F.col("pe").cast("int").alias("pe"), "n", "wo", "wi", "h").unionByName(every).groupBy("pe").agg(*[F.sum(c).alias(c) for c in ("n", "wo", "wi", "h")])
    startups = F.lit(p - 1) if dense else F.col("n")
    return per.select(F.lit(method).alias("method"), F.lit(step).alias("step"), "pe", startups.cast("long").alias("startups"), (F.col("wo") * words).alias("words_out"), (F.col("wi") * words).alias("words_in"), F.col("h").alias("held_after"))


def collective_rows(spark: SparkSession, method: str, step: int, p: int, rounds: int, words: int | list[int]) -> DataFrame:
    """Ledger of a collective: ``rounds`` startups on every PE and ``words`` both ways (a list: those of machines side by side, p PEs in all)."""
    words = words if isinstance(words, list) else [words]
    sent = per_cube(words, p // len(words), "id").cast("long")
    return spark.range(p).select(F.lit(method).alias("method"), F.lit(step).alias("step"), F.col("id").cast("int").alias("pe"), F.lit(rounds).cast("long").alias("startups"), sent.alias("words_out"), sent.alias("words_in"), F.lit(None).cast("long").alias("held_after"))


def union(parts: list[DataFrame], spark: SparkSession) -> DataFrame:
    return reduce(DataFrame.unionByName, parts) if parts else empty(spark)


def per_step(ledger: DataFrame) -> DataFrame:
    return ledger.groupBy("method", "step").agg(F.max("startups").alias("startups"), F.max(F.greatest("words_out", "words_in")).alias("words"), F.max("held_after").alias("held"), F.sum("words_out").alias("moved"))


def startups(ledger: DataFrame) -> DataFrame:
    return per_step(ledger).groupBy("method").agg(F.sum("startups").alias("startups"))


def volume(ledger: DataFrame) -> DataFrame:
    return per_step(ledger).groupBy("method").agg(F.sum("words").alias("words"))


def max_fan_in(moved: DataFrame) -> DataFrame:
    """Distinct senders of the busiest receiver, from rows with ``src`` and ``pe``."""
    return moved.where("src <> pe").groupBy("pe").agg(F.countDistinct("src").alias("senders")).agg(F.coalesce(F.max("senders"), F.lit(0)).alias("max_fan_in"))


def predict(ledger: DataFrame, alpha: float, beta: float) -> DataFrame:
    """alpha * startups + beta * words, summed over steps."""
    return per_step(ledger).groupBy("method").agg(F.sum(alpha * F.col("startups") + beta * F.col("words")).alias("time"))


def spark_metrics(df: DataFrame) -> DataFrame:
    """(metric, value) after running ``df``'s own plan: its exchanges, and the rows written to them."""
    execution = df._jdf.queryExecution()
    execution.toRdd().count()
    found, todo = {"exchanges": 0, "rows_exchanged": 0}, [execution.executedPlan()]
    while todo:
        node = todo.pop()
        kind = node.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
            continue
        if kind.endswith("QueryStageExec"):
            todo.append(node.plan())
            continue
        if kind == "ShuffleExchangeExec":
            found["exchanges"] += 1
            found["rows_exchanged"] += node.metrics().apply("shuffleRecordsWritten").value()
        children = node.children()
        todo += [children.apply(i) for i in range(children.size())]
    return df.sparkSession.createDataFrame(list(found.items()), "metric string, value bigint")


def time_per_element(seconds: float, n: float, p: int) -> float:
    """Microseconds of a run per element of a PE, the published axis."""
    return seconds * 1e6 / (n / p)


def local_work(n: float | Column, p: int) -> float | Column:
    """Of a number, or of a column of them, as the other formulas here."""
    return n / p * (F.log2(F.greatest(n, F.lit(2.0))) if isinstance(n, Column) else math.log2(max(n, 2)))


def kway_lower_bound(n: float | Column, p: int, k: int, alpha: float, beta: float) -> float | Column:
    """Local work, plus each word moved and k messages sent once per level."""
    levels = math.log(p, k) if p > 1 else 0
    return local_work(n, p) + beta * n / p * levels + alpha * k * levels


def imbalance_bound(n: float | Column, p: int, gamma: float) -> float | Column:
    """Bound of the product over levels of 1 + (2^i / n)^gamma."""
    return (F.exp if isinstance(n, Column) else math.exp)((p / n) ** gamma / (2**gamma - 1))


#: Latency and volume terms of each method, of n, p and fan-out k.
TERMS = {
    "gather_merge": (lambda n, p, k: math.log2(p), lambda n, p, k: n),
    "all_gather_merge": (lambda n, p, k: math.log2(p), lambda n, p, k: n * 2),
    "grid_rank": (lambda n, p, k: math.log2(p), lambda n, p, k: n / math.sqrt(p)),
    "bitonic": (lambda n, p, k: math.log2(p) ** 2, lambda n, p, k: n / p * math.log2(p) ** 2),
    "one_per_pe_quicksort": (lambda n, p, k: math.log2(p) ** 2, lambda n, p, k: math.log2(p) ** 2),
    "cube_quicksort": (lambda n, p, k: math.log2(p) ** 2, lambda n, p, k: n / p * math.log2(p)),
    "median_of_medians_quicksort": (lambda n, p, k: math.log2(p) ** 2, lambda n, p, k: p + n / p * math.log2(p)),
    "robust_cube_quicksort": (lambda n, p, k: math.log2(p) ** 2, lambda n, p, k: n / p * math.log2(p)),
    "kway_cube": (lambda n, p, k: k * math.log(p, k), lambda n, p, k: p + n / p * math.log(p, k)),
    "multilevel_samplesort": (lambda n, p, k: k * math.log(p, k), lambda n, p, k: n / p * math.log(p, k)),
    "direct_samplesort": (lambda n, p, k: p, lambda n, p, k: n / p + p),
    "exact_split_mergesort": (lambda n, p, k: p, lambda n, p, k: n / p + p * math.log2(p)),
}


def cost(method: str, n: float | Column, p: int, alpha: float, beta: float, k: int = 64) -> float | Column:
    latency, words = TERMS[method]
    return alpha * latency(n, p, k) + beta * words(n, p, k) + local_work(n, p) / 1000 * beta


def rank_methods(spark: SparkSession, p: int, loads: list[float] | DataFrame, alpha: float, beta: float, k: int = 64) -> DataFrame:
    """Every method's predicted time over the loads n/p (a list, or a table with ``n_over_p``), with its place among all."""
    if not isinstance(loads, DataFrame):
        loads = spark.createDataFrame([(float(x),) for x in loads], "n_over_p double")
    x = F.col("n_over_p")
    times = [F.struct(F.lit(m).alias("method"), (F.lit(0.0) + cost(m, x * float(p), p, alpha, beta, k)).alias("time")) for m in TERMS]
    df = loads.select("n_over_p", F.inline(F.array(*times))).where("method <> 'one_per_pe_quicksort' or n_over_p = 1").select("method", "n_over_p", "time")
    return df.withColumn("place", F.row_number().over(Window.partitionBy("n_over_p").orderBy(F.round("time", 9), "method")))


def crossover(a: str, b: str, p: int, alpha: float, beta: float, k: int = 64, low: float = 3**-5, high: float = 2**23) -> float | None:
    """The load n/p where b becomes cheaper than a, by bisection; None if it never does."""
    gap = lambda x: cost(a, x * p, p, alpha, beta, k) - cost(b, x * p, p, alpha, beta, k)
    if gap(low) > 0:
        return low
    if gap(high) <= 0:
        return None
    for _ in range(80):
        mid = math.sqrt(low * high)
        low, high = (mid, high) if gap(mid) <= 0 else (low, mid)
    return high
