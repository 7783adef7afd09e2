"""The paper's experiments on the given tables: counted costs, balance and verdicts of methods over inputs and loads.

Every function returns a long table (method, input, p, n, n_over_p, startups, words, time, imbalance, verdict).
``time`` is the counted cost alpha * startups + beta * words of the ledger, in units of one word's transfer; wall clock
belongs to ``bench.py``. To it come ``time_per_load`` (time over n/p, the published axis), ``to_best`` (time over the
best method's of the same input and load) and, in ablations, ``ratio`` (time over the reference method's).

All inputs and loads of one method and number of PEs run as machines side by side in one plan, so an experiment takes one run per method,
whatever its number of cases. Beyond ``AT_ONCE`` elements the machines take turns, and what a run staged is removed after it.
"""

from __future__ import annotations

from functools import partial, reduce
from itertools import product

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import method_sql
from .plans import bitonic, gather, gridrank, kway, medians, placement, quicksort, samplesort, verify
from .sources import inputs
from .sources.io import table
from .storage import passing, settled, staged

#: A startup costs as much as so many words.
ALPHA, BETA = 1000.0, 1.0
#: A PE that would hold more than so many times the mean runs out of memory.
CAPACITY = 8.0
#: Most elements that sort side by side, for the disk that their rounds take; a machine that holds more runs alone.
AT_ONCE = 1 << 26

METHODS = {
    "gather_merge": gather.gather_merge_sort,
    "all_gather_merge": gather.all_gather_merge_sort,
    "grid_rank": gridrank.grid_rank_sort,
    "bitonic": bitonic.bitonic_sort,
    "robust_cube_quicksort": quicksort.robust_cube_quicksort,
    "plain_cube_quicksort": quicksort.plain_cube_quicksort,
    "kway_cube": kway.kway_cube_sort,
    "multilevel": partial(samplesort.multilevel_samplesort, levels=2),
    "multilevel_noties": partial(samplesort.multilevel_samplesort, levels=2, ties=False),
    "multilevel_noplan": partial(samplesort.multilevel_samplesort, levels=2, plan="prefix"),
    "multilevel_bounded": partial(samplesort.multilevel_samplesort, levels=2, plan="bounded"),
    "multilevel_l3": partial(samplesort.multilevel_samplesort, levels=3),
    "multilevel_noplan_l3": partial(samplesort.multilevel_samplesort, levels=3, plan="prefix"),
    "multilevel_bounded_l3": partial(samplesort.multilevel_samplesort, levels=3, plan="bounded"),
    "direct": samplesort.direct_samplesort,
    # Delivery alone: splitters that are known beforehand, for uniform keys.
    "direct_given": lambda s, p, cubes=1: samplesort.direct_samplesort(s, p, splitters=[i * inputs.V // p for i in range(1, p)], cubes=cubes),
}
SCHEMA = "method string, input string, p int, n bigint, n_over_p double, startups bigint, words bigint, time double, imbalance double, verdict string"


def summary(result: placement.SortResult, p: int) -> DataFrame:
    """Per machine: ``startups`` and ``words`` (the largest of a step, summed), ``last`` (the largest final load), ``most`` (the largest load ever)."""
    steps = result.ledger.groupBy(placement.cube_of(p).alias("cube"), "step").agg(F.max("startups").alias("s"), F.max(F.greatest("words_out", "words_in")).alias("w"), F.max("held_after").alias("h"))
    return steps.groupBy("cube").agg(F.sum("s").alias("startups"), F.sum("w").alias("words"), F.max_by("h", F.when(F.col("h").isNotNull(), F.col("step"))).alias("last"), F.max("h").alias("most"))


def measure(spark: SparkSession, d: str, cases: list[tuple[str, str, int, int | None]], base: str = "orders") -> DataFrame:
    """Run (method, input, p, n) cases; the first n rows of the base table by dense uid, or all. Cases that are equal are run once."""
    ids = {"orders": ["o_orderkey"], "lineitem": ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate"]}[base]
    runs, shared, rows = {}, {}, []
    with passing(spark):
        uids = settled(spark, lambda: placement.dense_uid(table(spark, d, base, ids), ids).select("uid"), "uids")
        most = uids.count()
        for method, name, p, n in cases:
            runs.setdefault((method, p), {})[(name, most if n is None else min(n, most))] = None
        for (method, p), wanted in runs.items():
            shared.setdefault((tuple(wanted), p), []).append(method)
        for (machines, p), methods in shared.items():
            for turn in turns(machines, AT_ONCE):
                with passing(spark):
                    made = inputs.make_many(turn, uids, p)
                    for method in methods:
                        with passing(spark):
                            rows += rated(method, made, turn, p)
    return spark.createDataFrame(rows, SCHEMA)


def turns(machines, most: int) -> list[list[tuple[str, int]]]:
    """Machines (name, n) in their order, in turns that hold no more than ``most`` elements or one machine."""
    out, load = [], 0
    for machine in machines:
        if not out or load + machine[1] > most:
            out, load = [*out, []], 0
        out[-1].append(machine)
        load += machine[1]
    return out


def rated(method: str, made: DataFrame, machines: list[tuple[str, int]], p: int) -> list[tuple]:
    """Rows of one method's run over machines side by side."""
    result, rows = METHODS[method](made, p, cubes=len(machines)), []
    for r in summary(result, p).collect():  # one row per machine
        name, n = machines[r.cube]
        stalled = r.cube in result.notes.get("stalled", ())
        factor = lambda held: (held or 0) * p / n  # noqa: B023, E731
        verdict = "no_progress" if stalled else "overflow" if factor(r.most) > CAPACITY else "imbalanced" if factor(r.most) > 2.0 else "ok"
        imbalance = 0.0 if method == "all_gather_merge" else round(factor(r["last"]) - 1, 4)
        rows.append((method, name, p, n, n / p, r.startups, r.words, ALPHA * r.startups + BETA * r.words, imbalance, verdict))
    return rows


def time_per_load(results: DataFrame) -> DataFrame:
    """With the time over the elements per PE, as published curves have it."""
    return results.withColumn("time_per_load", F.col("time") / F.col("n_over_p"))


def over(results: DataFrame, references: dict[str, str]) -> DataFrame:
    """With ``ratio``: a method's time over that of the reference named for it, for the same input, p and load; null for others."""
    base = results.select(F.col("method").alias("_m"), F.col("input").alias("_i"), F.col("p").alias("_p"), F.col("n").alias("_n"), F.col("time").alias("_t"))
    named = F.create_map(*[F.lit(x) for pair in references.items() for x in pair])[F.col("method")]
    same = (F.col("_m") == named) & (F.col("_i") == F.col("input")) & (F.col("_p") == F.col("p")) & (F.col("_n") == F.col("n"))
    return results.join(base, same, "left").withColumn("ratio", F.try_divide(F.col("time"), F.col("_t"))).drop("_m", "_i", "_p", "_n", "_t")


def vs_best(results: DataFrame) -> DataFrame:
    """With ``to_best``: time over the best one's for the same input, p and n; null where the best needs none."""
    return results.withColumn("to_best", F.try_divide(F.col("time"), F.min("time").over(Window.partitionBy("input", "p", "n"))))


def fluctuation(runs: DataFrame) -> DataFrame:
    """(max - min) / median of repeated times, from rows (method, seconds)."""
    return runs.groupBy("method").agg(((F.max("seconds") - F.min("seconds")) / F.median("seconds")).alias("fluctuation"))


def mirrored_trace(spark, d, p: int = 16, n: int = 4096) -> DataFrame:
    """Largest load over the mean after each round of quicksort with exact medians on the mirrored input: up to sqrt(p)."""
    uids = placement.dense_uid(table(spark, d, "orders", ["o_orderkey"]), ["o_orderkey"])
    state = inputs.make("mirrored", uids, p, n=min(n, uids.count()))
    result = quicksort.cube_quicksort(state, p, pivot="exact")
    return verify.imbalance_trace(result.ledger, state.count(), p).select("step", F.round("factor", 4).alias("factor"))


def median_fit(spark, d, sizes=(64, 128, 256, 512, 1024), trees=(("binary", 2), ("binary", 4), ("binary", 8), ("ternary", 3))) -> DataFrame:
    """Fit of the mean error by size, and the bias, over blocks of the customers' balances, for binary trees of several window sizes and the tree of threes."""
    based = placement.dense_uid(table(spark, d, "customer", ["c_custkey", "c_acctbal"]), ["c_custkey"])
    held = staged(based.select(F.col("c_acctbal").alias("key"), F.col("uid").cast("long").alias("uid")), "held")
    parts = []
    for tree, k in trees:
        ranks = staged(medians.study_of(held, list(sizes), k if tree == "binary" else 2, tree), "study")
        per = ranks.groupBy("n").agg(F.avg("error").alias("error"))
        truth = medians.bias(ranks).agg(F.round(F.avg("mean_over_half"), 6).alias("bias"))
        parts.append(medians.fit(per).crossJoin(truth).select(F.lit(tree).alias("tree"), F.lit(k).alias("k"), F.round("c", 3).alias("c"), F.round("gamma", 3).alias("gamma"), "bias"))
    return reduce(DataFrame.unionByName, parts)


def parameter_grid(spark, d, p: int = 16, levels=(1, 2), oversample=(4, 16), overpartition=(1, 4)) -> DataFrame:
    """Balance and cost of the multi-level method over its parameters, on all rows of orders."""
    uids = placement.dense_uid(table(spark, d, "orders", ["o_orderkey"]), ["o_orderkey"])
    n, rows = uids.count(), []
    state = inputs.make("uniform", uids, p, n=n)
    for setting in product(levels, oversample, overpartition):
        r = summary(samplesort.multilevel_samplesort(state, p, *setting), p).first()
        time = ALPHA * r.startups + BETA * r.words
        rows.append((*setting, r.startups, r.words, time, time / (n / p), round(r["last"] * p / n - 1, 4)))
    return spark.createDataFrame(rows, "levels int, oversample int, overpartition int, startups bigint, words bigint, time double, time_per_load double, imbalance double")


def whole_size_sweep(spark, d) -> DataFrame:
    """All methods over loads from 3^-5 to all that the table has rows for; equal sizes once."""
    names, methods = ("uniform", "bucket_sorted", "det_dupl", "staggered"), ("gather_merge", "all_gather_merge", "grid_rank", "bitonic", "robust_cube_quicksort", "kway_cube", "multilevel")
    loads = [3.0**-k for k in range(5, 0, -1)]
    sizes = [(p, n) for p, most in SWEEP for n in sorted({max(1, int(x * p)) for x in [*loads, *(2.0**k for k in range(most + 1))]})]
    return time_per_load(vs_best(measure(spark, d, [(m, i, p, n) for i in names for p, n in sizes for m in methods], base="lineitem")))


#: Numbers of PEs of the sweep over loads, and the power of two of the largest load.
SWEEP = ((64, 13),)


def mirrored_traces(spark, d, ps=(16, 64)) -> DataFrame:
    """``mirrored_trace`` over all rows of orders, for each p."""
    n = table(spark, d, "orders", ["o_orderkey"]).count()
    return reduce(DataFrame.unionByName, [mirrored_trace(spark, d, p, n).withColumn("p", F.lit(p)) for p in ps])


def crossed(methods, names, ps, base: str = "orders", references: dict[str, str] | None = None):
    """Every method on every input at every p, over all rows of the table; with ratios to reference methods."""

    def run(spark, d):
        found = time_per_load(vs_best(measure(spark, d, [(m, i, p, None) for p in ps for i in names for m in methods], base=base)))
        return over(found, references) if references else found

    return run


#: Over all rows of their tables, with the inputs and methods of the survey's workloads; README tells how long they take.
QUERIES = {
    "exp_size_sweep": whole_size_sweep,
    "exp_quicksort_robustness": crossed(("robust_cube_quicksort", "plain_cube_quicksort"), ("uniform", "bucket_sorted", "staggered", "det_dupl", "mirrored"), (16, 64), references={"robust_cube_quicksort": "plain_cube_quicksort"}),
    "exp_tie_ablation": crossed(("multilevel", "multilevel_noties"), ("uniform", "bucket_sorted", "staggered", "det_dupl", "zero"), (16,), "lineitem", {"multilevel": "multilevel_noties"}),
    "exp_plan_ablation": crossed(("multilevel_noplan_l3", "multilevel_bounded_l3", "multilevel_l3"), ("uniform", "bucket_sorted", "staggered", "det_dupl", "all_to_one"), (64, 512), "lineitem", {"multilevel_l3": "multilevel_noplan_l3", "multilevel_bounded_l3": "multilevel_noplan_l3"}),
    "exp_against_direct": crossed(("multilevel_l3", "direct", "direct_given"), ("uniform",), (16, 64, 256), "lineitem", {"direct": "multilevel_l3", "direct_given": "multilevel_l3"}),
    "exp_verdicts": crossed(METHODS, inputs.NAMES, (16,)),
    "exp_mirrored_trace": mirrored_traces,
    "exp_parameter_grid": parameter_grid,
    "exp_median_fit": median_fit,
}

SIZES, TREES = [64, 128, 256, 512, 1024], (("binary", 2), ("binary", 4), ("binary", 8), ("ternary", 3))
_BALANCES = "(SELECT c_acctbal AS key, row_number() OVER (ORDER BY c_custkey) - 1 AS uid FROM customer)"
ORACLE = {"exp_median_fit": " UNION ALL ".join(f"SELECT * FROM ({method_sql.study_fit(SIZES, k if tree == 'binary' else 2, tree, _BALANCES)})" for tree, k in TREES)}
