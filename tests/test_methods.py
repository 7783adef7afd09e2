"""Sorting methods on the ten inputs: order, permutation, balance; measures and claims in shape."""

import numpy as np
import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from ordering_engine import experiments
from ordering_engine.functions.keys import By, comparable, global_rank
from ordering_engine.plans import bitonic, costs, cube, delivery, gather, gridrank, kway, medians, mergesort, placement, quicksort, samplesort, selector, shuffling, verify
from ordering_engine.sources import inputs

P = 8


@pytest.fixture(scope="module")
def uids(spark):
    return spark.range(400).select(F.col("id").alias("uid"))


def held(uids, name, p=P, n=None):
    return inputs.make(name, uids, p, n=n)


def sound(result, state):
    return verify.order(result.data) and verify.permutation(result.data, state)


METHODS = {
    "gather": lambda s: gather.gather_merge_sort(s, P), "grid": lambda s: gridrank.grid_rank_sort(s, P), "bitonic": lambda s: bitonic.bitonic_sort(s, P), "first_pe": lambda s: quicksort.cube_quicksort(s, P),
    "robust": lambda s: quicksort.robust_cube_quicksort(s, P), "robust_cube_shuffle": lambda s: quicksort.robust_cube_quicksort(s, P, k=4, shuffle="cube"), "plain": lambda s: quicksort.plain_cube_quicksort(s, P), "kway": lambda s: kway.kway_cube_sort(s, P, 4),
    "multilevel": lambda s: samplesort.multilevel_samplesort(s, P, 2), "noties": lambda s: samplesort.multilevel_samplesort(s, P, 2, ties=False), "bounded": lambda s: samplesort.multilevel_samplesort(s, P, 2, plan="bounded"),
    "direct": lambda s: samplesort.direct_samplesort(s, P, shuffle_first=True), "exact": lambda s: mergesort.exact_split_mergesort(s, P), "irregular": lambda s: quicksort.irregular_quicksort(s, 6),
}


@pytest.mark.parametrize("method", METHODS)
def test_sorts_duplicates(uids, method):
    state = held(uids, "rand_dupl")
    assert sound(METHODS[method](state), state)


@pytest.mark.parametrize("name", ["zero", "mirrored", "all_to_one"])
def test_robust_methods_balance_hard_inputs(uids, name):
    state = held(uids, name)
    for method, most in (("robust", 0.6), ("multilevel", 0.5), ("exact", 0.02)):
        result = METHODS[method](state)
        assert sound(result, state) and verify.imbalance(result.data, P) <= most, method


@pytest.mark.parametrize("n", [0, 1, 7, 8, 9])
def test_tiny_inputs(spark, uids, n):
    state = held(uids, "uniform", n=n) if n else held(uids, "uniform", n=1).where("uid < 0")
    for method in ("robust", "grid", "multilevel", "bitonic", "exact"):
        assert sound(METHODS[method](state), state), method


def test_ties_and_shuffle_are_both_needed(uids):
    zero, mirrored = held(uids, "zero"), held(uids, "mirrored", 16)
    assert verify.imbalance(quicksort.plain_cube_quicksort(zero, P, shuffle="direct").data, P) == P - 1
    assert verify.imbalance(quicksort.plain_cube_quicksort(zero, P, tie="local").data, P) < 0.1
    assert samplesort.multilevel_samplesort(zero, P, 2, ties=False).verdict == "no_progress"
    trace = {r.step: r.factor for r in verify.imbalance_trace(quicksort.cube_quicksort(mirrored, 16, pivot="exact").ledger, 400, 16).collect()}
    assert 3.5 <= max(trace.values()) <= 4.6  # the square root of 16, half way through


def test_grid_ranks_follow_the_implied_order(uids):
    state = held(uids, "det_dupl")
    got = gridrank.grid_rank(state, P, unique=True).orderBy("uid").toPandas()
    rows = state.toPandas()
    _, columns = placement.grid(P)
    rows["r"], rows["c"] = rows.pe // columns, rows.pe % columns
    rows = rows.sort_values(["key", "r", "c", "uid"]).reset_index(drop=True)
    want = dict(zip(rows.uid, rows.index))
    assert all(want[u] == r for u, r in zip(got.uid, got["rank"]))
    shared = gridrank.grid_rank(state, P).toPandas()
    assert all(shared.groupby("key")["rank"].nunique() == 1)


def test_descending_and_mixed_orders(spark):
    rows = [(1, "a", 1.0), (2, "ab", float("nan")), (3, None, -0.0), (4, "b", 0.0), (5, "é", None)]
    df = spark.createDataFrame(rows, "uid bigint, s string, x double")
    for order in ([By("s", False)], [By("x", False, False), "uid"], [By("s", True, False)], [By("s", False, False), By("x")]):
        by_key = [r.uid for r in df.withColumn("_k", comparable(df, order)).orderBy("_k", "uid").collect()]
        by_rank = [r.uid for r in global_rank(df, order, tie="uid").orderBy("rank").collect()]
        assert by_key == by_rank
    with pytest.raises(TypeError):
        comparable(spark.sql("SELECT map(1, 2) AS m"), "m")


def test_messages_are_bounded(spark):
    p, k = 64, 4
    # All PEs hold small pieces of every group but the last, and the piece of group 0 of the late PEs is one element.
    pieces = spark.createDataFrame([(s, g, 1 if g == 0 and s < 49 else 40 if g == 0 else 16) for s in range(p) for g in range(k)], "src_pe int, grp int, cnt bigint")
    free, bound = delivery.fan_in(delivery.prefix(pieces, p, k)).toPandas(), delivery.fan_in(delivery.bounded_messages(pieces, p, k)).toPandas()
    assert free.received.sum() == bound.received.sum() == pieces.agg(F.sum("cnt")).first()[0]
    assert free.senders.max() > 3 * k + 2 >= bound.senders.max()
    assert delivery.choose(pieces, p, k)[0] == "bounded"


def test_median_trees(spark, uids):
    fit = medians.fit(medians.study(spark, [64, 256, 1024], 60).groupBy("n").agg(F.avg("error").alias("error"))).first()
    assert 0.3 <= fit.gamma <= 0.5
    state = held(uids, "uniform", 8)
    keys = np.sort([r.key for r in state.collect()])
    for how in ("binary_tree", "ternary_tree", "median_of_medians", "exact"):
        s = medians.pivots(state, how, 8, 3, 4, 1).first().s
        assert abs(np.searchsorted(keys, s) / 200 - 1) < (0.01 if how == "exact" else 0.4), how
    assert medians.binary_tree(state.where("pe = 3"), 8, 1, 2, 1).count() == 1  # empty subcubes have no pivot


@pytest.mark.parametrize("seed", [2, 3, 4, 5])
def test_ternary_pivots_of_permuted_leaves(uids, seed):
    state = held(uids, "uniform", 8)
    keys = np.sort([r.key for r in state.collect()])
    s = medians.pivots(state, "ternary_tree", 8, 3, 2, seed).first().s
    assert abs(np.searchsorted(keys, s) / 200 - 1) < 0.4


@pytest.mark.parametrize("method", ["grid_rank", "bitonic", "robust_cube_quicksort", "kway_cube", "multilevel_l3", "direct", "all_gather_merge"])
def test_machines_side_by_side_do_what_each_does_alone(uids, method):
    cases = [("uniform", 300), ("rand_dupl", 120), ("mirrored", 5)]
    together = experiments.METHODS[method](inputs.make_many(cases, uids, P), P, cubes=3)
    rows = {r.cube: r for r in experiments.summary(together, P).collect()}
    for c, (name, n) in enumerate(cases[:2]):
        alone = experiments.summary(experiments.METHODS[method](held(uids, name, n=n), P), P).first()
        assert tuple(rows[c])[1:] == tuple(alone)[1:], name


def test_experiment_columns(spark, small):
    found = experiments.measure(spark, small, [(m, i, 4, n) for m in ("gather_merge", "robust_cube_quicksort") for i in ("uniform", "zero") for n in (4, 64)])
    out = experiments.over(experiments.time_per_load(experiments.vs_best(found)), {"robust_cube_quicksort": "gather_merge"}).toPandas()
    assert len(out) == 8 and (out.time == 1000 * out.startups + out.words).all() and (out.time_per_load == out.time / (out.n / 4)).all()
    gather = out[out.method == "gather_merge"].set_index(["input", "n"])
    # Two rounds; the root receives from one PE in the first and from one in the second, half of all and then a quarter at most per sender.
    assert (gather.startups == 4).sum() == 0 or (gather.startups <= 4).all()
    for r in out.itertuples():
        same = out[(out.input == r.input) & (out.n == r.n)]
        assert r.to_best == r.time / same.time.min()
        assert r.method == "gather_merge" and np.isnan(r.ratio) or r.ratio == r.time / gather.time[(r.input, r.n)]


def test_samples_of_smallest_hashes_sort_few_rows(spark, uids, monkeypatch):
    """Ranked are few more rows than the sample takes, and the sample is that of a window over all; a group with bad hashes is taken whole."""
    state = spark.range(20_000).select((F.col("id") % 3).cast("int").alias("group"), F.col("id").alias("uid")).where("group < 2 or uid < 60")
    w = Window.partitionBy("group").orderBy(samplesort.uid_hash("uid", 5), "uid")
    expected = sorted(map(tuple, state.withColumn("_r", F.row_number().over(w)).where("_r <= 100").drop("_r").collect()))
    kept, stage = [], samplesort.staged
    monkeypatch.setattr(samplesort, "staged", lambda df, label: kept.append(stage(df, label)) or kept[-1])
    assert sorted(map(tuple, samplesort.smallest_hashes(state, "group", 100, 5).collect())) == expected
    assert len(expected) == 220 and kept[0].count() < 600
    monkeypatch.setattr(samplesort, "uid_hash", lambda uid, seed: (F.col(uid) + samplesort.PRIME - 30_000).cast("long"))
    assert samplesort.smallest_hashes(state, "group", 100, 5).count() == 220


def test_exact_splitters(uids):
    for name, n in (("rand_dupl", 400), ("zero", 400), ("uniform", 399), ("uniform", 7)):
        state = held(uids, name, n=n)
        elements = sorted((r.key, r.uid) for r in state.collect())
        want = sorted({elements[r] for r in {-(-i * n // P) for i in range(1, P)} - {n}})
        got, rounds = mergesort.exact_splitters(state, P, oversample=2, few=20)
        assert sorted(tuple(r) for r in got.collect()) == want and (rounds > 0) == (n > 20)
        r = mergesort.exact_split_mergesort(state, P)
        assert sound(r, state) and max(x.held for x in verify.loads(r.data, P).collect()) == -(-n // P)


def test_elements_move_once_a_round(uids):
    """One shuffle of the elements in a round of quicksort, none for pivots or splits."""
    at = placement.staged(placement.local_positions(held(uids, "rand_dupl")), "at")
    s = medians.pivots(at, "binary_tree", P, 3, 2, 1)
    from ordering_engine.plans import ties

    sided = ties.local_split(at.withColumn("subcube", cube.subcube(F.col("pe"), 3)).join(F.broadcast(s), "subcube", "left"))
    moved = placement.local_positions(sided.select("pe", "key", "uid", "left").withColumn("pe", F.when(F.col("left"), F.col("pe")).otherwise(F.col("pe") + 4)))
    plan = moved._jdf.queryExecution().executedPlan().toString()
    wide = [line for line in plan.splitlines() if "Exchange hashpartitioning" in line]
    assert sum("Window" in line for line in plan.splitlines()) <= 2 and sum("uid" in line for line in wide) <= 1


def test_routing_and_collectives(spark, uids):
    state = held(uids, "uniform").withColumn("dst", (F.col("uid") % P).cast("int"))
    routed, ledger = cube.route(state, "dst", P)
    assert routed.where("pe <> dst").count() == 0 and costs.startups(ledger).first()[1] <= 2 * 3
    values = spark.range(P).select(F.col("id").cast("int").alias("pe"), F.col("id").alias("value"))
    assert [r.value for r in cube.exclusive_scan(values).orderBy("pe").collect()] == [0, 0, 1, 3, 6, 10, 15, 21]
    assert {r.value for r in cube.all_reduce(values, F.sum("value")).collect()} == {28}
    assert cube.all_gather(values, P).count() == 64 and cube.bcast(values.limit(1), P).count() == P
    loads = verify.loads(shuffling.direct(state, P), P).toPandas().held
    assert loads.max() < 90 and shuffling.by_dimension(state, P, exact_halves=True).count() == 400


def test_costs_and_selector(spark):
    assert [selector.choose(int(x * 1024), 1024) for x in (1 / 32, 4, 2**14, 2**15)] == ["gather_merge", "grid_rank", "robust_cube_quicksort", "multilevel_samplesort"]
    order = [next(r.method for r in costs.rank_methods(spark, 2**18, [x], 1.0, 2e-4).where("place = 1").collect()) for x in (2.0**-7, 2.0**6, 2.0**20)]
    assert order[0] in ("gather_merge", "grid_rank") and order[2] in ("multilevel_samplesort", "exact_split_mergesort", "kway_cube", "direct_samplesort")
    assert abs(costs.imbalance_bound(16 * 64, 16, 0.39) - 1.89) < 0.02 and costs.kway_lower_bound(1e6, 64, 8, 1, 1) > 0
    assert costs.crossover("grid_rank", "robust_cube_quicksort", 2**18, 1.0, 2e-4) > 1


def test_rank_needs_no_single_partition(spark, uids):
    df = spark.range(1000).select((F.col("id") % 7).alias("k"), F.col("id"))
    plan = global_rank(df, "k", tie="id")._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" not in plan.split("BroadcastExchange")[0]
    assert samplesort.planned_sort(df, "k", partitions=8, tie="id")._jdf.queryExecution().executedPlan().toString().count("Exchange rangepartitioning") == 1


def test_two_level_sort(spark, uids, tmp_path):
    df = spark.range(2000).select((F.col("id") * 7919 % 50).alias("k"), F.col("id"))
    out = samplesort.two_level_sort(df, "k", "id", 4, 8, str(tmp_path / "groups"))
    keys = [r.k for r in out.collect()]
    assert keys == sorted(keys) and len(keys) == 2000


def test_experiments_are_registered_whole(spark, small, monkeypatch):
    """All rows, inputs and methods; only the sweep over loads takes prefixes."""
    asked = {}
    monkeypatch.setattr(experiments, "measure", lambda s, d, cases, base="orders": asked.setdefault("cases", (cases, base)) and s.createDataFrame([], experiments.SCHEMA))

    def cases(name):
        asked.clear()
        experiments.QUERIES[name](spark, small)
        return asked["cases"]

    for name in ("exp_quicksort_robustness", "exp_tie_ablation", "exp_plan_ablation", "exp_against_direct", "exp_verdicts"):
        assert {n for *_, n in cases(name)[0]} == {None}
    assert {(m, i) for m, i, *_ in cases("exp_verdicts")[0]} == {(m, i) for m in experiments.METHODS for i in experiments.inputs.NAMES}
    sweep, base = cases("exp_size_sweep")
    assert base == "lineitem" and len({i for _, i, *_ in sweep}) == 4 and max(n for *_, n in sweep) == 1 << 19
    assert "direct_given" in {m for m, *_ in cases("exp_against_direct")[0]} and "exp_parameter_grid" in experiments.QUERIES


@pytest.mark.parametrize("size", [0, 1, 3, 15, 16, 63])
def test_search_in_generated_code(spark, size):
    """Steps of generated code find what the search of one expression finds, on arrays that are null, short, equal or at their bound."""
    import bisect

    from ordering_engine.functions.search import with_count_below

    bounds = sorted(7 * i // 2 % 40 for i in range(size))
    df = spark.range(60).select(F.when(F.col("id") % 9 > 0, F.col("id") - 5).alias("v"), F.when(F.col("id") < 50, F.lit(bounds).cast("array<bigint>")).alias("ss"))
    found = with_count_below(df, "ss", "v", "at", max(1, size))
    assert "aggregate(" not in found._jdf.queryExecution().executedPlan().toString() and found.columns == ["v", "ss", "at"]
    assert all(r["at"] == (bisect.bisect_left(r.ss, r.v) if r.ss and r.v is not None else 0) for r in found.collect())


def test_grid_cells_are_sorted_once(spark, uids):
    """One window ranks a cell, whatever the ties."""
    state = inputs.make("rand_dupl", uids, 16)
    for unique in (True, False):
        assert gridrank.grid_rank(state, 16, unique)._jdf.queryExecution().optimizedPlan().toString().count("windowspecdefinition(cr") == 1
    want = {r.uid: r["rank"] for r in state.select("uid", (F.rank().over(Window.orderBy("key")) - 1).alias("rank")).collect()}
    assert want == {r.uid: r["rank"] for r in gridrank.grid_rank(state, 16).collect()}


def test_runs_leave_nothing_staged(spark, small, monkeypatch):
    """Machines in turns give the rows of machines side by side, and no run's tables stay."""
    import os

    from ordering_engine import storage

    cases = [("multilevel_l3", i, 8, 500) for i in ("uniform", "zero")]
    before, made = set(storage._left), []
    together = sorted(map(tuple, experiments.measure(spark, small, cases).collect()))
    monkeypatch.setattr(experiments, "AT_ONCE", 500)
    monkeypatch.setattr(inputs, "make_many", lambda turn, *rest, make=inputs.make_many: made.append(turn) or make(turn, *rest))
    assert sorted(map(tuple, experiments.measure(spark, small, cases).collect())) == together
    assert made == [[("uniform", 500)], [("zero", 500)]] and storage._left == before
    assert all(not os.path.exists(p) for p in storage._left - before)
