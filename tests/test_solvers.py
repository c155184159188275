"""Cross-method equality, bounds and invariants."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from shadowpack import workloads
from shadowpack.operators import candidates, groundtruth, measures, solvers, subproblem
from shadowpack.operators.lp_bound import lp_bound, simplex
from shadowpack.plans.facades import exactly_one_offset, kp01, mckp, mdkp, mmkp
from shadowpack.plans.hierarchy import Hierarchy
from shadowpack.plans.problem import KnapsackProblem
from shadowpack.sources import instances
from shadowpack.sources.lattice import LatticeDataSource, lattice_items, lattice_problem

ITEMS = "group_id long, item_id int, profit double, needs array<double>"


def random_problem(spark, seed, groups=4, m=4, k=2, caps=((1, (0, 1)), (2, None))):
    rng = random.Random(seed)
    rows = [(g, j, float(rng.randint(1, 50)), [float(rng.randint(0, 9)) for _ in range(k)]) for g in range(groups) for j in range(m)]
    h = Hierarchy.build([(c, None if i is None else list(i)) for c, i in caps])
    total = [sum(r[3][x] for r in rows) for x in range(k)]
    return KnapsackProblem.from_long(spark.createDataFrame(rows, ITEMS), [max(1.0, t // 4) for t in total], h).pack()


def decided(df):
    return sorted((r["group_id"], r["item_id"], r["units"]) for r in df.collect())


@pytest.mark.parametrize("caps", [((1, (0, 1)), (2, None)), ((1, (0, 1)), (1, (2, 3)), (1, (0, 1, 2)), (2, None)), ((2, None),), ()])
def test_greedy_is_optimal_and_engines_agree(spark, caps):
    if caps and any(set(a[1]) & set(b[1]) and not set(a[1]) <= set(b[1]) and not set(b[1]) <= set(a[1]) for a in caps for b in caps if a[1] and b[1]):
        pytest.skip("crossing sets")
    p = random_problem(spark, 5, groups=125, m=5, caps=caps)
    prices = [1.7, 2.3]
    greedy, sql, exact = subproblem.greedy_take(p, prices), subproblem.greedy_take(p, prices, "sql"), subproblem.exact_take(p, prices)
    assert decided(greedy) == decided(sql)
    value = lambda d: {r[0]: r[1] for r in subproblem.group_value(d, p.items, prices).collect()}
    a, b = value(greedy), value(exact)
    assert a.keys() == b.keys() and all(a[g] == pytest.approx(b[g]) for g in a)
    assert measures.local_violations(p, greedy) == 0


def test_bounds_order(spark):
    for seed in range(3):
        p = random_problem(spark, seed)
        s = solvers.solve(p, reduce="exact", max_iter=20)
        best = groundtruth.brute_force(p)
        upper, lower = lp_bound(p, 1e-6, 80)
        assert s.metrics["primal"] <= best + 1e-6 <= upper + 1e-3
        assert lower <= upper + 1e-6
        assert measures.evaluate(p, [0.5, 3.0]).dual >= upper - 1e-6
        used = [r["used"] for r in measures.used_by_knapsack(s.decisions, p.items, p.budgets).orderBy("knapsack_id").collect()]
        assert all(u <= b for u, b in zip(used, p.budgets, strict=True))
        # the solution is optimal for budgets equal to its own use, plus slack where the price is 0
        e = measures.evaluate(p, s.prices)
        own = [u if x > 0 else max(u, b) for u, x, b in zip(e.used, s.prices, p.budgets, strict=True)]
        assert groundtruth.brute_force(p, own) == pytest.approx(e.primal)


def test_general_and_linear_maps_agree(spark, small):
    for q in (1, 2, 3):
        p = KnapsackProblem.from_long(instances.user_offers(spark, small), [1.0] * 5, Hierarchy.root(q)).pack()
        prices = [3000.0, 1000.0, 0.0, 2500.0, 6000.0]
        rows = [sorted((r["knapsack"], round(r["v1"], 6), r["v2"]) for r in x.collect()) for x in (candidates.sparse_emissions(candidates.sparse_packed(p), prices, q), candidates.scd_emissions(p, prices))]
        assert rows[0] == rows[1]
        assert candidates.is_linear_case(p)


def test_use_falls_with_price_and_cyclic_steps_lower_the_dual(spark):
    p = random_problem(spark, 9, groups=60)
    used = [e.used[0] for e in measures.evaluate_many(p, [[x, 1.0] for x in (0.0, 0.5, 1.0, 2.0, 5.0, 50.0)])]
    assert used == sorted(used, reverse=True)
    duals = [h["dual"] for h in solvers.scd(p, 1.0, mode="cyclic", reduce="exact", max_iter=5, tol=-1.0).history]
    assert all(b <= a + 1e-6 for a, b in zip(duals, duals[1:], strict=False))


def test_scaling(spark):
    p = random_problem(spark, 3, groups=40, k=1)
    base = solvers.scd(p, 1.0, solver="general", reduce="exact").prices[0]
    doubled = KnapsackProblem.from_long(p.items.withColumn("profit", F.col("profit") * 2).drop("max_units"), p.budgets, p.hierarchy).pack()
    assert solvers.scd(doubled, 1.0, solver="general", reduce="exact").prices[0] == pytest.approx(2 * base)
    needs = p.items.withColumn("needs", F.transform("needs", lambda x: x * 4)).drop("max_units")
    wider = KnapsackProblem.from_long(needs, [4 * b for b in p.budgets], p.hierarchy).pack()
    assert solvers.scd(wider, 1.0, solver="general", reduce="exact").prices[0] == pytest.approx(base / 4)


def test_partitioning_changes_nothing(spark):
    p = random_problem(spark, 4, groups=50)
    q = KnapsackProblem.from_long(p.items.drop("max_units").orderBy(F.rand(3)), p.budgets, p.hierarchy).pack(partitions=7)
    assert solvers.scd(p, 1.0, reduce="exact", max_iter=3).prices == solvers.scd(q, 1.0, reduce="exact", max_iter=3).prices


def test_slack_budgets_have_no_price(spark):
    p = random_problem(spark, 2).with_budgets([1e6, 1e6])
    s = solvers.solve(p, reduce="exact")
    assert s.prices == [0.0, 0.0] and s.metrics["gap"] == pytest.approx(0.0)


def test_budget_below_every_need_takes_nothing(spark):
    rows = [(g, 0, 5.0, [2.0]) for g in range(5)]
    p = KnapsackProblem.from_long(spark.createDataFrame(rows, ITEMS), [1.0]).pack()
    assert solvers.solve(p, reduce="exact").decisions.count() == 0


def test_plain_coordinate_descent(spark):
    p = random_problem(spark, 8, groups=60, k=1)
    a = solvers.coordinate_descent(p, 1.0, cycles=2)
    b = solvers.scd(p, 1.0, solver="general", reduce="exact")
    assert a.prices[0] == pytest.approx(b.prices[0], rel=1e-2)


def test_one_knapsack_gap_and_exact_table(spark, small):
    items = instances.benchmark_pick(spark, small)
    p = kp01(items, 2500.0).pack()
    s = solvers.solve(p, solver="general", reduce="exact")
    best = groundtruth.dp_exact(p)
    assert best - measures.k1_gap_bound(p) <= s.metrics["primal"] <= best
    fractional = groundtruth.fractional_knapsack(items, 2500.0).agg(F.sum(F.col("profit") * F.col("part"))).first()[0]
    assert best <= fractional + 1e-6
    assert lp_bound(p, 1e-6)[0] == pytest.approx(fractional, rel=1e-4)


def test_facades(spark):
    df = spark.createDataFrame([(1, 0, 5.0, 2.0), (1, 1, 9.0, 5.0), (2, 0, 4.0, 1.0), (2, 1, 6.0, 6.0)], "group_id long, item_id int, profit double, need double")
    p = mckp(df, 7.0).pack()
    assert groundtruth.brute_force(p) == groundtruth.dp_exact(p) == 13.0
    e = mckp(df, 7.0, exactly_one=True)
    assert e.budgets == [4.0] and sorted(r["item_id"] for r in exactly_one_offset(df).collect()) == [0, 0]
    base = df.select("group_id", "item_id", "profit", F.array("need", "need").alias("needs"))
    assert mmkp(base, [7.0, 8.0]).hierarchy.single_cap() == 1
    assert not mdkp(base.where("item_id = 0"), [3.0, 3.0]).hierarchy.sets


def test_crossing_caps_and_own_objective(spark):
    rows = [(1, 0, 5.0, [0.0]), (1, 1, 6.0, [0.0]), (1, 2, 5.0, [0.0])]
    p = KnapsackProblem.from_long(spark.createDataFrame(rows, ITEMS), [1.0], Hierarchy.build([(1, [0, 1]), (1, [1, 2])])).pack()
    assert [x[1] for x in decided(subproblem.exact_take(p, [0.0]))] == [0, 2]
    with pytest.raises(ValueError):
        subproblem.greedy_take(p, [0.0])
    square = lambda ids, profits, take: np.sqrt(take @ profits)
    assert decided(subproblem.exact_take(p, [0.0], value=square)) == decided(subproblem.exact_take(p, [0.0]))


def test_presolve_repair_and_early_stop(spark):
    p = lattice_problem(spark, 4000, 5, 5, True, "C1", uniform=True)
    s = solvers.solve(p, presolve=400, prices0=20.0, reduce="bucketed", interpolate="exact", max_iter=30, tol=1e-2)
    assert s.metrics["relative_gap"] < 0.01
    cold = solvers.scd(p, 20.0, reduce="exact", max_iter=30, tol=1e-2)
    assert s.iterations <= cold.iterations
    early = solvers.solve(p, reduce="exact", early_stop_violation=0.05)
    assert early.iterations <= 30 and early.metrics["primal"] > 0
    assert solvers.history_frame(p, cold.history).count() == 5 * len(cold.history)


def test_optimality_at_a_thousand_groups(spark):
    p = lattice_problem(spark, 1000, 10, 5, False, "C1")
    s = solvers.solve(p, max_iter=20)
    upper, _ = lp_bound(p, 1e-3, 30, [s.prices], s.history)
    assert s.metrics["primal"] / upper > 0.986


def test_descent_violates_more_than_coordinates(spark):
    """Once both are near the optimum; the smaller step size has not come so far by then."""
    from shadowpack import workloads

    worst = {r["method"]: r["m"] for r in workloads.descent_traces(spark, None, 10_000, 10, iterations=14).groupBy("method").agg(F.max("max_violation").alias("m")).collect()}
    assert worst["scd"] < worst["dd 0.002"]


def test_simplex():
    a = np.array([[1.0, 2.0, 1.0, 0.0], [3.0, 1.0, 0.0, 1.0]])
    x, y, value = simplex(np.array([3.0, 4.0, 0, 0]), a, np.array([4.0, 6.0]), [2, 3])
    assert value == pytest.approx(9.6) and y @ np.array([4.0, 6.0]) == pytest.approx(9.6)
    assert (a @ x == pytest.approx([4.0, 6.0]))


def test_lattice_data_source(spark):
    spark.dataSource.register(LatticeDataSource)
    got = spark.read.format("lattice").option("groups", 50).option("items", 3).option("knapsacks", 3).load()
    want = lattice_items(spark, 50, 3, 3, True)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.select(got.columns).collect()))


def test_an_iteration_moves_no_group_rows(spark):
    p = random_problem(spark, 6, groups=200)
    out = candidates.scd_emissions(p, [1.0, 1.0])
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "MapInArrow" in plan


def test_sinks_and_resume(spark, tmp_path):
    p = random_problem(spark, 12, groups=30)
    first = solvers.scd(p, 1.0, reduce="exact", max_iter=2, tol=-1.0, damping=False)
    solvers.history_frame(p, first.history).write.mode("append").parquet(str(tmp_path / "history"))
    again = solvers.scd(p, first.prices, reduce="exact", max_iter=2, tol=-1.0, damping=False)
    whole = solvers.scd(p, 1.0, reduce="exact", max_iter=4, tol=-1.0, damping=False)
    assert again.prices == pytest.approx(whole.prices)
    d = subproblem.greedy_take(p, again.prices).withColumn("day", F.lit("2024-01-01"))
    d.write.partitionBy("day").parquet(str(tmp_path / "decisions"))
    assert spark.read.parquet(str(tmp_path / "decisions")).where("day = '2024-01-01'").count() == d.count()


def test_files_and_tables(spark, tmp_path):
    from shadowpack.sources import io

    (tmp_path / "b.csv").write_text("knapsack_id,budget\n2,5.5\n1,3\n")
    (tmp_path / "b.json").write_text('{"knapsack_id": 1, "budget": 3.0}\n')
    (tmp_path / "c.json").write_text('{"set_id": 1, "cap": 1, "item_ids": [0, 1]}\n{"set_id": 2, "cap": 2}\n')
    assert io.read_budgets(spark, str(tmp_path / "b.csv")) == [3.0, 5.5]
    assert io.read_budgets(spark, str(tmp_path / "b.json"), "json") == [3.0]
    assert [s.cap for s in io.read_caps(spark, str(tmp_path / "c.json")).topo()] == [1, 2]
    caps = spark.createDataFrame([(1, [0, 1]), (2, [1, 2]), (3, [0, 1, 2])], "set_id int, item_ids array<int>")
    assert [tuple(r) for r in io.crossing_sets(spark, caps).collect()] == [(1, 2)]
    p = random_problem(spark, 1, groups=20)
    d = subproblem.greedy_take(p, [1.0, 1.0])
    for day in ("2024-01-01", "2024-01-02", "2024-01-01"):
        io.write_decisions(d, str(tmp_path / "d"), day)
    assert spark.read.parquet(str(tmp_path / "d")).count() == 2 * d.count()
    s = solvers.scd(p, 1.0, reduce="exact", max_iter=3, tol=-1.0)
    io.append_history(solvers.history_frame(p, s.history), str(tmp_path / "h"))
    assert io.last_prices(spark, str(tmp_path / "h")) == pytest.approx(s.history[-1]["prices"])
    cost = measures.emission_cost(p, [1.0, 1.0])
    assert cost["emitted_rows"] >= cost["histogram_rows"] > 0


def test_daily_solve_takes_the_days_of_the_table(spark, tmp_path):
    rows = [(i, f"2023-05-{d:02d} 10:00:00", i % 7, t, 5.0 + i % 4) for i, (d, t) in enumerate([(d, t) for d in (30, 9, 11) for t in instances.EVENT_TYPES] * 4)]
    spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double").withColumn("ts", F.col("ts").cast("timestamp")).write.parquet(f"{tmp_path}/events.parquet")
    got = workloads.daily_solve(spark, str(tmp_path)).collect()
    assert [r["day"] for r in got] == ["2023-05-09", "2023-05-11", "2023-05-30"] and all(r["primal"] > 0 for r in got)


def test_exact_takes_more_than_64_units(spark):
    items = spark.createDataFrame([(1, 0, 5.0, [1.0], 2**31 - 1), (1, 1, 3.0, [1.0], 80)], "group_id long, item_id int, profit double, needs array<double>, max_units int")
    p = KnapsackProblem.from_long(items, [1000.0], Hierarchy.root(100)).pack()
    assert [tuple(r) for r in subproblem.exact_take(p, [0.5]).collect()] == [(1, 0, 100)]
    assert [tuple(r) for r in subproblem.greedy_take(p, [0.5]).collect()] == [(1, 0, 100)]


def test_ways_to_reduce_agree(spark):
    p = random_problem(spark, 21, groups=300, m=5, k=3)
    start = [2.0, 1.0, 0.5]
    for mode, blocks in (("sync", None), ("block", [[1, 3], [2]])):
        got = [solvers.scd(p, start, mode=mode, blocks=blocks, reduce=r, threshold=t, max_iter=4, tol=-1.0).prices for t in ("crossing", "last_fit") for r in ("exact", "ranged", "window")]
        assert all(pytest.approx(got[3 * t]) == got[3 * t + i] for t in range(2) for i in (1, 2))
        assert got[0] != got[3]
    with pytest.raises(ValueError):
        solvers.scd(p, threshold="last_fit")
    with pytest.raises(ValueError):
        solvers.scd(p, reduce="sorted")


def test_histograms_of_the_pass_are_those_of_the_emissions(spark, monkeypatch):
    from shadowpack.operators import passes
    from shadowpack.plans.kernels import Buckets

    p = random_problem(spark, 22, groups=400, m=6, k=2)
    prices = [1.5, 2.5]
    out = candidates.scd_emissions(p, prices).groupBy("knapsack", "v1").agg(F.sum("v2").alias("v2")).collect()
    rows, e, _ = passes.run_pass(p, prices, {1: Buckets("value"), 2: Buckets("value")}, False)
    assert sorted((k, r["hi"], r["mass"]) for k, many in rows.items() for r in many) == sorted((r["knapsack"], r["v1"], r["v2"]) for r in out)
    assert e == measures.evaluate(p, prices)
    # within a window: the same prices, and one row for all that comes above
    low, high = 0.8, 2.0
    near = passes.run_pass(p, prices, {1: Buckets("value")}, False, windows={1: (low, high)})[0][1]
    assert [(r["hi"], r["mass"]) for r in near[1:]] == [(r["hi"], r["mass"]) for r in rows[1] if low < r["hi"] <= high]
    assert near[0]["mass"] == sum(r["mass"] for r in rows[1] if r["hi"] > high)
    # a price found by probes and windows is the one found in all emissions, few or many to a bucket
    for few in (20_000, 3):
        monkeypatch.setattr(passes, "FEW", few)
        memory = passes.Memory()
        for _ in range(3):
            new, _ = passes.next_prices(p, prices, [1, 2], False, "exact", memory=memory)
            assert list(new.values()) == pytest.approx(solvers.scd(p, prices, reduce="window", max_iter=1, tol=-1.0, damping=False).prices)
            prices = [(a + b) / 2 for a, b in zip(prices, new.values(), strict=True)]


def test_few_rows_leave_a_task(spark):
    from shadowpack.operators import passes
    from shadowpack.plans.kernels import Buckets

    p = lattice_problem(spark, 3000, 6, 3, False, "hier", uniform=True)
    out = passes.pass_rows(p, [0.2] * 3, {k: Buckets("uneven", 0.2, 1e-3) for k in (1, 2, 3)}, False)
    assert out.count() <= 3 * 40 + 6
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert plan.index("MapInArrow") > plan.index("Exchange") > 0  # the only exchange is of the histogram


def test_best_bound_without_a_trace(spark):
    p = random_problem(spark, 5, groups=60)
    for reduce in ("exact", "window"):
        traced = solvers.scd(p, 1.0, reduce=reduce, max_iter=4, tol=0.0)
        bare = solvers.scd(p, 1.0, reduce=reduce, max_iter=4, tol=0.0, trace=False)
        assert bare.prices == traced.prices and not bare.history
        if not traced.converged:
            assert measures.evaluate(p, bare.prices).dual <= min(h["dual"] for h in traced.history) + 1e-9


def test_cycles_fall_back_in_any_mode_and_random_starts(spark, monkeypatch):
    p = random_problem(spark, 5, groups=20)
    modes = []
    blocks_of = solvers.blocks_of
    monkeypatch.setattr(solvers, "blocks_of", lambda mode, *a: modes.append(mode) or blocks_of(mode, *a))
    swing = iter([[2.0, 1.0], [1.0, 2.0]] * 20)

    def swinging(problem, prices, block, *_, measure=True, **__):
        now = next(swing)
        return {k: now[k - 1] for k in block}, measures.evaluate(problem, prices) if measure else None

    monkeypatch.setattr(solvers, "next_prices", swinging)
    solvers.scd(p, 1.0, mode="block", blocks=[[1, 2]], max_iter=8, damping=False, tol=0.0)
    assert modes[0] == "block" and modes[-1] == "cyclic"
    assert solvers.start_prices(p, "random:7") == solvers.start_prices(p, "random:7") != solvers.start_prices(p, "random:8")
    with pytest.raises(ValueError):
        solvers.start_prices(p, "warm")


@pytest.mark.parametrize("values", [1, 3, 10_000])
def test_repair_of_ties_without_a_task_for_all(spark, monkeypatch, values):
    from shadowpack.operators import feasibility

    rng = random.Random(values)
    rows = [(g, float(rng.randrange(values)), 1.0, [float(rng.randint(0, 3)), float(rng.randint(0, 3))]) for g in range(2000)]
    groups = spark.createDataFrame(rows, "group_id long, value double, profit double, used array<double>").repartition(5)
    used = [sum(r[3][k] for r in rows) for k in range(2)]
    monkeypatch.setattr(feasibility, "FEW_GROUPS", 50)
    for budgets, only in (([0.7 * used[0], used[1]], False), ([0.7 * used[0], used[1]], True), ([0.0, 0.0], False)):
        over = [k for k in range(2) if used[k] > budgets[k]]
        gone, left = [], list(used)
        for g, value, _, need in sorted(rows, key=lambda r: (r[1], r[0])):
            if all(left[k] <= budgets[k] for k in over):
                break
            if not only or any(need[k] > 0 for k in over):
                gone.append(g)
                left = [x - y for x, y in zip(left, need, strict=True)]
        fixed = feasibility.repair(groups, used, budgets, only)
        if budgets == [0.0, 0.0]:
            assert all(sum(r["used"]) == 0 for r in fixed.keep.collect())
        else:
            assert fixed.dropped == len(gone) and not {r["group_id"] for r in fixed.keep.collect()} & set(gone)


def test_dropped_groups_take_nothing(spark):
    from shadowpack.operators.feasibility import drop_groups, repair

    p = random_problem(spark, 31, groups=500, m=4, k=2)
    prices = [0.2, 0.2]
    e, groups = measures.evaluate(p, prices), subproblem.group_results(p, prices)
    for only in (False, True):
        fixed = repair(groups, e.used, p.budgets, only)
        assert fixed.dropped > 0
        assert decided(subproblem.greedy_take(p, prices, dropped=fixed.rule)) == decided(drop_groups(subproblem.greedy_take(p, prices), fixed.keep))


def test_density_order_in_ranges(spark):
    rng = random.Random(2)
    rows = [(i, float(rng.randint(1, 9)), float(rng.randint(1, 9))) for i in range(500)]
    items = spark.createDataFrame(rows, "item_id int, profit double, need double").repartition(6)
    before, want = 0.0, {}
    for i, _, need in sorted(rows, key=lambda r: (-r[1] / r[2], r[0])):
        want[i] = before
        before += need
    assert {r["item_id"]: r["before"] for r in groundtruth.by_density(items).collect()} == want
    with pytest.raises(ValueError):
        groundtruth.dp_exact(kp01(items, 1e9))


def test_violated_caps_are_counted(spark):
    p = random_problem(spark, 8, groups=40, m=4, caps=((1, (0, 1)), (2, None)))
    loose = KnapsackProblem.from_long(p.items.drop("max_units"), p.budgets, Hierarchy.root(3)).pack()
    taken = subproblem.greedy_take(loose, [0.0, 0.0])
    got = {}
    for g, i, u in decided(taken):
        got.setdefault(g, []).append((i, u))
    want = sum((sum(u for i, u in x if i in (0, 1)) > 1) + (sum(u for _, u in x) > 2) for x in got.values())
    assert measures.local_violations(p, taken) == want > 0


def test_polished_prices_keep_more_after_the_repair(spark):
    p = lattice_problem(spark, 400, 10, 8, False, "C1")
    assert len(p.packed.inputFiles()) == 1
    plain = solvers.solve(p, max_iter=6)
    start = measures.evaluate(p, plain.prices)
    better = solvers.polished(p, plain.prices, 4)
    end = measures.evaluate(p, better)
    assert end.primal / (1 + end.max_violation) >= start.primal / (1 + start.max_violation)
    s = solvers.finish(p, solvers.Solution(better, True, 0))
    used = measures.used_by_knapsack(s.decisions, p.items, p.budgets).collect()
    assert all(r["used"] <= r["budget"] * (1 + 1e-9) for r in used)
    assert s.metrics["primal"] <= lp_bound(p, 1e-3, 10, [better])[0] * (1 + 1e-9)
    # without any violation or price there is nothing to move
    assert solvers.polished(p.with_budgets([1e12] * 8), [0.0] * 8, 1) == [0.0] * 8


def test_single_units_by_pairs_take_what_the_greedy_does(monkeypatch):
    from shadowpack.plans import kernels

    rng = np.random.default_rng(7)
    for m in (1, 2, 5, 9):
        net = rng.integers(-3, 6, (300, m)).astype(float)
        units = rng.integers(0, 2, (300, m))
        least = rng.integers(0, 2, (300, m)) * 0.5
        fine, coarse = rng.integers(-1, 3, (300, m)), rng.integers(-1, 2, (300, m))
        fine[coarse < 0] = -1
        whole = (np.zeros((300, m), dtype=np.int64), np.array([3]))
        for levels in ([(fine * 2 + coarse * (fine >= 0), np.full(6, 1)), (coarse, np.array([2, 1])), whole], [whole], [(whole[0], np.array([1]))], [(coarse, np.array([1, 2]))]):
            got = kernels.greedy(net, units, levels, least)
            with monkeypatch.context() as patch:
                patch.setattr(kernels, "MOST_PAIRED", 0)
                # one level over all items has a way of its own; a second copy of it changes nothing
                want = kernels.greedy(net, units, [*levels, levels[-1]], least)
            assert got.tolist() == want.tolist()


def test_a_window_lists_critical_prices_of_groups_that_change_in_it_only(spark, monkeypatch):
    from shadowpack.plans import kernels

    p = lattice_problem(spark, 1000, 10, 5, False, "hier")
    batch = pa.Table.from_batches(p.packed.toArrow().to_batches()).combine_chunks().to_batches()[0]
    (block,) = kernels.blocks(batch, 5)
    levels = kernels.Caps(p.hierarchy, p.levels).nodes(block)
    prices, seen = np.array([40.0, 30.0, 20.0, 10.0, 5.0]), []
    look = kernels.candidates
    monkeypatch.setattr(kernels, "candidates", lambda a, b: seen.append(a.shape[0]) or look(a, b))
    v1, v2 = kernels.emissions(block, prices, 0, levels)
    for low, high in ((38.0, 42.0), (0.0, 5.0), (60.0, np.inf), (float(np.nextafter(v1[0], 0)), float(v1[0]))):
        seen.clear()
        w1, w2 = kernels.emissions(block, prices, 0, levels, window=(low, high))
        inside = (v1 > low) & (v1 <= high)
        mine = (w1 > low) & (w1 <= high)
        assert sorted(zip(w1[mine], w2[mine])) == sorted(zip(v1[inside], v2[inside]))
        assert w2[w1 > high].sum() == v2[v1 > high].sum()
        assert seen[0] < 1000


def test_the_ratio_query_packs_once(spark, small, monkeypatch):
    from shadowpack.plans import problem

    packs = []
    pack = problem.KnapsackProblem.pack
    monkeypatch.setattr(problem.KnapsackProblem, "pack", lambda self, *a, **k: packs.append(self.k) or pack(self, *a, **k))
    monkeypatch.setattr(workloads.solvers, "solve", lambda p, **k: solvers.Solution([1.0] * p.k, True, 1, metrics={"primal": sum(p.budgets), "n_violated_before_repair": len(p.levels)}))
    monkeypatch.setattr(workloads, "lp_bound", lambda p, *a: (1.0, 1.0))
    got = {(r["k"], r["scenario"]): (r["primal"], r["violated_before_repair"]) for r in workloads.optimality_order_lines(spark, small, (1, 3)).collect()}
    assert packs == [3]
    monkeypatch.undo()
    for k in (1, 3):
        for c in ("C1", "C2", "hier"):
            p = instances.orders_problem(spark, small, k, c)
            assert got[k, c] == (sum(p.budgets), len(p.levels))


def test_stored_blocks_hold_the_same_groups_and_give_the_same_iterations(spark, small):
    from shadowpack.operators.passes import next_prices

    for scenario in ("C1", "hier"):
        p = instances.orders_problem(spark, small, 3, scenario)
        q = p.pack(as_blocks=True)
        assert "width" in q.packed.columns and q.packed.count() < p.packed.count() / 10
        for prices in ([0.0, 0.0, 0.0], [30000.0, 150000.0, 90000.0]):
            a, b = measures.evaluate(p, prices), measures.evaluate(q, prices)
            assert (a.used, a.primal, a.taken) == (b.used, b.primal, b.taken)
            rows = [sorted(tuple(r) for r in subproblem.greedy_take(x, prices).collect()) for x in (p, q)]
            assert rows[0] == rows[1]
        assert next_prices(p, [1.0] * 3, [1, 2, 3], False)[0] == next_prices(q, [1.0] * 3, [1, 2, 3], False)[0]


def test_margins_say_which_groups_a_window_can_not_change():
    from shadowpack.plans import kernels

    rng = np.random.default_rng(3)
    n, m = 4000, 5
    fine, coarse = rng.integers(0, 3, (n, m)), rng.integers(0, 2, (n, m))
    profit, needs = np.asfortranarray(rng.integers(0, 60, (n, m)).astype(float)), rng.integers(0, 9, (n, m, 2)).astype(float)
    ones = np.ones((n, m), dtype=np.int64)
    block = kernels.Block(np.arange(n), np.tile(np.arange(m), (n, 1)), profit, needs, ones, ones.astype(bool), [], full=True, single=True)
    root = kernels.Level((np.broadcast_to(np.int8(0), (n, m)), np.array([3])))
    for levels in ([root], [kernels.Level((fine * 2 + coarse, np.full(6, 1))), kernels.Level((coarse, np.full(2, 2))), root]):
        prices, window = np.array([2.0, 3.0]), (1.8, 2.2)
        net = block.net(prices)
        settled = kernels.Settled(block, prices, levels, net, kernels.greedy(net, None, levels), needs)
        sure = settled.margin > 0.2001 * needs[:, :, 0].max(axis=1)
        assert 100 < sure.sum() < n
        for x in np.linspace(*window, 9):
            take = kernels.greedy(block.net(np.array([x, 3.0])), None, levels)
            assert (take[sure] == settled.take[sure]).all()
        want, got = kernels.emissions(block, prices, 0, levels, window=window), settled.emissions(0, window)
        assert sorted(zip(*want)) == sorted(zip(*got))


def test_the_cut_is_the_repair_without_writing_groups(spark, small, monkeypatch):
    from shadowpack.operators import cuts, feasibility

    p = instances.orders_problem(spark, small, 3, "hier").pack(as_blocks=True)
    prices = [20000.0, 90000.0, 60000.0]
    e = measures.evaluate(p, prices, tolerant=True)
    groups = subproblem.group_results(p, prices, tolerant=True)
    for few in (20_000, 3):
        monkeypatch.setattr(cuts, "FEW_GROUPS", few)
        for shares, only in (((0.9, 0.8, 2.0), False), ((2.0, 2.0, 0.7), True), ((1e-9, 2.0, 2.0), False), ((2.0, 2.0, 2.0), False)):
            budgets = [u * s for u, s in zip(e.used, shares, strict=True)]
            got = cuts.find_cut(p.with_budgets(budgets), prices, e.used, only)
            want = feasibility.repair(groups, e.used, budgets, only)
            if want.rule is not None:
                assert (got.rule.value, got.rule.group, got.rule.touching) == (want.rule.value, want.rule.group, want.rule.touching)
                assert got.dropped == want.dropped and got.kept == (want.keep.agg({"profit": "sum"}).first()[0] or 0.0)
