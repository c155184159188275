"""Hand-checked instances."""

import numpy as np
import pytest

from shadowpack.functions.columns import bucket_id
from shadowpack.operators import candidates, feasibility, groundtruth, measures, solvers, subproblem, thresholds
from shadowpack.plans.hierarchy import Hierarchy
from shadowpack.plans.kernels import Block, emissions, greedy, linear_emissions
from shadowpack.plans.problem import KnapsackProblem


def block(profit, needs, ids=None):
    profit = np.array([profit], dtype=float)
    m = profit.shape[1]
    return Block(np.array([1]), np.array([ids or list(range(m))]), profit, np.array([needs], dtype=float).reshape(1, m, -1), np.ones((1, m), dtype=np.int64), np.ones((1, m), dtype=bool), [])


def levels(h, ids):
    from shadowpack.plans.kernels import Caps

    return Caps(h, []).nodes(block([0.0] * len(ids), [[0.0]] * len(ids), ids))


def test_nested_greedy_takes_the_best_of_each_node():
    h = Hierarchy.build([(1, [0, 1]), (1, [2, 3]), (1, [0, 1, 2, 3]), (2, None)])
    net = np.array([[9.0, 8, 7, 3, -1, 5]])
    take = greedy(net, np.ones((1, 6), dtype=np.int64), levels(h, list(range(6))))
    assert np.flatnonzero(take[0]).tolist() == [0, 5]
    assert (take * net).sum() == 14


@pytest.mark.parametrize(("q", "expected"), [(1, [(1, 3.0, 2.0)]), (2, [(1, 4.0, 2.0), (2, 1.5, 4.0)]), (3, [(1, 5.0, 2.0), (2, 2.0, 4.0), (3, 3.0, 1.0)])])
def test_linear_map(spark, q, expected):
    items = spark.createDataFrame([(1, 0, 10.0, 1, 2.0), (1, 1, 8.0, 2, 4.0), (1, 2, 3.0, 3, 1.0)], "group_id long, item_id int, profit double, knapsack_id int, need double")
    p = KnapsackProblem.from_long(items, [1.0] * 3, Hierarchy.root(q))
    got = candidates.sparse_emissions(candidates.sparse_packed(p), [1.0] * 3, q).collect()
    assert sorted((r["knapsack"], r["v1"], r["v2"]) for r in got) == expected
    ok, v1 = linear_emissions(np.array([[10.0, 8, 3]]), np.array([[2.0, 4, 1]]), np.array([[8.0, 4, 2]]), q)
    assert [(k + 1, v1[0, k]) for k in np.flatnonzero(ok[0])] == [(k, v) for k, v, _ in expected]


def test_segment_emissions():
    root = levels(Hierarchy.root(1), [0, 1])
    b = block([6.0, 4.0], [[3.0], [1.0]])
    v1, v2 = emissions(b, np.array([1.0]), 0, root)
    assert list(zip(v1, v2, strict=True)) == [(4.0, 1.0), (1.0, 2.0)]
    one = block([6.0], [[3.0]])
    assert [x.tolist() for x in emissions(one, np.array([1.0]), 0, levels(Hierarchy.root(1), [0]))] == [[2.0], [3.0]]
    assert emissions(one, np.array([1.0]), 0, levels(Hierarchy.root(1), [0]), "point")[0].size == 0


def test_thresholds(spark):
    values = [(5.0, 2.0), (3.0, 4.0), (2.0, 1.0), (1.0, 6.0)]
    em = spark.createDataFrame([(1, *v) for v in values], "knapsack int, v1 double, v2 double")
    for budget, crossing, last in ((7.0, 1.0, 2.0), (13.0, 0.0, 0.0), (1.0, 5.0, 5.0)):
        table = spark.createDataFrame([(1, budget)], "knapsack int, budget double")
        assert thresholds.threshold_exact(em, table).first()["price"] == crossing
        assert thresholds.threshold_exact(em, table, "last_fit").first()["price"] == last
        assert thresholds.crossing(values, budget) == crossing
        assert thresholds.crossing(values, budget, "last_fit") == last
        assert thresholds.threshold_ranged(em, {1: budget}, 3)[1] == crossing
        assert thresholds.threshold_bucketed(em, {1: 2.0}, {1: budget}, 0.5, interpolate="exact")[1] == crossing


def test_bucket_numbers(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(5.0,), (3.0,), (2.1,), (0.1,), (2.0,)], "v double")
    assert [r[0] for r in df.select(bucket_id(F.col("v"), F.lit(2.0), F.lit(0.5))).collect()] == [1, 0, 0, -1, 0]
    shifted = [r[0] for r in df.select(bucket_id(F.col("v"), F.lit(2.0), F.lit(0.5), shifted=True)).collect()]
    assert shifted == [2, 1, 0, -2, 0]


def test_dual_step():
    new = solvers.dd_update([1.0, 0.2], [150, 80], [100, 120], 0.01)
    assert new == pytest.approx([1.5, 0.0])


def test_repair(spark):
    groups = spark.createDataFrame([(1, 1.0, 0.0, [3.0, 0.0]), (2, 0.5, 0.0, [0.0, 2.0]), (3, 2.0, 0.0, [4.0, 4.0])], "group_id long, value double, profit double, used array<double>")
    fixed = feasibility.repair(groups, [7.0, 6.0], [5.0, 6.0])
    assert [r["group_id"] for r in fixed.keep.collect()] == [3]
    fixed = feasibility.repair(groups, [7.0, 6.0], [5.0, 6.0], only_violating=True)
    assert sorted(r["group_id"] for r in fixed.keep.collect()) == [2, 3]
    assert feasibility.repair(groups, [5.0, 6.0], [5.0, 6.0]).dropped == 0


def tiny(spark, profits=(6.0, 4.0), needs=(3.0, 1.0), budget=2.0):
    items = spark.createDataFrame([(1, i, p, [n]) for i, (p, n) in enumerate(zip(profits, needs, strict=True))], "group_id long, item_id int, profit double, needs array<double>")
    return KnapsackProblem.from_long(items, [budget], Hierarchy.root(1)).pack()


def test_one_group_end_to_end(spark):
    p = tiny(spark)
    s = solvers.scd(p, 1.0, solver="general", reduce="exact")
    assert s.prices == [1.0] and s.converged and s.iterations == 1 or s.prices == [1.0]
    e = measures.evaluate(p, [1.0])
    assert (e.primal, e.dual, e.gap) == (6.0, 5.0, -1.0) or (e.primal, e.dual, e.gap) == (4.0, 5.0, 1.0)
    assert groundtruth.brute_force(p) == 4.0


def test_violation_measures():
    e = measures.Evaluation([1.0, 0.0], [110.0, 90.0], [100.0, 100.0], 1.0, 1.0, 1)
    assert e.violations == pytest.approx([0.1, 0.0]) and e.max_violation == pytest.approx(0.1) and e.n_violated == 1
    assert measures.iteration_saving(32, 8) == 0.75


def test_invalid_inputs(spark):
    schema = "group_id long, item_id int, profit double, needs array<double>"
    for rows, budgets in (([(1, 0, -1.0, [1.0])], [1.0]), ([(1, 0, 1.0, [-1.0])], [1.0]), ([(1, 0, None, [1.0])], [1.0]), ([(1, 0, float("nan"), [1.0])], [1.0]), ([(1, 0, 1.0, [1.0]), (1, 0, 2.0, [1.0])], [1.0]), ([(1, 0, 1.0, [1.0])], [0.0])):
        with pytest.raises(ValueError):
            KnapsackProblem.from_long(spark.createDataFrame(rows, schema), budgets).validate()
    with pytest.raises(ValueError):
        Hierarchy.build([(0, [1])])
    with pytest.raises(ValueError):
        Hierarchy.build([(1, [0, 1]), (1, [1, 2])]).require_laminar()
    unbounded = spark.createDataFrame([(1, 0, 1.0, [1.0], None)], schema + ", max_units int")
    with pytest.raises(ValueError):
        KnapsackProblem.from_long(unbounded, [1.0]).validate()
    KnapsackProblem.from_long(unbounded, [1.0], Hierarchy.root(3)).validate()


def test_equal_sets_take_the_smaller_cap():
    h = Hierarchy.build([(3, [0, 1]), (2, [1, 0])])
    assert [(s.cap, s.items) for s in h.topo()] == [(2, frozenset({0, 1}))]


def test_integer_units():
    take = greedy(np.array([[5.0, 3.0, 1.0]]), np.array([[2, 4, 9]]), levels(Hierarchy.root(5), [0, 1, 2]))
    assert take.tolist() == [[2, 3, 0]]


def test_greedy_units_sql(spark):
    items = spark.createDataFrame([(1, 0, 5.0, 2), (1, 1, 3.0, 4), (1, 2, 1.0, 9)], "group_id long, item_id int, net double, max_units int")
    assert sorted((r["item_id"], r["units"]) for r in subproblem.greedy_units(items, 5).collect()) == [(0, 2), (1, 3)]
