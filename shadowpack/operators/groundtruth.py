"""Exact answers for small instances, and plain baselines."""

from __future__ import annotations

from itertools import product

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.problem import KnapsackProblem, written


#: Cells (items x budget) that the exact table may fill.
MOST_CELLS = 1 << 30


def _rows(problem: KnapsackProblem, most: int) -> list:
    rows = problem.items.limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError("too many items")
    return sorted(rows, key=lambda r: (r["group_id"], r["item_id"]))


def brute_force(problem: KnapsackProblem, budgets: list[float] | None = None) -> float:
    """The best profit over all 0/1 choices (at most 20 items in all)."""
    rows = _rows(problem, 20)
    take = np.array(list(product((0, 1), repeat=len(rows))), dtype=np.int64).reshape(-1, len(rows))
    needs = np.array([r["needs"] for r in rows]).reshape(len(rows), -1)
    ok = (take @ needs <= np.array(budgets or problem.budgets) + 1e-9).all(axis=1)
    for g in {r["group_id"] for r in rows}:
        mine = [i for i, r in enumerate(rows) if r["group_id"] == g]
        for s in problem.hierarchy.topo():
            inside = [i for i in mine if s.items is None or rows[i]["item_id"] in s.items]
            ok &= take[:, inside].sum(axis=1) <= s.cap
        for column, cap in problem.levels:
            for value in {rows[i][column] if column else None for i in mine}:
                ok &= take[:, [i for i in mine if not column or rows[i][column] == value]].sum(axis=1) <= cap
    return float((take @ np.array([r["profit"] for r in rows]))[ok].max())


def dp_exact(problem: KnapsackProblem) -> float:
    """The best profit for one knapsack with whole needs and budget, by a table over the budget. Groups take at
    most one item under a cap of 1, else any. Refuses more than MOST_CELLS items x budget."""
    if problem.k != 1:
        raise ValueError("one knapsack only")
    budget = int(problem.budgets[0])
    best = np.zeros(budget + 1)
    groups: dict[int, list] = {}
    for r in _rows(problem, MOST_CELLS // (budget + 1)):
        groups.setdefault(r["group_id"], []).append((int(r["needs"][0]), r["profit"]))
    one = problem.hierarchy.single_cap() == 1
    for options in groups.values():
        for choice in [options] if one else [[o] for o in options]:
            new = best.copy()
            for need, profit in choice:
                if need <= budget:
                    new[need:] = np.maximum(new[need:], best[: budget + 1 - need] + profit)
            best = new
    return float(best[budget])


def by_density(items: DataFrame) -> DataFrame:
    """items (item_id, profit, need > 0) with `before`: the need of all items of more profit per need (equal ones by
    item_id). Items are dealt out by ranges of that order and written; running sums stay inside a range, and
    only a sum for each range is prefixed on the driver."""
    order = [F.desc("_density"), F.col("item_id")]
    dealt = items.withColumn("_density", F.col("profit") / F.col("need")).repartitionByRange(*order).withColumn("_part", F.spark_partition_id())
    dealt = written(dealt)
    ahead, rows = 0.0, []
    for r in dealt.groupBy("_part").agg(F.sum("need").alias("need")).orderBy("_part").collect():
        rows.append((r["_part"], ahead))
        ahead += r["need"]
    parts = items.sparkSession.createDataFrame(rows, "_part int, _ahead double")
    own = F.coalesce(F.sum("need").over(Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    return dealt.withColumn("_own", own).join(F.broadcast(parts), "_part").withColumn("before", F.col("_own") + F.col("_ahead")).drop("_part", "_own", "_ahead", "_density")


def fractional_knapsack(items: DataFrame, budget: float) -> DataFrame:
    """One knapsack, one item per group, fractions allowed: items by profit per need while the budget lasts;
    the item where it ends is split. items: item_id, profit, need (> 0). Adds `part` (0..1)."""
    part = F.greatest(F.lit(0.0), F.least(F.lit(1.0), (F.lit(float(budget)) - F.col("before")) / F.col("need")))
    return by_density(items).withColumn("part", part).drop("before")


def density_greedy(items: DataFrame, budget: float) -> DataFrame:
    """A price-free floor: items by profit per need, whole, as long as the running need fits."""
    return by_density(items).where(F.col("before") + F.col("need") <= F.lit(float(budget))).drop("before")
