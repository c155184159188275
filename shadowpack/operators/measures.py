"""One-pass evaluation at given prices, and the measures built on it."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.kernels import Caps, blocks, gathered, total_of
from ..plans.problem import KnapsackProblem
from ..plans.session import ship_package
from .subproblem import packed_of, solve_block


@dataclass
class Evaluation:
    """Uses, values and bounds of the greedy solution at some prices."""

    prices: list[float]
    used: list[float]
    budgets: list[float]
    primal: float
    group_values: float
    taken: int

    @property
    def dual(self) -> float:
        return self.group_values + sum(p * b for p, b in zip(self.prices, self.budgets, strict=True))

    @property
    def gap(self) -> float:
        return self.dual - self.primal

    @property
    def violations(self) -> list[float]:
        return [max(u - b, 0.0) / b for u, b in zip(self.used, self.budgets, strict=True)]

    @property
    def max_violation(self) -> float:
        return max(self.violations)

    @property
    def n_violated(self) -> int:
        return sum(v > 0 for v in self.violations)

    @property
    def slackness(self) -> list[float]:
        """price * (used - budget) of each knapsack; 0 at an optimum."""
        return [p * (u - b) for p, u, b in zip(self.prices, self.used, self.budgets, strict=True)]


def evaluate_many(problem: KnapsackProblem, price_vectors: list[list[float]], tolerant: bool = False) -> list[Evaluation]:
    """Evaluates several price vectors in one pass over the groups. Each task yields one row per vector; the
    driver gets one row per vector, whatever the number of groups."""
    ship_package(problem.items.sparkSession)
    k, caps, vectors = problem.k, Caps(problem.hierarchy, problem.levels), np.array(price_vectors, dtype=float).reshape(len(price_vectors), -1)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((vectors.shape[0], k + 3))
        for batch in gathered(batches):
            for block in blocks(batch, k):
                levels = caps.nodes(block)
                for v, price in enumerate(vectors):
                    net, take = solve_block(block, price, caps, tolerant, levels)
                    amount = take.astype(float)
                    total[v, :k] += block.total_used(take, k)
                    total[v, k] += total_of(amount, block.profit)
                    total[v, k + 1] += total_of(amount, net)
                    total[v, k + 2] += take.sum()
        n = total.size
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(n)), pa.array(total.ravel())], ["cell", "x"])

    rows = packed_of(problem).mapInArrow(kernel, "cell long, x double").groupBy("cell").agg(F.sum("x").alias("x")).collect()
    cells = np.zeros(vectors.shape[0] * (k + 3))
    for r in rows:
        cells[r["cell"]] = r["x"]
    return [Evaluation(list(map(float, p)), x[:k].tolist(), problem.budgets, float(x[k]), float(x[k + 1]), int(x[k + 2])) for p, x in zip(vectors, cells.reshape(-1, k + 3), strict=True)]


def evaluate(problem: KnapsackProblem, prices: list[float], tolerant: bool = False) -> Evaluation:
    return evaluate_many(problem, [prices], tolerant)[0]


def scaled_budgets(problem: KnapsackProblem, numerator: int = 1, denominator: int = 2) -> list[float]:
    """Whole-number budgets: a fraction of what the groups would use if nothing had a price."""
    free = evaluate(problem, [0.0] * problem.k)
    return [float(max(1, int(u) * numerator // denominator)) for u in free.used]


def used_by_knapsack(decisions: DataFrame, items: DataFrame, budgets: list[float]) -> DataFrame:
    """knapsack_id (from 1), budget, used: one row per budget, from long decisions and items."""
    chosen = decisions.join(items.select("group_id", "item_id", "needs"), ["group_id", "item_id"])
    used = chosen.select("units", F.posexplode("needs").alias("k", "need")).groupBy("k").agg(F.sum(F.col("need") * F.col("units")).alias("used"))
    table = items.sparkSession.createDataFrame([(i + 1, b) for i, b in enumerate(budgets)], "knapsack_id int, budget double")
    return table.join(used.select((F.col("k") + 1).alias("knapsack_id"), "used"), "knapsack_id", "left").withColumn("used", F.coalesce("used", F.lit(0.0)))


def violation_ratios(used: DataFrame) -> DataFrame:
    """used, budget -> excess over the budget as a share of it, 0 within."""
    return used.withColumn("ratio", F.greatest(F.col("used") - F.col("budget"), F.lit(0.0)) / F.col("budget"))


def primal_value(decisions: DataFrame, items: DataFrame) -> float:
    row = decisions.join(items, ["group_id", "item_id"]).agg(F.sum(F.col("profit") * F.col("units"))).first()
    return float(row[0] or 0.0)


def local_violations(problem: KnapsackProblem, decisions: DataFrame) -> int:
    """Groups and cap sets over their cap (0 for every valid solution)."""
    chosen = decisions.join(problem.items, ["group_id", "item_id"])
    n = 0
    for column, cap in problem.levels:
        n += chosen.groupBy("group_id", *([column] if column else [])).agg(F.sum("units").alias("u")).where(F.col("u") > cap).count()
    for s in problem.hierarchy.topo():
        part = chosen if s.items is None else chosen.where(F.col("item_id").isin(sorted(s.items)))
        n += part.groupBy("group_id").agg(F.sum("units").alias("u")).where(F.col("u") > s.cap).count()
    return n


def optimality_ratio(primal: float, lp_value: float) -> float:
    return primal / lp_value if lp_value else 1.0


def iteration_saving(without: int, with_presolve: int) -> float:
    return 1 - with_presolve / without


def k1_gap_bound(problem: KnapsackProblem) -> float:
    """With one knapsack the gap is at most the largest profit of any item."""
    return float(problem.items.agg(F.max("profit")).first()[0] or 0.0)


def emission_cost(problem: KnapsackProblem, prices: list[float], delta: float | None = None) -> dict[str, int]:
    """What one general iteration emits and what is left of it after bucketing: rows that would be shuffled by
    an exact reduce, and rows of the histogram."""
    from .candidates import scd_emissions
    from .thresholds import bucket_histogram

    out = scd_emissions(problem, prices).persist()
    table = problem.items.sparkSession.createDataFrame([(k + 1, float(p)) for k, p in enumerate(prices)], "knapsack int, price double")
    try:
        return {"emitted_rows": out.count(), "histogram_rows": bucket_histogram(out, table, delta).count()}
    finally:
        out.unpersist()
