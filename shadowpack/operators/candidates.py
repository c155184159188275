"""Critical prices and emissions: where lowering one price changes what a group takes."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import price_row
from ..plans.kernels import Caps, blocks, linear_block
from ..plans.kernels import emissions as block_emissions
from ..plans.problem import KnapsackProblem
from ..plans.session import ship_package
from .subproblem import packed_of

EMISSIONS = "knapsack int, v1 double, v2 double"


def candidate_prices(intercepts: Column, slopes: Column) -> Column:
    """Distinct critical prices of one group and knapsack, descending, from arrays of the items' intercepts
    (profit less all other priced needs) and needs: zero crossings and pairwise crossings, where
    finite and positive. Built-in array functions only."""
    lines = F.arrays_zip(intercepts.alias("i"), slopes.alias("s"))
    zero = F.transform(F.filter(lines, lambda x: x["s"] > 0), lambda x: x["i"] / x["s"])
    pairs = F.flatten(F.transform(lines, lambda a: F.transform(F.filter(lines, lambda b: b["s"] < a["s"]), lambda b: (a["i"] - b["i"]) / (a["s"] - b["s"]))))
    return F.sort_array(F.array_distinct(F.filter(F.concat(zero, pairs), lambda x: x > 0)), asc=False)


def scd_emissions(problem: KnapsackProblem, prices: list[float], knapsacks: list[int] | None = None, eval_at: str = "segment") -> DataFrame:
    """(knapsack from 1, v1, v2) of every group by the general map: all critical prices of each knapsack,
    descending, the group solved between each two, growth of use emitted."""
    ship_package(problem.items.sparkSession)
    problem.hierarchy.require_laminar()
    k, price, caps = problem.k, np.array(prices, dtype=float), Caps(problem.hierarchy, problem.levels)
    chosen = list(range(k)) if knapsacks is None else [x - 1 for x in knapsacks]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch, k, candidate_bytes(batch)):
                levels = caps.nodes(block)
                for x in chosen:
                    v1, v2 = block_emissions(block, price, x, levels, eval_at)
                    if v1.size:
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(v1.size, x + 1, dtype=np.int32)), pa.array(v1), pa.array(v2)], ["knapsack", "v1", "v2"])

    return packed_of(problem).mapInArrow(kernel, EMISSIONS)


def linear_emissions(problem: KnapsackProblem, prices: list[float], knapsacks: list[int] | None = None) -> DataFrame:
    """(knapsack, v1, v2) of a packed sparse problem by the linear-time map: the two rivals of each group are
    selected, not sorted out. A narrow map."""
    ship_package(problem.items.sparkSession)
    k, price, q = problem.k, np.array(prices, dtype=float), Caps(problem.hierarchy, problem.levels).single()
    chosen = np.array(knapsacks or range(1, k + 1))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch, k):
                knapsack, v1, v2 = linear_block(block, price, q)
                mine = np.isin(knapsack, chosen)
                if mine.any():
                    yield pa.RecordBatch.from_arrays([pa.array(knapsack[mine].astype(np.int32)), pa.array(v1[mine]), pa.array(v2[mine])], ["knapsack", "v1", "v2"])

    return packed_of(problem).mapInArrow(kernel, EMISSIONS)


def candidate_bytes(batch: pa.RecordBatch) -> int | Callable[[int], int]:
    """Bytes for each item's share of its group's candidates, by the batch's largest group, or by each block's own width if
    blocks are stored: they get fewer groups where there are many."""
    if "width" in batch.schema.names:
        return lambda m: 12 * m * (m + 1)
    m = int(np.diff(batch.column("item_ids").offsets.to_numpy()).max(initial=1))
    return 24 * max(1, m * (m + 1) // 2)


def sparse_packed(problem: KnapsackProblem) -> DataFrame:
    """group_id, entries: array of (item_id, knapsack, profit, need), for one-knapsack items."""
    return problem.items.groupBy("group_id").agg(F.sort_array(F.collect_list(F.struct("item_id", "knapsack", "profit", "need"))).alias("entries"))


def sparse_emissions(entries: DataFrame, prices: list[float], q: int) -> DataFrame:
    """The linear-time map for items of one knapsack each and one cap q per group: at most one critical price
    per item, against the (q+1)-th adjusted profit if the item is among the top q (ties inside), else
    against the q-th; a missing one counts as 0. Array functions on packed rows: a narrow map."""
    row = price_row(entries.sparkSession, prices)
    adjusted = F.transform("entries", lambda e: F.greatest(e["profit"] - F.element_at("prices", e["knapsack"]) * e["need"], F.lit(0.0)))
    table = entries.crossJoin(row).withColumn("adjusted", adjusted).withColumn("ordered", F.sort_array("adjusted", asc=False))
    table = table.withColumn("qth", F.coalesce(F.get("ordered", F.lit(q - 1)), F.lit(0.0))).withColumn("next", F.coalesce(F.get("ordered", F.lit(q)), F.lit(0.0)))
    found = F.zip_with("entries", "adjusted", lambda e, a: F.struct(e["knapsack"].alias("knapsack"), e["profit"].alias("profit"), e["need"].alias("need"), F.when(a >= F.col("qth"), F.col("next")).otherwise(F.col("qth")).alias("rival")))
    flat = table.select(F.inline(F.filter(found, lambda x: (x["profit"] > x["rival"]) & (x["need"] > 0))))
    return flat.select("knapsack", ((F.col("profit") - F.col("rival")) / F.col("need")).alias("v1"), F.col("need").alias("v2"))


def is_linear_case(problem: KnapsackProblem) -> bool:
    """Whether the linear-time map applies: every item uses at most one knapsack, no two items of a group share
    one, units are 1, and one cap covers the whole group."""
    if problem.linear is None:
        problem.linear = _is_linear(problem)
    return problem.linear


def _is_linear(problem: KnapsackProblem) -> bool:
    if Caps(problem.hierarchy, problem.levels).single() is None or not problem.sparse:
        return False
    bad = problem.items.agg(F.count_if(F.coalesce(F.col("max_units"), F.lit(2)) != 1)).first()[0]
    return not bad and problem.items.groupBy("group_id", "knapsack").count().where("count > 1").limit(1).count() == 0
