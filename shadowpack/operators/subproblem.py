"""The per-group problem at fixed prices."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import net_profit
from ..plans.hierarchy import Hierarchy
from ..plans.kernels import Block, Caps, blocks, greedy
from ..plans.problem import KnapsackProblem
from ..plans.session import ship_package
from .feasibility import Rule

DECISIONS = "group_id long, item_id int, units int"


def with_net(items: DataFrame, prices: list[float], needs: list[str] | None = None) -> DataFrame:
    """items with `net`; needs: names of need columns, or the array column `needs`."""
    columns = [F.col(n) for n in needs] if needs else [F.element_at("needs", i + 1) for i in range(len(prices))]
    return items.withColumn("net", net_profit(F.col("profit"), columns, prices))


def greedy_levels(items: DataFrame, levels: list[tuple[list[str], int]], group: str = "group_id", item: str = "item_id") -> DataFrame:
    """The greedy in relational form, on long items with `net`: keeps positive nets, then level by level,
    bottom-up, the best `cap` items of each node (order: net descending, item ascending). A level is
    (node columns, cap); rows with a null node column are in no node of that level. All windows share
    the group's partitioning."""
    kept = items.where("net > 0")
    for columns, cap in levels:
        inside = F.lit(True)
        for c in columns:
            inside = inside & F.col(c).isNotNull()
        rank = F.row_number().over(Window.partitionBy(group, *columns).orderBy(F.desc("net"), item))
        kept = kept.withColumn("_rank", rank).where(~inside | (F.col("_rank") <= cap)).drop("_rank")
    return kept


def hierarchy_levels(items: DataFrame, hierarchy: Hierarchy) -> tuple[DataFrame, list[tuple[list[str], list[int]]]]:
    """items with one node column per height of the hierarchy, and each level's caps by node."""
    levels = []
    for h, sets in enumerate(hierarchy.levels()):
        node: Column = F.lit(None).cast("int")
        for n, s in enumerate(sets):
            node = F.when(F.lit(True) if s.items is None else F.col("item_id").isin(sorted(s.items)), n).otherwise(node)
        items = items.withColumn(f"_node{h}", node)
        levels.append(([f"_node{h}"], [s.cap for s in sets]))
    return items, levels


def greedy_take_sql(problem: KnapsackProblem, prices: list[float]) -> DataFrame:
    """Decisions by windows over long items (unit items)."""
    items = with_net(problem.items, prices)
    levels: list[tuple[list[str], int | list[int]]] = [([c] if c else [], cap) for c, cap in problem.levels]
    if problem.hierarchy.sets:
        problem.hierarchy.require_laminar()
        items, named = hierarchy_levels(items, problem.hierarchy)
        levels += named
    kept = items.where("net > 0")
    for columns, cap in levels:
        rank = F.row_number().over(Window.partitionBy("group_id", *columns).orderBy(F.desc("net"), "item_id"))
        limit = F.lit(cap) if isinstance(cap, int) else F.element_at(F.array(*[F.lit(c) for c in cap]), F.col(columns[0]) + 1)
        free = F.col(columns[0]).isNull() if columns else F.lit(False)
        kept = kept.withColumn("_rank", rank).where(free | (F.col("_rank") <= limit)).drop("_rank")
    return kept.select("group_id", "item_id", F.lit(1).cast("int").alias("units"))


def topq_take(items: DataFrame, q: int) -> DataFrame:
    """The q best positive nets of each group (one cap over all items)."""
    return greedy_levels(items, [([], q)])


def greedy_units(items: DataFrame, cap: int) -> DataFrame:
    """Integer takes under one cap: each item as many of its max_units as room is left; adds `units`."""
    w = Window.partitionBy("group_id").orderBy(F.desc("net"), "item_id").rowsBetween(Window.unboundedPreceding, -1)
    before = F.coalesce(F.sum("max_units").over(w), F.lit(0))
    units = F.greatest(F.lit(0), F.least(F.col("max_units").cast("bigint"), F.lit(cap) - before))
    return items.where("net > 0").withColumn("units", units).where("units > 0")


def price_tolerance(profit: np.ndarray) -> np.ndarray:
    """Nets up to this count as zero in production solves: floating error can't flip a tied item."""
    return 1e-9 * np.maximum(1.0, profit)


def solve_block(block: Block, prices: np.ndarray, caps: Caps, tolerant: bool, levels: list[tuple[np.ndarray, np.ndarray]] | None = None) -> tuple[np.ndarray, np.ndarray]:
    net = block.priced(block.net(prices))
    return net, greedy(net, block.amounts, caps.nodes(block) if levels is None else levels, price_tolerance(block.profit) if tolerant else 0.0)


def greedy_take(problem: KnapsackProblem, prices: list[float], engine: str = "arrow", tolerant: bool = False, dropped: Rule | None = None) -> DataFrame:
    """Decisions (group_id, item_id, units) at fixed prices. engine: 'arrow' on packed rows (a narrow map),
    'sql' by windows on long rows. dropped: groups that a repair has dropped take nothing (arrow only)."""
    if engine == "sql":
        return greedy_take_sql(problem, prices)
    ship_package(problem.items.sparkSession)
    problem.hierarchy.require_laminar()
    k, price, caps = problem.k, np.array(prices, dtype=float), Caps(problem.hierarchy, problem.levels)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch, k):
                net, take = solve_block(block, price, caps, tolerant)
                if dropped is not None:
                    take[gone_groups(block, net, take, dropped, k)] = 0
                r, j = np.nonzero(take)
                yield pa.RecordBatch.from_arrays([pa.array(block.group[r]), pa.array(block.ids[r, j].astype(np.int32)), pa.array(take[r, j].astype(np.int32))], ["group_id", "item_id", "units"])

    return packed_of(problem).mapInArrow(kernel, DECISIONS)


def gone_groups(block: Block, net: np.ndarray, take: np.ndarray, rule: Rule, k: int) -> np.ndarray:
    """The same test as rule.gone(). The boundary group is told by its id: its value may be summed in another order."""
    value = (net * take).sum(axis=1)
    gone = (value < rule.value) | (value == rule.value) & (block.group < rule.group) | (block.group == rule.group)
    if rule.touching is not None:
        gone &= (block.used(take, k)[:, list(rule.touching)] > 0).any(axis=1)
    return gone


def packed_of(problem: KnapsackProblem) -> DataFrame:
    if problem.packed is None:
        raise ValueError("pack() the problem first")
    return problem.packed


def group_results(problem: KnapsackProblem, prices: list[float], tolerant: bool = False) -> DataFrame:
    """Per group with a non-empty take: group_id, value (net of the take), profit, used (array of K)."""
    ship_package(problem.items.sparkSession)
    k, price, caps = problem.k, np.array(prices, dtype=float), Caps(problem.hierarchy, problem.levels)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch, k):
                net, take = solve_block(block, price, caps, tolerant)
                some = np.flatnonzero(take.any(axis=1))
                used = block.used(take, k)[some]
                yield pa.RecordBatch.from_arrays([pa.array(block.group[some]), pa.array((net * take).sum(axis=1)[some]), pa.array((block.profit * take).sum(axis=1)[some]), pa.ListArray.from_arrays(pa.array(np.arange(some.size + 1, dtype=np.int32) * k), pa.array(used.ravel()))], ["group_id", "value", "profit", "used"])

    return packed_of(problem).mapInArrow(kernel, "group_id long, value double, profit double, used array<double>")


def group_value(decisions: DataFrame, items: DataFrame, prices: list[float]) -> DataFrame:
    """Net of the chosen items per group, from decisions and long items."""
    priced = with_net(items, prices)
    return decisions.join(priced, ["group_id", "item_id"]).groupBy("group_id").agg(F.sum(F.col("net") * F.col("units")).alias("group_value"))


def feasible_takes(units: list[int], sets: list[tuple[list[int], int]]) -> np.ndarray:
    """Every unit vector within the caps (positions of items in sets)."""
    if np.prod([u + 1 for u in units], dtype=float) > 1 << 20:
        raise ValueError("too many items for enumeration")
    rows = np.array(list(product(*[range(u + 1) for u in units])), dtype=np.int64).reshape(-1, len(units))
    ok = np.ones(rows.shape[0], dtype=bool)
    for members, cap in sets:
        ok &= rows[:, members].sum(axis=1) <= cap
    return rows[ok]


def exact_take(problem: KnapsackProblem, prices: list[float], value=None) -> DataFrame:
    """Exact per-group solver for any cap sets, crossing ones too, by enumeration (few items per group).

    value(ids, profits, take rows) -> value of each row: an own objective per group in place of the sum of
    profits (a decomposable non-linear objective); priced needs are subtracted in either case."""
    ship_package(problem.items.sparkSession)
    k, price, sets, levels = problem.k, np.array(prices, dtype=float), problem.hierarchy.topo(), problem.levels

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables: dict = {}
        for batch in batches:
            for block in blocks(batch, k):
                out, needs = [], block.dense(k)
                for g in range(block.group.size):
                    n = int(block.valid[g].sum())
                    ids = block.ids[g, :n]
                    named = [([j for j in range(n) if s.items is None or int(ids[j]) in s.items], s.cap) for s in sets]
                    code = 0
                    for column, cap in levels:
                        if column is None:
                            named.append((list(range(n)), cap))
                        else:
                            nodes = block.nodes[code][g, :n]
                            named += [(np.flatnonzero(nodes == x).tolist(), cap) for x in np.unique(nodes)]
                            code += 1
                    # no item takes more than the smallest cap over it
                    units = tuple(min([int(block.units[g, j]), *[c for m, c in named if j in m]]) for j in range(n))
                    key = (units, tuple((tuple(m), c) for m, c in named))
                    if key not in tables:
                        if len(tables) > 256:
                            tables.clear()
                        tables[key] = feasible_takes(list(units), [(m, c) for m, c in named if m])
                    rows = tables[key]
                    gain = rows @ block.profit[g, :n] if value is None else value(ids, block.profit[g, :n], rows)
                    best = rows[int(np.argmax(gain - rows @ (needs[g, :n] @ price)))]
                    out += [(block.group[g], ids[j], best[j]) for j in np.flatnonzero(best)]
                if out:
                    g_, i_, u_ = zip(*out, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(g_, pa.int64()), pa.array(i_, pa.int32()), pa.array(u_, pa.int32())], ["group_id", "item_id", "units"])

    return packed_of(problem).mapInArrow(kernel, DECISIONS)
