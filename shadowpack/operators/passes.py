"""One pass over the packed groups per iteration: a histogram of critical prices for each knapsack, and the
measures at the prices the pass started from.

Critical prices are counted inside the kernel, so that at most knapsacks x buckets rows leave a task, however
many groups it holds."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.kernels import Buckets, Caps, Histogram, Settled, blocks, gathered, linear_block, total_of, use_at
from ..plans.kernels import emissions as block_emissions
from ..plans.problem import KnapsackProblem
from ..plans.session import ship_package
from .candidates import candidate_bytes
from .measures import Evaluation
from .subproblem import packed_of, solve_block

HISTOGRAM = "knapsack int, bucket long, mass double, lo double, hi double, n long"
#: Even buckets by which a crossing bucket is cut; emissions from which on each price is counted by itself.
SUB_BUCKETS, FEW = 4096, 20_000
#: Probes by which the general map first finds out where a price lies, as multiples of the old price.
PROBES, FINER = (0.0, 1 / 64, 1 / 8, 1 / 2, 1.0, 2.0, 8.0), 6


def pass_rows(problem: KnapsackProblem, prices: list[float], buckets: dict[int, Buckets], linear: bool, eval_at: str = "segment", measure: bool = True, windows: dict[int, tuple[float, float]] | None = None, grids: dict[int, list[float]] | None = None) -> DataFrame:
    """Rows of HISTOGRAM for the knapsacks (from 1) of `buckets`, summed over tasks. With measure, also rows of
    knapsack 0: uses, profit, group values and takes at `prices`, one bucket each. windows: where the general
    map looks at critical prices one by one. grids: knapsacks whose use is taken at some prices only, in rows of
    the negative knapsack."""
    ship_package(problem.items.sparkSession)
    buckets = {x: replace(b, top=windows[x][1]) if windows and x in windows else b for x, b in buckets.items()}
    if not linear:
        problem.hierarchy.require_laminar()
    k, price, caps = problem.k, np.array(prices, dtype=float), Caps(problem.hierarchy, problem.levels)
    q, windows, grids = caps.single(), windows or {}, grids or {}

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = {x: Histogram(b) for x, b in buckets.items()}
        total, uses = np.zeros(k + 3), {x: np.zeros(len(g)) for x, g in grids.items()}
        for batch in gathered(batches):
            for block in blocks(batch, k, 64 if linear else candidate_bytes(batch)):
                levels = caps.nodes(block)
                if measure:
                    net, take = solve_block(block, price, caps, False, levels)
                    amount = take.astype(float)
                    total[:k] += block.total_used(take, k)
                    total[k:] += total_of(amount, block.profit), total_of(amount, net), take.sum()
                if linear:
                    knapsack, v1, v2 = linear_block(block, price, q)
                    for x, h in found.items():
                        mine = knapsack == x
                        h.add(v1[mine], v2[mine])
                else:
                    needs = block.dense(k)
                    near = {x for x, w in windows.items() if w[0] <= prices[x - 1] <= w[1]} if measure and Settled.fits(block) else set()
                    settled = Settled(block, price, levels, net, take, needs) if near else None
                    for x, h in found.items():
                        h.add(*(settled.emissions(x - 1, windows[x]) if x in near else block_emissions(block, price, x - 1, levels, eval_at, windows.get(x), needs)))
                    for x, g in grids.items():
                        uses[x] += use_at(block, price, x - 1, levels, g, needs)
        out = [[np.full(rows[0].size, x, dtype=np.int32), *rows] for x, rows in ((x, h.merge()) for x, h in found.items())]
        for x, mass in [*((-x, u) for x, u in uses.items()), *([(0, total)] if measure else [])]:
            n = np.arange(mass.size)
            out.append([np.full(mass.size, x, dtype=np.int32), n, mass, np.zeros(mass.size), np.zeros(mass.size), n])
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*out, strict=True)], ["knapsack", "bucket", "mass", "lo", "hi", "n"])

    rows = packed_of(problem).mapInArrow(kernel, HISTOGRAM)
    return rows.groupBy("knapsack", "bucket").agg(F.sum("mass").alias("mass"), F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.sum("n").alias("n"))


def run_pass(problem: KnapsackProblem, prices: list[float], buckets: dict[int, Buckets], linear: bool, eval_at: str = "segment", measure: bool = True, windows: dict[int, tuple[float, float]] | None = None, grids: dict[int, list[float]] | None = None) -> tuple[dict[int, list], Evaluation | None, dict[int, np.ndarray]]:
    """(histogram rows by knapsack, highest prices first; evaluation; uses at the grids)."""
    by: dict[int, list] = {x: [] for x in buckets}
    total, uses = np.zeros(problem.k + 3), {x: np.zeros(len(g)) for x, g in (grids or {}).items()}
    for r in pass_rows(problem, prices, buckets, linear, eval_at, measure, windows, grids).collect():
        if r["knapsack"] > 0:
            by[r["knapsack"]].append(r)
        else:
            (uses[-r["knapsack"]] if r["knapsack"] else total)[r["bucket"]] = r["mass"]
    for rows in by.values():
        rows.sort(key=lambda r: -r["hi"])
    k = problem.k
    return by, Evaluation(list(map(float, prices)), total[:k].tolist(), problem.budgets, float(total[k]), float(total[k + 1]), int(total[k + 2])) if measure else None, uses


def first_buckets(price: float, delta: float | None, base: float | None, shifted: bool, even_width: float | None, exact: bool, few: bool) -> Buckets:
    if exact and few:
        return Buckets("value")
    if even_width:
        return Buckets("even", width=even_width)
    return Buckets("uneven", price, max(1.0, price) * 1e-5 if delta is None else delta, base, shifted)


class Memory:
    """What one iteration tells the next: how many emissions each knapsack had, and how far its price may move."""

    def __init__(self) -> None:
        self.counts: dict[int, int] = {}
        self.reach: dict[int, float] = {}

    def window(self, x: int, price: float, scale: float) -> tuple[float, float] | None:
        """Where the next price is looked for; None is everywhere."""
        reach = self.reach.get(x)
        if reach is None or reach >= 1.0:
            return None
        return (0.0, reach * scale) if price <= 0 else (price * (1 - reach), price * (1 + reach))

    def moved(self, x: int, old: float, new: float, scale: float) -> None:
        self.reach[x] = 0.02 + 3 * abs(new - old) / max(old, new, 1e-3 * scale, 1e-300)


def next_prices(
    problem: KnapsackProblem,
    prices: list[float],
    block: list[int],
    linear: bool,
    interpolate: str = "linear",
    threshold: str = "crossing",
    delta: float | None = None,
    base: float | None = None,
    shifted: bool = False,
    even_width: float | None = None,
    eval_at: str = "segment",
    measure: bool = True,
    memory: Memory | None = None,
) -> tuple[dict[int, float], Evaluation | None]:
    """New prices of the block's knapsacks, from histograms alone, and the evaluation at the old ones.

    interpolate: 'linear' on mass within the bucket where the budget is crossed, 'upper' (its highest price), or
    'exact': that bucket is cut further, in passes of their own, until it holds one price. The general map first
    looks near the old price, if the memory of earlier iterations says that it has settled, else takes
    the use at some probes and then at finer ones; critical prices are looked at one by one between two
    probes only."""
    memory = memory or Memory()
    exact, scale = interpolate == "exact", max(prices)
    buckets = {x: first_buckets(prices[x - 1], delta, base, shifted, even_width, exact, memory.counts.get(x, FEW + 1) <= FEW) for x in block}
    if linear or eval_at != "segment":
        found, evaluation, _ = run_pass(problem, prices, buckets, linear, eval_at, measure)
    else:
        windows = {x: w for x in block if (w := memory.window(x, prices[x - 1], scale))}
        unit = {x: prices[x - 1] if prices[x - 1] > 1e-9 * scale else scale / 16 or 1.0 for x in block}
        grids = {x: [unit[x] * y for y in PROBES] for x in block if x not in windows}
        found, evaluation, uses = run_pass(problem, prices, {x: buckets[x] for x in windows}, False, eval_at, measure, windows, grids)
        # what fits at no price at all needs no further look
        free = [x for x in grids if uses[x][0] <= problem.budgets[x - 1]]
        found |= {x: [] for x in free}
        near = {x: _bracket(g, uses[x], problem.budgets[x - 1]) for x, g in grids.items() if x not in free}
        grids = {x: np.linspace(*w, FINER + 2).tolist() for x, w in near.items() if w[1] < math.inf}
        if grids and sum(memory.counts.get(x, FEW + 1) for x in grids) > FEW:
            _, _, uses = run_pass(problem, prices, {}, False, eval_at, False, None, {x: g[1:-1] for x, g in grids.items()})
            near |= {x: _bracket([g[0], *g[1:-1], g[-1]], np.array([math.inf, *uses[x], 0.0]), problem.budgets[x - 1]) for x, g in grids.items()}
        for x, (low, high) in windows.items():
            if not _inside(found[x], problem.budgets[x - 1], (low, high)):
                over = sum(r["mass"] for r in found[x]) > problem.budgets[x - 1]
                near[x] = (high, math.inf) if over else (0.0, low)
        if near:
            found |= run_pass(problem, prices, {x: buckets[x] for x in near}, False, eval_at, False, near)[0]
        missed = {x: buckets[x] for x, w in near.items() if not _inside(found[x], problem.budgets[x - 1], w)}
        if missed:  # ties at the very edge of a window
            found |= run_pass(problem, prices, missed, False, eval_at, False)[0]
    memory.counts |= {x: sum(r["n"] for r in rows) for x, rows in found.items() if rows}
    out = {x: 0.0 for x in block}
    above = {x: 0.0 for x in block}
    fit: dict[int, float] = {}
    while buckets:
        again: dict[int, Buckets] = {}
        for x, b in buckets.items():
            for r in found[x]:
                if above[x] + r["mass"] > problem.budgets[x - 1]:
                    break
                above[x] += r["mass"]
                fit[x] = r["lo"]
            else:
                # everything fits; inside a cut bucket that is rounding: its lowest price is the one that crosses
                out[x] = 0.0 if b.high == float("inf") else b.low
                continue
            share = (problem.budgets[x - 1] - above[x]) / r["mass"]
            out[x] = r["hi"] if interpolate != "linear" else r["hi"] - share * (r["hi"] - r["lo"])
            if exact and r["lo"] < r["hi"]:
                width = (r["hi"] - r["lo"]) / SUB_BUCKETS
                fine = r["n"] <= FEW or r["lo"] + width <= r["lo"]
                again[x] = Buckets("value" if fine else "even", width=width or 1.0, low=r["lo"], high=r["hi"])
            elif exact and threshold == "last_fit":
                out[x] = fit.get(x, r["hi"])
        buckets = again
        if buckets:
            near = {} if linear or eval_at != "segment" else {x: (math.nextafter(b.low, -math.inf), b.high) for x, b in buckets.items()}
            found, _, _ = run_pass(problem, prices, buckets, linear, eval_at, False, near)
    for x, p in out.items():
        memory.moved(x, prices[x - 1], p, scale)
    return {x: float(p) for x, p in out.items()}, evaluation


def _bracket(grid: list[float], uses: np.ndarray, budget: float) -> tuple[float, float]:
    """The two neighbouring prices of the grid between which use comes over the budget."""
    i = int(np.flatnonzero(uses > budget).max())
    return grid[i], grid[i + 1] if i + 1 < len(grid) else math.inf


def _inside(rows: list, budget: float, window: tuple[float, float]) -> bool:
    """Whether the budget is crossed by prices of the window alone, or nowhere and the window goes down to 0."""
    mass = 0.0
    for r in rows:
        mass += r["mass"]
        if mass > budget:
            return r["hi"] <= window[1]
    return window[0] <= 0.0
