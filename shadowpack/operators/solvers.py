"""Price updates: dual descent, coordinate descent in its modes, and the end-to-end solve."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame

from ..plans.problem import KnapsackProblem, discard
from .candidates import is_linear_case, linear_emissions, scd_emissions
from .cuts import find_cut
from .measures import Evaluation, evaluate, evaluate_many
from .passes import Memory, next_prices
from .presolve import sample_problem
from .subproblem import greedy_take
from .thresholds import threshold_exact, threshold_ranged

MOST_ITERATIONS, TOLERANCE = 50, 1e-6
#: Polishing: relative steps per relative excess, and margins on all prices.
POLISH_STEPS, POLISH_MARGINS = (0.25, 0.5, 1.0, 2.0), (-0.005, 0.005, 0.02)


@dataclass
class Solution:
    prices: list[float]
    converged: bool
    iterations: int
    history: list[dict] = field(default_factory=list)
    decisions: DataFrame | None = None
    metrics: dict = field(default_factory=dict)


def has_converged(old: list[float], new: list[float], tol: float = TOLERANCE) -> bool:
    return all(abs(n - o) <= tol * max(1.0, abs(o)) for o, n in zip(old, new, strict=True))


def _record(history: list[dict], iteration: int, e: Evaluation, began: float) -> None:
    history.append({"iter": iteration, "prices": e.prices, "used": e.used, "primal": e.primal, "dual": e.dual, "max_violation": e.max_violation, "n_violated": e.n_violated, "seconds": time.time() - began})


def history_frame(problem: KnapsackProblem, history: list[dict]) -> DataFrame:
    """One row per iteration and knapsack."""
    rows = [(h["iter"], k + 1, float(h["prices"][k]), float(h["used"][k]), problem.budgets[k], h["primal"], h["dual"], h["max_violation"], h["seconds"]) for h in history for k in range(problem.k)]
    return problem.items.sparkSession.createDataFrame(rows, "iter int, knapsack_id int, price double, used double, budget double, primal double, dual double, max_violation double, seconds double")


def dd_update(prices: list[float], used: list[float], budgets: list[float], alpha: float) -> list[float]:
    """Each price moves with its knapsack's excess use, and never below 0."""
    return [max(0.0, p + alpha * (u - b)) for p, u, b in zip(prices, used, budgets, strict=True)]


def dual_descent(problem: KnapsackProblem, alpha: float, prices0: list[float] | float = 1.0, max_iter: int = MOST_ITERATIONS, tol: float = TOLERANCE) -> Solution:
    prices = start_prices(problem, prices0)
    history: list[dict] = []
    for t in range(max_iter):
        began = time.time()
        e = evaluate(problem, prices)
        _record(history, t, e, began)
        new = dd_update(prices, e.used, problem.budgets, alpha)
        done = has_converged(prices, new, tol)
        prices = new
        if done:
            return Solution(prices, True, t + 1, history)
    return Solution(prices, False, max_iter, history)


def dd_sweep(problem: KnapsackProblem, alphas: list[float], prices0: list[float] | float = 1.0, max_iter: int = 20) -> dict[float, Solution]:
    """Dual descent for several step sizes at once: each pass over the groups evaluates all of them."""
    prices = {a: start_prices(problem, prices0) for a in alphas}
    histories: dict[float, list[dict]] = {a: [] for a in alphas}
    for t in range(max_iter):
        began = time.time()
        for a, e in zip(alphas, evaluate_many(problem, [prices[a] for a in alphas]), strict=True):
            _record(histories[a], t, e, began)
            prices[a] = dd_update(prices[a], e.used, problem.budgets, a)
    return {a: Solution(prices[a], False, max_iter, histories[a]) for a in alphas}


def coordinate_descent(problem: KnapsackProblem, prices0: list[float] | float = 1.0, cycles: int = 10, probes: int = 9, rounds: int = 8, tol: float = 1e-4) -> Solution:
    """Plain coordinate descent without candidate prices: the smallest price of one knapsack at which its use
    fits, others fixed, by a narrowing grid; all probes of a round share one pass."""
    prices = start_prices(problem, prices0)
    history: list[dict] = []
    for t in range(cycles):
        began, old = time.time(), list(prices)
        for k in range(problem.k):
            fits = lambda p, k=k: p.used[k] <= problem.budgets[k]
            low, high = 0.0, max(prices[k], 1e-6)
            if fits(evaluate(problem, [*prices[:k], 0.0, *prices[k + 1 :]])):
                prices[k] = 0.0
                continue
            while not fits(evaluate(problem, [*prices[:k], high, *prices[k + 1 :]])):
                low, high = high, high * 4
            for _ in range(rounds):
                grid = [low + (high - low) * (i + 1) / (probes + 1) for i in range(probes)]
                ok = [fits(e) for e in evaluate_many(problem, [[*prices[:k], x, *prices[k + 1 :]] for x in grid])]
                first = ok.index(True) if True in ok else probes
                low, high = (grid[first - 1] if first else low), (grid[first] if first < probes else high)
                if high - low <= tol * 0.01 * max(1.0, high):
                    break
            prices[k] = high
        _record(history, t, evaluate(problem, prices), began)
        if has_converged(old, prices, tol):
            return Solution(prices, True, t + 1, history)
    return Solution(prices, False, cycles, history)


def blocks_of(mode: str, k: int, blocks: list[list[int]] | None) -> list[list[int]]:
    """Which knapsacks (from 1) are updated together: all ('sync'), one at a time ('cyclic') or as given."""
    if mode == "sync":
        return [list(range(1, k + 1))]
    if mode == "cyclic":
        return [[i] for i in range(1, k + 1)]
    if not blocks or sorted(x for b in blocks for x in b) != list(range(1, k + 1)):
        raise ValueError("blocks must hold every knapsack once")
    return blocks


def scd(
    problem: KnapsackProblem,
    prices0: list[float] | float | str = 1.0,
    mode: str = "sync",
    blocks: list[list[int]] | None = None,
    solver: str = "auto",
    reduce: str = "bucketed",
    interpolate: str = "linear",
    threshold: str = "crossing",
    delta: float | None = None,
    max_iter: int = MOST_ITERATIONS,
    tol: float = TOLERANCE,
    early_stop_violation: float | None = None,
    trace: bool = True,
    eval_at: str = "segment",
    damping: bool = True,
) -> Solution:
    """Synchronous, cyclic or block coordinate descent over critical prices.

    solver: 'linear' (one-knapsack items, one cap), 'general', or 'auto'. reduce: 'bucketed' by histograms made
    inside the pass, with `interpolate` within the crossing bucket; 'exact', the same with the crossing bucket
    cut until it holds one price; 'ranged' and 'window' move the emissions themselves, dealt out by price
    ranges or by one window for each knapsack (few emissions only). threshold: 'crossing', or 'last_fit' where
    prices are exact. Histogram passes measure the old prices as they go; the other two need a pass more for
    a trace.

    Prices that move at once can overshoot together where knapsacks share items; with damping, a price that
    swings back by about as much as it came takes half steps, and full ones again once it moves steadily. A
    price vector that comes back is a cycle: the mode then falls back to 'cyclic', whose steps never raise
    the dual bound. The prices of the best dual bound seen are returned if nothing converges; with a
    negative tol, which always runs max_iter iterations, the last ones."""
    if threshold not in ("crossing", "last_fit"):
        raise ValueError(f"unknown threshold {threshold!r}")
    if reduce not in ("bucketed", "exact", "ranged", "window"):
        raise ValueError(f"unknown reduce {reduce!r}")
    interpolate = "exact" if reduce == "exact" else interpolate
    fused = reduce in ("bucketed", "exact")
    if threshold == "last_fit" and fused and interpolate != "exact":
        raise ValueError("last_fit needs exact prices: reduce='exact', or interpolate='exact'")
    prices = start_prices(problem, prices0)
    linear = is_linear_case(problem) if solver == "auto" else solver == "linear"
    spark = problem.items.sparkSession
    history: list[dict] = []
    seen: set[tuple] = set()
    visited: list[list[float]] = []
    best: tuple[float, list[float]] | None = None
    memory = Memory()
    converged, t = False, 0
    share, last = [1.0] * problem.k, [0.0] * problem.k
    for t in range(max_iter):
        began, old = time.time(), list(prices)
        visited.append(old)
        e = evaluate(problem, prices) if trace and not fused else None
        stop = False
        for i, block in enumerate(blocks_of(mode, problem.k, blocks)):
            if fused:
                found, measured = next_prices(problem, prices, block, linear, interpolate, threshold, delta, eval_at=eval_at, measure=i == 0, memory=memory)
                e = measured if i == 0 else e
            else:
                found = _by_emissions(spark, problem, prices, block, linear, reduce, threshold, eval_at)
            if i == 0 and e is not None:
                if best is None or e.dual < best[0]:
                    best = (e.dual, old)
                stop = early_stop_violation is not None and t > 0 and e.max_violation <= early_stop_violation
                if stop:
                    break
            for k, p in found.items():
                prices[k - 1] = p
        if trace and e is not None:
            _record(history, t, e, began)
        if stop:
            break
        if has_converged(old, prices, tol):
            converged = True
            break
        if damping and mode != "cyclic":
            prices = _damped(old, prices, share, last)
        key = tuple(round(p, 12) for p in prices)
        if key in seen and mode != "cyclic":
            mode, seen = "cyclic", set()
        seen.add(key)
    if not converged and tol >= 0 and not stop:
        # one pass tells which of the prices seen has the best bound
        rest = [prices] if best is not None else [*visited, prices]
        for e in evaluate_many(problem, rest):
            if best is None or e.dual <= best[0]:
                best = (e.dual, e.prices)
        prices = list(best[1])
    return Solution(prices, converged, t + 1, history)


def _by_emissions(spark, problem: KnapsackProblem, prices: list[float], block: list[int], linear: bool, reduce: str, threshold: str, eval_at: str) -> dict[int, float]:
    """New prices from the emissions themselves, which leave the tasks."""
    out = linear_emissions(problem, prices, block) if linear else scd_emissions(problem, prices, block, eval_at)
    part = {k: problem.budgets[k - 1] for k in block}
    if reduce == "ranged":
        return threshold_ranged(out, part, threshold=threshold)
    table = spark.createDataFrame(list(part.items()), "knapsack int, budget double")
    return {r["knapsack"]: r["price"] for r in threshold_exact(out, table, threshold).collect()}


def _damped(old: list[float], new: list[float], share: list[float], last: list[float]) -> list[float]:
    """Prices after damped steps; updates each price's share of the full step and its last full step."""
    out = []
    for k, (a, b) in enumerate(zip(old, new, strict=True)):
        step = b - a
        swings = step * last[k] < 0 and abs(step) > 0.6 * abs(last[k])
        share[k] = max(share[k] / 2, 1 / 16) if swings else min(1.0, share[k] * 1.25)
        last[k] = step
        out.append(a + share[k] * step)
    return out


def presolve_prices(problem: KnapsackProblem, n: int = 10_000, seed: int = 0, prices0: list[float] | float | str = 1.0, **options) -> list[float]:
    """Prices of a sample of about n groups under proportional budgets; a start for the full solve, not a
    substitute (on all groups they may violate budgets)."""
    part, got, _ = sample_problem(problem, n, seed)
    try:
        return scd(part, prices0, **({"trace": False, "reduce": "exact"} | options)).prices if got else start_prices(problem, prices0)
    finally:
        discard(part.packed)


def solve(problem: KnapsackProblem, method: str = "scd", presolve: int | None = None, repair_budgets: bool = True, only_violating: bool = False, alpha: float = 1e-3, polish: int = 0, **options) -> Solution:
    """Presolve, iterate, polish if asked (that many passes), decide, repair, measure. After the repair every
    budget holds."""
    problem = problem if problem.packed is not None else problem.pack()
    start = options.pop("prices0", 1.0)
    if presolve:
        start = presolve_prices(problem, presolve, prices0=start)
    if method == "scd":
        out = scd(problem, start, **options)
    elif method == "dd":
        out = dual_descent(problem, alpha, start, **options)
    elif method == "cd":
        out = coordinate_descent(problem, start, **options)
    else:
        raise ValueError(f"unknown method {method!r}")
    if polish:
        out.prices = polished(problem, out.prices, polish)
    return finish(problem, out, repair_budgets, only_violating)


def finish(problem: KnapsackProblem, out: Solution, repair_budgets: bool = True, only_violating: bool = False) -> Solution:
    """Decisions at the solution's prices, repaired, and what they are worth."""
    e = evaluate(problem, out.prices, tolerant=True)
    out.metrics = {"primal_before_repair": e.primal, "dual": e.dual, "max_violation_before_repair": e.max_violation, "n_violated_before_repair": e.n_violated, "dropped": 0}
    primal, dropped = e.primal, None
    if repair_budgets and e.n_violated:
        cut = find_cut(problem, out.prices, e.used, only_violating)
        primal, dropped, out.metrics["dropped"] = cut.kept, cut.rule, cut.dropped
    out.metrics |= {"primal": primal, "gap": e.dual - primal, "relative_gap": (e.dual - primal) / primal if primal else 0.0}
    # one boundary says which groups go, so decisions are one narrow pass over the groups
    out.decisions = greedy_take(problem, out.prices, tolerant=True, dropped=dropped)
    return out


def polished(problem: KnapsackProblem, prices: list[float], passes: int = 8) -> list[float]:
    """Prices near the given ones that should be worth most after the repair.

    Among prices of nearly the same dual bound, use may differ by percents where groups are few, and each percent
    of excess costs a percent of all groups. A pass evaluates several steps at once: each price moves with its
    knapsack's relative excess, or all rise by a margin. The best by primal value over 1 + largest
    violation is the next start; without a better one, steps shrink."""

    def worth(e: Evaluation) -> float:
        return e.primal / (1 + e.max_violation)

    best = evaluate(problem, prices)
    reach = 1.0
    for _ in range(passes):
        excess = [u / b - 1 for u, b in zip(best.used, problem.budgets, strict=True)]
        ways = [[p * max(0.5, 1 + reach * x * min(d, 0.25)) for p, d in zip(best.prices, excess, strict=True)] for x in POLISH_STEPS]
        ways += [[p * max(0.5, 1 + reach * x * max(0.0, min(d, 0.25))) for p, d in zip(best.prices, excess, strict=True)] for x in POLISH_STEPS]
        ways += [[p * (1 + reach * x) for p in best.prices] for x in POLISH_MARGINS]
        found = max(evaluate_many(problem, ways), key=worth)
        if worth(found) > worth(best):
            best = found
        else:
            reach /= 2
    return best.prices


def start_prices(problem: KnapsackProblem, prices0: list[float] | float | str) -> list[float]:
    """One price for all, given ones, or 'random' ('random:SEED'): uniform in [0, 2), from the seed alone."""
    if isinstance(prices0, str):
        kind, _, seed = prices0.partition(":")
        if kind != "random":
            raise ValueError(f"unknown start {prices0!r}")
        return np.random.default_rng(int(seed or 0)).uniform(0.0, 2.0, problem.k).tolist()
    return [float(prices0)] * problem.k if isinstance(prices0, (int, float)) else [float(p) for p in prices0]
