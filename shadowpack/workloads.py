"""The experiments, as functions that return tables of measures."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import candidates, groundtruth, measures, solvers, subproblem, thresholds
from .operators.feasibility import repair
from .operators.lp_bound import lp_bound
from .plans.hierarchy import Hierarchy
from .plans.problem import KnapsackProblem, discard
from .plans.session import ship_package
from .sources import instances
from .sources.lattice import lattice_problem, standard_hierarchy, uniform_items


#: Points of a grid that are solved at a time: small instances are bound by job starts, which overlap.
AT_ONCE = 8


def _grid(spark: SparkSession, points: list[Callable[[], tuple]]) -> list[tuple]:
    """The row of every point of a grid, in order."""
    ship_package(spark)
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return list(pool.map(lambda point: point(), points))


def solve_offers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Flagship: converged prices and repaired decisions of the user offers, as (group_id, item_id, units)."""
    return solvers.solve(instances.offers_problem(spark, sf_dir), reduce="exact", trace=False).decisions


def optimality_order_lines(spark: SparkSession, sf_dir: str, ks=(1, 2, 3, 4, 5)) -> DataFrame:
    """Optimality ratio against the linear relaxation on order lines: needs K, local scenario."""

    problems = instances.orders_problems(spark, sf_dir, ks, ("C1", "C2", "hier"))

    def point(k: int, scenario: str) -> tuple:
        p = problems[k, scenario]
        s = solvers.solve(p, max_iter=20)
        upper, lower = lp_bound(p, 1e-3, 40, [s.prices], s.history)
        return k, scenario, s.metrics["primal"], upper, lower, s.metrics["primal"] / upper, s.iterations, s.metrics["n_violated_before_repair"]

    # the largest first, so that none is left to end alone
    rows = _grid(spark, [lambda k=k, c=c: point(k, c) for k, c in reversed(problems)])
    discard(next(iter(problems.values())).packed)
    rows.sort(key=lambda r: ks.index(r[0]))
    return spark.createDataFrame(rows, "k int, scenario string, primal double, lp_upper double, lp_lower double, ratio double, iterations int, violated_before_repair int")


def optimality_lattice(spark: SparkSession, sf_dir: str | None = None, ns=(1000,), ks=(1, 5, 10, 15, 20), scenarios=("C1", "C2", "hier"), runs: int = 3) -> DataFrame:
    """The same on synthetic groups of ten items, the mean over offsets of the lattice, as solved and with polished
    prices. (The published grid also has ns=(10_000,), which takes too long for a registered query.)"""

    def point(n: int, k: int, scenario: str, run: int) -> tuple[float, float]:
        p = lattice_problem(spark, n, 10, k, False, scenario, offset=run * 1_000_003)
        s = solvers.solve(p, max_iter=20)
        upper, _ = lp_bound(p, 2e-3, 20, [s.prices], s.history)
        better = s.metrics
        if better["n_violated_before_repair"]:
            better = solvers.finish(p, solvers.Solution(solvers.polished(p, s.prices), True, 0)).metrics
        discard(p.packed)
        return s.metrics["primal"] / upper, better["primal"] / upper

    places = [(n, k, c) for n in ns for k in ks for c in scenarios]
    ratios = _grid(spark, [lambda n=n, k=k, c=c, r=r: point(n, k, c, r) for n, k, c in places for r in range(runs)])
    rows = []
    for i, place in enumerate(places):
        plain, better = zip(*ratios[i * runs : (i + 1) * runs], strict=True)
        rows.append((*place, sum(plain) / runs, min(plain), sum(better) / runs, min(better)))
    return spark.createDataFrame(rows, "n int, k int, scenario string, mean_ratio double, least_ratio double, mean_polished double, least_polished double")


def gap_sparse(spark: SparkSession, sf_dir: str | None = None, n: int = 10_000, ms=(1, 5, 10, 20, 100)) -> DataFrame:
    """Iterations, primal value, duality gap and violated budgets of sparse instances (one knapsack per item, cap
    1) by items per group."""

    def point(m: int) -> tuple:
        p = lattice_problem(spark, n, m, m, True, "C1", uniform=True, share=0.5)
        s = solvers.solve(p, reduce="exact", max_iter=30, tol=1e-4, trace=False)
        discard(p.packed)
        return m, s.iterations, s.converged, s.metrics["primal"], s.metrics["gap"], s.metrics["relative_gap"], s.metrics["n_violated_before_repair"], s.metrics["dropped"]

    rows = _grid(spark, [lambda m=m: point(m) for m in ms])
    return spark.createDataFrame(rows, "m int, iterations int, converged boolean, primal double, gap double, relative_gap double, violated_before_repair int, dropped int")


def presolve_effect(spark: SparkSession, sf_dir: str | None = None, ns=(20_000, 60_000, 200_000), m: int = 10, sample_share: int = 20) -> DataFrame:
    """Iterations with and without warm start, and what the sample's prices alone do on all groups."""
    rows = []
    for n in ns:
        p = lattice_problem(spark, n, m, m, True, "C1", uniform=True, share=0.5)
        options = {"max_iter": 50, "tol": 1e-4}
        plain = solvers.scd(p, 1.0, **options)
        start = solvers.presolve_prices(p, n // sample_share)
        warm = solvers.scd(p, start, **options)
        e, full = measures.evaluate_many(p, [start, warm.prices])
        discard(p.packed)
        rows.append((n, plain.iterations, warm.iterations, measures.iteration_saving(plain.iterations, warm.iterations), e.n_violated, e.max_violation, e.primal, full.primal))
    return spark.createDataFrame(rows, "n int, iterations_without int, iterations_with int, saving double, presolve_violated int, presolve_max_violation double, presolve_primal double, solved_primal double")


def presolve_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Warm start on customers by order priority, and the sample's prices alone."""
    p = KnapsackProblem.from_long(instances.customer_priority(spark, sf_dir), [1.0] * 5, Hierarchy.root(1)).pack()
    p = p.with_budgets(measures.scaled_budgets(p))
    options = {"reduce": "exact", "tol": 1e-4, "trace": False}
    plain = solvers.scd(p, 1.0, **options)
    start = solvers.presolve_prices(p, 500)
    warm = solvers.scd(p, start, **options)
    e = measures.evaluate(p, start)
    return spark.createDataFrame([(plain.iterations, warm.iterations, e.n_violated, e.max_violation)], "iterations_without int, iterations_with int, presolve_violated int, presolve_max_violation double")


def descent_traces(spark: SparkSession, sf_dir: str | None = None, n: int = 10_000, m: int = 10, alphas=(1e-3, 2e-3), iterations: int = 30) -> DataFrame:
    """Duality gap and largest violation by iteration: dual descent at several step sizes, and synchronous
    coordinate descent, on the same sparse instance of uniform draws."""
    p = lattice_problem(spark, n, m, m, True, "C1", uniform=True, share=0.5)
    rows = [(f"dd {a:g}", h["iter"], h["dual"] - h["primal"], h["max_violation"]) for a, s in solvers.dd_sweep(p, list(alphas), max_iter=iterations).items() for h in s.history]
    s = solvers.scd(p, 1.0, max_iter=iterations, tol=1e-4)
    rows += [("scd", h["iter"], h["dual"] - h["primal"], h["max_violation"]) for h in s.history]
    return spark.createDataFrame(rows, "method string, iter int, gap double, max_violation double")


def modes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Synchronous, cyclic and block updates, and plain coordinate descent by line search, on user offers."""
    p = instances.offers_problem(spark, sf_dir, 2)
    rows = []
    for mode, blocks in (("sync", None), ("cyclic", None), ("block", [[1, 2], [3, 4, 5]])):
        s = solvers.scd(p, 1.0, mode=mode, blocks=blocks, reduce="exact", max_iter=12, trace=False)
        e = measures.evaluate(p, s.prices, tolerant=True)
        rows.append((mode, s.iterations, s.converged, e.primal, e.dual, e.max_violation))
    s = solvers.coordinate_descent(p, 1000.0, cycles=1, rounds=4)
    e = measures.evaluate(p, s.prices, tolerant=True)
    rows.append(("line search", s.iterations, s.converged, e.primal, e.dual, e.max_violation))
    return spark.createDataFrame(rows, "mode string, iterations int, converged boolean, primal double, dual double, max_violation double")


def bucket_error(spark: SparkSession, sf_dir: str, deltas=(0.01, 1.0, 100.0)) -> DataFrame:
    """Largest price error of bucketed thresholds against exact ones by bucket size and interpolation, uneven
    buckets and even ones of the same smallest size."""
    p = instances.offers_problem(spark, sf_dir)
    old = [5800.0] * 5
    out = candidates.sparse_emissions(candidates.sparse_packed(p), old, 1).persist()
    budgets = {k + 1: b for k, b in enumerate(p.budgets)}
    prices = {k: old[k - 1] for k in budgets}
    exact = thresholds.threshold_ranged(out, budgets, 8)
    rows = []
    for delta in deltas:
        for kind in ("linear", "upper", "exact"):
            got = thresholds.threshold_bucketed(out, prices, budgets, delta, interpolate=kind)
            rows.append((delta, kind, "uneven", max(abs(got[k] - exact[k]) for k in budgets)))
        got = thresholds.threshold_bucketed(out, prices, budgets, delta, interpolate="linear", even_width=max(delta, 1.0))
        rows.append((delta, "linear", "even", max(abs(got[k] - exact[k]) for k in budgets)))
    out.unpersist()
    return spark.createDataFrame(rows, "delta double, interpolate string, buckets string, largest_error double")


def repair_effect(spark: SparkSession, sf_dir: str, iterations: int = 3) -> DataFrame:
    """What repair costs after a few iterations only: profit lost, violations removed; also with the option that
    passes over groups which use no violated knapsack."""
    rows = []
    for name, p in (("offers", instances.offers_problem(spark, sf_dir)), ("orders", instances.orders_problem(spark, sf_dir, 2, "hier"))):
        s = solvers.scd(p, 1.0, max_iter=iterations, reduce="exact", trace=False, tol=-1.0)
        prices = [0.97 * x for x in s.prices]  # a little too cheap, so that budgets are violated
        e = measures.evaluate(p, prices)
        groups = subproblem.group_results(p, prices)
        for only in (False, True):
            fixed = repair(groups, e.used, p.budgets, only)
            after = fixed.keep.agg(F.sum("profit").alias("p"), *[F.sum(F.element_at("used", k + 1)).alias(f"u{k}") for k in range(p.k)]).first()
            violated = sum((after[f"u{k}"] or 0) > b for k, b in enumerate(p.budgets))
            rows.append((name, only, e.n_violated, e.max_violation, fixed.dropped, e.primal, float(after["p"] or 0), violated))
    return spark.createDataFrame(rows, "instance string, only_violating boolean, violated_before int, max_violation_before double, dropped int, primal_before double, primal_after double, violated_after int")


def daily_solve(spark: SparkSession, sf_dir: str, days=None) -> DataFrame:
    """One solve per day of events (all days of the table unless given), each started from the day before's prices."""
    if days is None:
        day = F.date_format("ts", "yyyy-MM-dd").alias("day")
        days = [r["day"] for r in instances.table(spark, sf_dir, "events").where("ts is not null").select(day).distinct().orderBy("day").collect()]
    prices, rows = 1.0, []
    for day in days:
        p = instances.offers_problem(spark, sf_dir, 2, day=day)
        s = solvers.solve(p, prices0=prices, reduce="exact", trace=False)
        prices = s.prices
        rows.append((day, s.iterations, s.metrics["primal"], s.metrics["relative_gap"], s.metrics["dropped"]))
    return spark.createDataFrame(rows, "day string, iterations int, primal double, relative_gap double, dropped int")


def linear_speedup(spark: SparkSession, sf_dir: str | None = None, ns=(5000, 20_000, 80_000), m: int = 10, iterations: int = 3) -> DataFrame:
    """Seconds of a solve's iterations on sparse instances: the linear-time map against the general one, with their
    largest price difference, which must be nothing."""
    rows = []
    for n in ns:
        p = lattice_problem(spark, n, m, m, True, "C1", uniform=True)
        solvers.scd(p, 1.0, solver="linear", max_iter=1, tol=-1.0)
        found = {}
        for solver in ("linear", "general"):
            began = time.time()
            prices = solvers.scd(p, 1.0, solver=solver, reduce="exact", max_iter=iterations, tol=-1.0).prices
            found[solver] = (time.time() - began, prices)
        discard(p.packed)
        (fast, a), (slow, b) = found["linear"], found["general"]
        rows.append((n, fast, slow, slow / fast, max(abs(x - y) for x, y in zip(a, b, strict=True))))
    return spark.createDataFrame(rows, "n int, linear_seconds double, general_seconds double, speedup double, largest_difference double")


def greedy_against_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The per-group greedy against the generic exact solver: seconds and value, on nested caps."""
    p = instances.orders_problem(spark, sf_dir, 2, "hier")
    prices, rows = [120000.0, 350000.0], []
    for name, f in (("greedy", subproblem.greedy_take), ("exact", subproblem.exact_take)):
        began = time.time()
        d = f(p, prices)
        net = d.join(subproblem.with_net(p.items, prices), ["group_id", "item_id"]).agg(F.sum(F.col("net") * F.col("units"))).first()[0]
        rows.append((name, time.time() - began, net))
    return spark.createDataFrame(rows, "method string, seconds double, net double")


def single_knapsack(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One knapsack over benchmark items: exact table, fractional bound, price-free greedy, priced solve."""
    from .plans.facades import kp01

    items = instances.benchmark_pick(spark, sf_dir)
    budget = float(items.agg(F.sum("need")).first()[0] // 3)
    p = kp01(items, budget)
    s = solvers.solve(p.pack(), solver="general", reduce="exact")
    fractional = groundtruth.fractional_knapsack(items, budget).agg(F.sum(F.col("profit") * F.col("part"))).first()[0]
    density = groundtruth.density_greedy(items, budget).agg(F.sum("profit")).first()[0]
    rows = [("dynamic programming", groundtruth.dp_exact(p)), ("fractional bound", float(fractional)), ("density greedy", float(density)), ("priced", s.metrics["primal"])]
    return spark.createDataFrame(rows, "method string, value double")


def scale_solve(spark: SparkSession, n: int, m: int, k: int, scenario: str = "hier", iterations: int = 3) -> tuple[float, int]:
    """Seconds per iteration of the general solver on a dense nested instance, measures included, and its variables."""
    p = KnapsackProblem.from_long(uniform_items(spark, n, m, k, False), [1.0] * k, standard_hierarchy(m, scenario)).pack()
    p = p.with_budgets([0.5 * u for u in measures.evaluate(p, [0.0] * k).used])
    began = time.time()
    solvers.scd(p, 1.0, solver="general", max_iter=iterations, tol=-1.0)
    seconds = time.time() - began
    discard(p.packed)
    return seconds / iterations, n * m
