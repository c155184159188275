"""Upper bound by the linear relaxation: column generation over full solutions.

A column is what the groups earn and use at some prices. The master problem mixes columns within the
budgets; its prices are evaluated on the groups, which gives a new column and, by weak duality, an upper
bound. For nested or disjoint caps the two meet at the relaxation's optimum."""

from __future__ import annotations

import numpy as np

from ..plans.problem import KnapsackProblem
from .measures import evaluate_many

#: Shares of the way from the best prices to the master's that one pass evaluates.
STEPS = (0.25, 0.5, 1.0)


def simplex(c: np.ndarray, a: np.ndarray, b: np.ndarray, basis: list[int], most: int = 5000) -> tuple[np.ndarray, np.ndarray, float]:
    """max c x, a x = b, x >= 0 from a feasible basis (Bland's rule). Returns x, row prices, value."""
    m, n = a.shape
    basis = list(basis)
    for _ in range(most):
        mat = a[:, basis]
        y = np.linalg.solve(mat.T, c[basis])
        reduced = c - y @ a
        reduced[basis] = 0
        enter = np.flatnonzero(reduced > 1e-9 * max(1.0, np.abs(c).max()))
        x_b = np.linalg.solve(mat, b)
        if not enter.size:
            x = np.zeros(n)
            x[basis] = x_b
            return x, y, float(c @ x)
        j = int(enter[0])
        way = np.linalg.solve(mat, a[:, j])
        up = np.flatnonzero(way > 1e-12)
        if not up.size:
            raise ValueError("unbounded")
        ratio = np.maximum(x_b[up], 0) / way[up]
        tied = up[ratio <= ratio.min() + 1e-12]
        leave = int(min(tied, key=lambda i: basis[i]))
        basis[leave] = j
    raise RuntimeError("simplex did not end")


def master(columns: list[tuple[float, list[float]]], budgets: list[float]) -> tuple[list[float], float]:
    """Prices and value of the best mix of columns (primal, used) within the budgets; weights sum to 1 with
    the all-zero column. Values are scaled to keep the system well conditioned."""
    k = len(budgets)
    scale = max((abs(p) for p, _ in columns), default=1.0) or 1.0
    cols = [(0.0, [0.0] * k), *columns]
    n = len(cols)
    a = np.zeros((k + 1, n + k))
    a[:k, :n] = np.array([[u[i] / budgets[i] for _, u in cols] for i in range(k)])
    a[k, :n] = 1
    a[:k, n:] = np.eye(k)
    c = np.concatenate([[p / scale for p, _ in cols], np.zeros(k)])
    _, y, value = simplex(c, a, np.ones(k + 1), [*range(n, n + k), 0])
    return [max(0.0, y[i] * scale / budgets[i]) for i in range(k)], value * scale


def lp_bound(problem: KnapsackProblem, tol: float = 1e-4, most_rounds: int = 120, start: list[list[float]] | None = None, history: list[dict] | None = None) -> tuple[float, float]:
    """(upper, lower) bounds of the relaxation's value, within tol. history: records of a solver whose
    iterations are columns already."""
    columns: list[tuple[float, list[float]]] = [(h["primal"], h["used"]) for h in history or []]
    upper = min((h["dual"] for h in history or []), default=float("inf"))
    lower = 0.0
    for e in evaluate_many(problem, [[0.0] * problem.k, *(start or [])]):
        columns.append((e.primal, e.used))
        upper = min(upper, e.dual)
    centre = None
    for _ in range(most_rounds):
        prices, lower = master(columns, problem.budgets)
        if upper - lower <= tol * max(upper, 1e-12):
            break
        # steps from the best prices so far towards the master's, all in one pass: fewer rounds than jumping there
        tried = [prices] if centre is None else [[c + x * (p - c) for c, p in zip(centre, prices, strict=True)] for x in STEPS]
        for e in evaluate_many(problem, tried):
            columns.append((e.primal, e.used))
            if e.dual < upper:
                upper, centre = e.dual, e.prices
    return upper, lower
