"""The repair's search on packed groups: which boundary (value, group_id) drops the least valuable groups until every
budget holds. Groups are never written: each pass solves them again and sums them by classes of their value's bits (then of
their id's), which order as the numbers do."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from ..plans.kernels import Caps, blocks, gathered
from ..plans.problem import KnapsackProblem
from ..plans.session import ship_package
from .feasibility import FEW_GROUPS, Rule
from .subproblem import packed_of, solve_block

#: Bits of the value, then of the group's id, that a class leaves out, pass by pass.
SHIFTS = (42, 21, 0)


@dataclass
class Cut:
    """rule: which groups go, None if none does; dropped: how many; kept: the profit of those that stay."""

    rule: Rule | None
    dropped: int
    kept: float


def find_cut(problem: KnapsackProblem, prices: list[float], used: list[float], only_violating: bool = False) -> Cut:
    """The shortest prefix of the groups in order of (value, group_id) whose removal brings every use within its budget, at
    the tolerant take of the prices. only_violating: groups that use no violated knapsack are passed over."""
    k = problem.k
    excess = [u - b for u, b in zip(used, problem.budgets, strict=True)]
    over = [i for i in range(k) if excess[i] > 0]
    touching = tuple(over) if only_violating else None
    removed, dropped, kept = np.zeros(k), 0, 0.0
    inside: list[tuple[int, int, int]] = []
    for column, shift in [(c, s) for c in (0, 1) for s in SHIFTS]:
        rows = _classes(problem, prices, touching, inside, (column, shift))
        if not inside:
            kept += sum(r["profit"] for r in rows if r["class"] is None)
        rows = sorted((r for r in rows if r["class"] is not None), key=lambda r: r["class"])
        if not rows:
            return Cut(None, 0, kept)
        target = len(rows) - 1
        for at, r in enumerate(rows):
            after = removed + np.array(r["used"])
            if at == target or all(after[i] >= excess[i] for i in over):
                target = at
                break
            removed, dropped = after, dropped + r["n"]
        kept += sum(r["profit"] for r in rows[target + 1 :])
        inside.append((column, shift, rows[target]["class"]))
        if rows[target]["n"] <= FEW_GROUPS:
            break
    last = sorted(_members(problem, prices, touching, inside), key=lambda r: (r["value"], r["group_id"]))
    for at, r in enumerate(last):
        removed, dropped = removed + np.array(r["used"]), dropped + 1
        if all(removed[i] >= excess[i] for i in over):
            break
    # if even all of them don't suffice, everything droppable goes
    return Cut(Rule(float(r["value"]), int(r["group_id"]), touching), dropped, kept + sum(x["profit"] for x in last[at + 1 :]))


def _solved(problem: KnapsackProblem, prices: list[float], touching: tuple[int, ...] | None, inside: list[tuple[int, int, int]]):
    """A map from batches to (group_id, value, profit, used, whether it may go) of groups that take something and lie in
    the classes."""
    ship_package(problem.items.sparkSession)
    k, price, caps = problem.k, np.array(prices, dtype=float), Caps(problem.hierarchy, problem.levels)

    def solved(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        for batch in gathered(batches):
            for block in blocks(batch, k):
                net, take = solve_block(block, price, caps, True)
                some = take.any(axis=1)
                value = (net * take).sum(axis=1)
                for at in inside:
                    some &= _class_of(value, block.group, *at[:2]) == at[2]
                used = block.used(take, k)
                goes = np.ones(some.size, dtype=bool) if touching is None else (used[:, list(touching)] > 0).any(axis=1)
                if inside:
                    some &= goes
                yield block.group[some], value[some], (block.profit * take).sum(axis=1)[some], used[some], goes[some]

    return solved


def _class_of(value: np.ndarray, group: np.ndarray, column: int, shift: int) -> np.ndarray:
    """Positive doubles order as their bits do."""
    return (group if column else np.ascontiguousarray(value).view(np.int64)) >> shift


def _classes(problem: KnapsackProblem, prices: list[float], touching: tuple[int, ...] | None, inside: list[tuple[int, int, int]], by: tuple[int, int]) -> list[dict]:
    """n, profit and use of each class; those that may not go are class None."""
    k, solved = problem.k, _solved(problem, prices, touching, inside)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, sums = np.zeros(0, dtype=np.int64), np.zeros((0, k + 2))
        stays = 0.0
        for group, value, profit, used, goes in solved(batches):
            stays += float(profit[~goes].sum())
            own = np.concatenate([np.ones((group.size, 1)), profit[:, None], used], axis=1)[goes]
            keys, sums = _added(np.concatenate([keys, _class_of(value, group, *by)[goes]]), np.concatenate([sums, own]))
        key = pa.array([*keys.tolist(), None], pa.int64())
        sums = np.concatenate([sums, [[0.0, stays, *[0.0] * k]]])
        yield pa.RecordBatch.from_arrays([key, *(pa.array(np.ascontiguousarray(sums[:, x])) for x in range(k + 2))], names)

    names = ["class", "n", "profit", *(f"u{i}" for i in range(k))]
    rows = packed_of(problem).mapInArrow(kernel, "class long, " + ", ".join(f"{c} double" for c in names[1:]))
    found = rows.groupBy("class").agg(*[F.sum(c).alias(c) for c in names[1:]]).collect()
    return [{"class": r["class"], "n": int(r["n"]), "profit": r["profit"], "used": [r[f"u{i}"] for i in range(k)]} for r in found]


def _added(keys: np.ndarray, sums: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows of equal keys as one."""
    if not keys.size:
        return keys, sums
    order = np.argsort(keys, kind="stable")
    keys, head = np.unique(keys[order], return_index=True)
    return keys, np.add.reduceat(sums[order], head, axis=0)


def _members(problem: KnapsackProblem, prices: list[float], touching: tuple[int, ...] | None, inside: list[tuple[int, int, int]]) -> list:
    """The groups of the last class, few by then."""
    k, solved = problem.k, _solved(problem, prices, touching, inside)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group, value, profit, used, _ in solved(batches):
            rows = pa.ListArray.from_arrays(pa.array(np.arange(group.size + 1, dtype=np.int32) * k), pa.array(np.ascontiguousarray(used).ravel()))
            yield pa.RecordBatch.from_arrays([pa.array(group), pa.array(value), pa.array(profit), rows], ["group_id", "value", "profit", "used"])

    return packed_of(problem).mapInArrow(kernel, "group_id long, value double, profit double, used array<double>").collect()
