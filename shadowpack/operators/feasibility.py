"""Repair: drops the least valuable groups until every budget holds."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Quantile classes of one pass over the groups; groups that one task may order by itself.
VALUE_BUCKETS, FEW_GROUPS = 256, 20_000


@dataclass(frozen=True)
class Rule:
    """Groups up to (value, group_id) go; if `touching` is not None, of these only groups that use any of its
    knapsacks (from 0)."""

    value: float
    group: int
    touching: tuple[int, ...] | None = None

    def gone(self) -> Column:
        """Whether a group (group_id, value, used) goes."""
        gone = (F.col("value") < self.value) | ((F.col("value") == self.value) & (F.col("group_id") <= self.group))
        return gone if self.touching is None else gone & touches(self.touching)


@dataclass
class Repair:
    """keep: groups that stay; boundary: (value, group_id) of the last dropped group, None if none is."""

    keep: DataFrame
    boundary: tuple[float, int] | None
    dropped: int
    rule: Rule | None = None


def touches(knapsacks) -> Column:
    out = F.lit(False)
    for i in knapsacks:
        out = out | (F.element_at("used", i + 1) > 0)
    return out


def removal_sums(groups: DataFrame, k: int) -> DataFrame:
    """groups (group_id, value, used) with removed_1..k: the use of all groups up to this one, in order of
    (value, group_id). One task: for few groups."""
    w = Window.orderBy("value", "group_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return groups.select("*", *[F.sum(F.element_at("used", i + 1)).over(w).alias(f"removed_{i + 1}") for i in range(k)])


def repair(groups: DataFrame, used: list[float], budgets: list[float], only_violating: bool = False) -> Repair:
    """groups: group_id, value, used (array), those with a non-empty take. Finds the shortest prefix in order
    of (value, group_id) whose removal brings every use within its budget. only_violating: groups that use
    no violated knapsack are passed over.

    Use per quantile class (a bounded table, prefixed on the driver) tells in which class the last excess
    goes; that class is cut again, by value and among equal values by group_id, until few groups are left,
    and these are summed one by one."""
    k = len(budgets)
    excess = [u - b for u, b in zip(used, budgets, strict=True)]
    over = [i for i in range(k) if excess[i] > 0]
    if not over:
        return Repair(groups, None, 0)
    droppable = groups.where(touches(over)) if only_violating else groups
    inside, before, boundary = droppable, [0.0] * k, None
    while boundary is None:
        column, edges, n = _edges(inside)
        if n <= FEW_GROUPS:
            enough = F.lit(True)
            for i in over:
                enough = enough & (F.col(f"removed_{i + 1}") + F.lit(before[i]) >= F.lit(excess[i]))
            first, last = F.min(F.when(enough, F.struct("value", "group_id"))), F.max(F.struct("value", "group_id"))
            r = removal_sums(inside, k).agg(first.alias("first"), last.alias("last")).first()
            # if even all of them don't suffice, everything droppable goes
            boundary = r["first"] or r["last"]
            break
        rows = _class_sums(inside, column, edges, k)
        target = rows[-1]["class"]
        for r in rows:
            after = [before[i] + r[f"u{i}"] for i in range(k)]
            if all(after[i] >= excess[i] for i in over):
                target = r["class"]
                break
            if r is not rows[-1]:
                before = after
        inside = inside.where(_in_class(column, edges, target))
    if boundary is None:
        return Repair(groups, None, 0)
    rule = Rule(float(boundary["value"]), int(boundary["group_id"]), tuple(over) if only_violating else None)
    return Repair(groups.where(~rule.gone()), (rule.value, rule.group), groups.where(rule.gone()).count(), rule)


def _edges(groups: DataFrame) -> tuple[str, list, int]:
    """(column to cut by, edges, number of groups): quantiles of the value, or of group_id where all values are
    equal. Each edge is followed by the next number, so that a value that many groups have is a class of its own."""
    quantiles = [i / VALUE_BUCKETS for i in range(1, VALUE_BUCKETS)]

    def near(column: str):
        return F.percentile_approx(column, quantiles, 10_000).alias("edges")

    r = groups.agg(F.count(F.lit(1)).alias("n"), F.min("value").alias("lo"), F.max("value").alias("hi")).first()
    if r["n"] <= FEW_GROUPS:
        return "value", [], r["n"]
    column = "group_id" if r["lo"] == r["hi"] else "value"
    edges = groups.agg(near(column)).first()["edges"]
    return column, sorted({x for e in edges for x in ((e, e + 1) if column == "group_id" else (e, math.nextafter(e, math.inf)))}), r["n"]


def _class_sums(groups: DataFrame, column: str, edges: list, k: int) -> list:
    """Use of each class with groups in it (class, u0..), in order; a class is how many edges are at or below the
    value. Summed in a kernel: one binary search a group."""
    points = np.array(edges)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros((k, points.size + 1)), np.zeros(points.size + 1, dtype=np.int64)
        for batch in batches:
            at = np.searchsorted(points, batch.column(0).to_numpy(), side="right")
            used = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, k)
            n += np.bincount(at, minlength=n.size)
            for i in range(k):
                total[i] += np.bincount(at, used[:, i], n.size)
        some = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(some), *(pa.array(t[some]) for t in total)], ["class", *(f"u{i}" for i in range(k))])

    schema = ", ".join(["class long", *(f"u{i} double" for i in range(k))])
    rows = groups.select(column, F.col("used").cast("array<double>")).mapInArrow(kernel, schema)
    return rows.groupBy("class").agg(*[F.sum(f"u{i}").alias(f"u{i}") for i in range(k)]).orderBy("class").collect()


def _in_class(column: str, edges: list, which: int) -> Column:
    out = F.lit(True)
    if which > 0:
        out = out & (F.col(column) >= F.lit(edges[which - 1]))
    return out & (F.col(column) < F.lit(edges[which])) if which < len(edges) else out


def drop_groups(decisions: DataFrame, kept: DataFrame) -> DataFrame:
    """Decisions of the groups that stay."""
    return decisions.join(kept.select("group_id"), "group_id", "left_semi")
