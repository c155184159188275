"""Warm starts: prices solved on a sample of groups with budgets scaled to it."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import row_hash
from ..plans.problem import KnapsackProblem, written


def hash_sample(df: DataFrame, share: float, seed: int = 0, column: str = "group_id") -> DataFrame:
    """The rows whose id hashes below `share`: the same groups on any partitioning, and whole groups."""
    return df.where(row_hash(F.col(column), seed) < share)


def sample_problem(problem: KnapsackProblem, n: int, seed: int = 0) -> tuple[KnapsackProblem, int, int]:
    """About n groups and budgets times n'/N, with the sampled and total numbers of groups."""
    total = problem.packed.count()
    part = hash_sample(problem.packed, min(1.0, n / max(total, 1)), seed).coalesce(8)
    part = written(part)
    got = part.count()
    scale = got / max(total, 1)
    items = hash_sample(problem.items, min(1.0, n / max(total, 1)), seed)
    return replace(problem, items=items, packed=part, budgets=[b * scale for b in problem.budgets]), got, total
