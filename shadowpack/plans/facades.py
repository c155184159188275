"""Classical special cases, stated as problems."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .hierarchy import Hierarchy
from .problem import KnapsackProblem


def mdkp(df: DataFrame, budgets: list[float]) -> KnapsackProblem:
    """Multi-dimensional knapsack: df has group_id, profit and needs (or need_map); one item per group."""
    return KnapsackProblem.from_long(df.withColumn("item_id", F.lit(0)), budgets)


def mckp(df: DataFrame, budget: float, exactly_one: bool = False) -> KnapsackProblem:
    """Multi-choice knapsack: group_id, item_id, profit, need; at most one item per group. exactly_one: each
    group must take one. Its cheapest item is then the fallback: items compete by what they add to it, in
    profit and in need, and the budget is what the fallbacks leave (see exactly_one_offset)."""
    if exactly_one:
        base = df.groupBy("group_id").agg(F.min(F.struct("need", (-F.col("profit")).alias("col2"), "item_id")).alias("m"))
        base = base.select("group_id", F.col("m.need").alias("need0"), (-F.col("m.col2")).alias("profit0"), F.col("m.item_id").alias("item0"))
        df = df.join(base, "group_id").where("item_id <> item0").where("profit > profit0").select("group_id", "item_id", (F.col("profit") - F.col("profit0")).alias("profit"), (F.col("need") - F.col("need0")).alias("need"))
        spent = base.agg(F.sum("need0")).first()[0]
        budget = max(float(budget) - float(spent), 1e-9)
    return KnapsackProblem.from_long(df.withColumn("needs", F.array("need")).drop("need"), [budget], Hierarchy.root(1))


def exactly_one_offset(df: DataFrame) -> DataFrame:
    """The fallback item of each group (smallest need, then largest profit, then smallest id)."""
    m = F.min_by(F.struct("item_id", "profit", "need"), F.struct("need", -F.col("profit"), "item_id"))
    return df.groupBy("group_id").agg(m.alias("m")).select("group_id", "m.*")


def mmkp(df: DataFrame, budgets: list[float]) -> KnapsackProblem:
    """Multi-dimensional multi-choice knapsack: at most one item per group, several budgets."""
    return KnapsackProblem.from_long(df, budgets, Hierarchy.root(1))


def kp01(df: DataFrame, budget: float) -> KnapsackProblem:
    """The classical single knapsack: item_id, profit, need; every item is a group of its own."""
    return KnapsackProblem.from_long(df.select(F.col("item_id").alias("group_id"), F.lit(0).alias("item_id"), "profit", F.array(F.col("need").cast("double")).alias("needs")), [budget])
