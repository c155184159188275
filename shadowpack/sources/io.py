"""Budgets and caps from files; decisions, histories and packed groups to files and tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.hierarchy import Hierarchy
from ..plans.problem import KnapsackProblem

BUDGETS, CAPS = "knapsack_id int, budget double", "set_id int, cap int, item_ids array<int>"


def read_budgets(spark: SparkSession, path: str, form: str = "csv") -> list[float]:
    """knapsack_id, budget (CSV with a header, or JSON lines) -> budgets in order; ids must run from 1."""
    reader = spark.read.schema(BUDGETS)
    rows = (reader.option("header", True).csv(path) if form == "csv" else reader.json(path)).orderBy("knapsack_id").collect()
    if [r["knapsack_id"] for r in rows] != list(range(1, len(rows) + 1)):
        raise ValueError("knapsack ids must run from 1 without gaps")
    return [r["budget"] for r in rows]


def read_caps(spark: SparkSession, path: str) -> Hierarchy:
    """JSON lines of set_id, cap, item_ids (null: every item)."""
    return Hierarchy.build([(r["cap"], r["item_ids"]) for r in spark.read.schema(CAPS).json(path).orderBy("set_id").collect()])


def crossing_sets(spark: SparkSession, caps: DataFrame) -> DataFrame:
    """Pairs of cap sets (set_id, item_ids) that are neither nested nor disjoint: a relational check."""
    a, b = caps.alias("a"), caps.alias("b")
    shared = F.array_intersect(F.col("a.item_ids"), F.col("b.item_ids"))
    only = lambda x, y: F.size(F.array_except(F.col(f"{x}.item_ids"), F.col(f"{y}.item_ids"))) > 0
    return a.join(b, F.col("a.set_id") < F.col("b.set_id")).where((F.size(shared) > 0) & only("a", "b") & only("b", "a")).select(F.col("a.set_id").alias("one"), F.col("b.set_id").alias("other"))


def write_decisions(decisions: DataFrame, path: str, day: str) -> None:
    """One partition per day; a day's rerun replaces that day alone."""
    decisions.withColumn("day", F.lit(day)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("day").parquet(path)


def append_history(history: DataFrame, path: str) -> None:
    history.write.mode("append").parquet(path)


def last_prices(spark: SparkSession, path: str) -> list[float]:
    """Prices of the last iteration in a history: where a broken-off run goes on."""
    h = spark.read.parquet(path)
    last = h.agg(F.max("iter")).first()[0]
    return [r["price"] for r in h.where(F.col("iter") == last).orderBy("knapsack_id").collect()]


def save_packed(problem: KnapsackProblem, table: str, buckets: int) -> None:
    """Packed groups as a bucketed table: joins and repacks by group need no further shuffle."""
    problem.packed.write.mode("overwrite").bucketBy(buckets, "group_id").sortBy("group_id").saveAsTable(table)
