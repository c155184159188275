"""Reproducible synthetic instances of any size."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.columns import row_hash
from ..plans.hierarchy import Hierarchy
from ..plans.problem import KnapsackProblem

# Multipliers and modulus of the lattice, the same in every engine.
PROFIT_STEPS, NEED_STEPS, MODULUS = (7919, 104729, 31), (6101, 15485863, 17), 10007
# End of fixed values.

#: Groups x items x knapsacks worth a task: below that, starting tasks takes longer than the groups in them.
CELLS = 250_000


def lattice_items(spark: SparkSession, n: int | DataFrame, m: int, k: int, sparse: bool, offset: int = 0) -> DataFrame:
    """n groups, or those of a table (group_id, and its place on the lattice), x m items by modular arithmetic. Profits 1..MODULUS; dense needs: k per item, from one of two
    ranges by parity; sparse: item j uses knapsack j % k only."""
    a, b, c = PROFIT_STEPS
    u, v, w = NEED_STEPS
    g, j = F.col("place") + offset, F.col("item_id")
    groups = n if isinstance(n, DataFrame) else spark.range(n).select(F.col("id").alias("group_id"), F.col("id").alias("place"))
    base = groups.select("group_id", "place", F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("item_id"))
    profit = ((g * a + j * b + g * j * c) % MODULUS + 1).cast("double")

    def need(x):
        raw = (g * u + j * v + g * j * w + x * 7907) % 1009
        return F.when((g + j + x) % 2 == 0, raw % 100 + 1).otherwise(raw + 1).cast("double")

    if sparse:
        return base.select("group_id", "item_id", profit.alias("profit"), (j % k + 1).cast("int").alias("knapsack_id"), need(F.lit(0)).alias("need"))
    return base.select("group_id", "item_id", profit.alias("profit"), F.transform(F.sequence(F.lit(1), F.lit(k)), need).alias("needs"))


def uniform_items(spark: SparkSession, n: int, m: int, k: int, sparse: bool, seed: int = 0) -> DataFrame:
    """The same shape with uniform draws in [0, 1) hashed from the place, whatever the partitioning."""
    base = spark.range(n).select(F.col("id").alias("group_id"), F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("item_id"))

    def draw(x):
        return row_hash(F.struct("group_id", "item_id", F.lit(x).alias("x") if isinstance(x, int) else x.alias("x")), seed)

    if sparse:
        return base.select("group_id", "item_id", draw(0).alias("profit"), (F.col("item_id") % k + 1).cast("int").alias("knapsack_id"), draw(1).alias("need"))
    return base.select("group_id", "item_id", draw(0).alias("profit"), F.array(*[draw(x + 1) for x in range(k)]).alias("needs"))


def standard_hierarchy(m: int, scenario: str) -> Hierarchy:
    """The three local scenarios: at most 1, at most 2, or nested halves (1 each, 2 together)."""
    if scenario == "C1":
        return Hierarchy.root(1)
    if scenario == "C2":
        return Hierarchy.root(2)
    half = max(1, m // 2)
    quarters = [(1, list(range(half // 2 or 1)))] if half > 1 else []
    return Hierarchy.build([*quarters, (1, list(range(half))), (2, None)])


def lattice_problem(spark: SparkSession, n: int, m: int, k: int, sparse: bool, scenario: str = "C1", offset: int = 0, uniform: bool = False, share: float = 0.5) -> KnapsackProblem:
    """Packed instance whose budgets are `share` of what is used when nothing has a price."""
    from ..operators.measures import evaluate

    items = uniform_items(spark, n, m, k, sparse, offset) if uniform else lattice_items(spark, n, m, k, sparse, offset)
    parts = -(-n * m * k // CELLS)
    problem = KnapsackProblem.from_long(items, [1.0] * k, standard_hierarchy(m, scenario))
    problem = problem.pack(partitions=parts if parts < spark.sparkContext.defaultParallelism else None)
    free = evaluate(problem, [0.0] * k)
    return problem.with_budgets([max(share * u, 1e-9) for u in free.used])


class LatticeDataSource(DataSource):
    """spark.read.format('lattice').option('groups', n).option('items', m).option('knapsacks', k): the sparse
    lattice as a data source, split by ranges of groups."""

    @classmethod
    def name(cls) -> str:
        return "lattice"

    def schema(self) -> str:
        return "group_id long, item_id int, profit double, knapsack_id int, need double"

    def reader(self, schema) -> DataSourceReader:
        return LatticeReader(dict(self.options))


class LatticeReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.m, self.k, self.parts = (int(options.get(x, d)) for x, d in (("groups", 1000), ("items", 5), ("knapsacks", 5), ("partitions", 8)))

    def partitions(self):
        step = max(1, -(-self.n // self.parts))
        return [InputPartition((a, min(a + step, self.n))) for a in range(0, self.n, step)]

    def read(self, partition):
        first, last = partition.value
        (a, b, c), (u, v, w) = PROFIT_STEPS, NEED_STEPS
        for g in range(first, last):
            for j in range(self.m):
                raw = (g * u + j * v + g * j * w) % 1009
                yield g, j, float((g * a + j * b + g * j * c) % MODULUS + 1), j % self.k + 1, float(raw % 100 + 1 if (g + j) % 2 == 0 else raw + 1)
