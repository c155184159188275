"""The selection problem: items of groups, budgets shared by all groups, caps within each group."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .hierarchy import Hierarchy
from .kernels import STORED_GROUPS, blocks, stored, stored_columns
from .session import ship_package

#: Items that a task packs into blocks at a time, and bytes of a row group of stored blocks, which one task reads.
PACKED_ITEMS, ROW_GROUP = 400_000, 16 << 20

ITEM_SCHEMA = "group_id long, item_id int, profit double, max_units int, needs array<double>"


@dataclass
class KnapsackProblem:
    """items: group_id, item_id, profit, max_units, needs (array of K doubles, dense form).

    Sparse instances, one knapsack per item, also carry `knapsack` and `need`; `sparse` says so and the
    linear-time map then applies. budgets: K positive numbers, on the driver."""

    items: DataFrame
    budgets: list[float]
    hierarchy: Hierarchy = field(default_factory=Hierarchy.none)
    sparse: bool = False
    packed: DataFrame | None = None
    #: Caps by item attributes, bottom-up and nested: (column of items, cap); column None is the whole group.
    levels: list[tuple[str | None, int]] = field(default_factory=list)
    #: Whether the linear-time map applies, once found out.
    linear: bool | None = None

    @property
    def k(self) -> int:
        return len(self.budgets)

    @classmethod
    def from_long(cls, items: DataFrame, budgets: list[float], hierarchy: Hierarchy | None = None, levels: list[tuple[str | None, int]] | None = None) -> KnapsackProblem:
        """items with needs ARRAY (dense), need_map MAP (general sparse) or knapsack_id and need (one knapsack
        per item, numbered from 1); profits and needs may be of any numeric type."""
        k = len(budgets)
        cols = set(items.columns)
        if "needs" in cols:
            needs, sparse = F.transform("needs", lambda x: x.cast("double")), False
        elif "need_map" in cols:
            needs, sparse = F.transform(F.sequence(F.lit(1), F.lit(k)), lambda j: F.coalesce(F.try_element_at("need_map", j).cast("double"), F.lit(0.0))), False
        else:
            needs, sparse = F.transform(F.sequence(F.lit(1), F.lit(k)), lambda j: F.when(j == F.col("knapsack_id"), F.col("need").cast("double")).otherwise(F.lit(0.0))), True
        units = F.col("max_units").cast("int") if "max_units" in cols else F.lit(1)
        base = [F.col("group_id").cast("long").alias("group_id"), F.col("item_id").cast("int").alias("item_id"), F.col("profit").cast("double").alias("profit"), units.alias("max_units"), needs.alias("needs")]
        if sparse:
            base += [F.col("knapsack_id").cast("int").alias("knapsack"), F.col("need").cast("double").alias("need")]
        base += [c for c, _ in levels or [] if c is not None]
        return cls(items.select(*base), [float(b) for b in budgets], hierarchy or Hierarchy.none(), sparse, None, list(levels or []))

    def validate(self) -> KnapsackProblem:
        """Raises ValueError on negative, null or NaN profits and needs, needs of a wrong length, repeated
        (group, item) pairs, budgets that aren't positive, or unbounded units that no cap covers."""
        if not self.budgets or any(not b > 0 for b in self.budgets):
            raise ValueError("budgets must be positive")

        def bad(x):
            return x.isNull() | F.isnan(x) | (x < 0)

        row = self.items.agg(
            F.count_if(F.col("group_id").isNull() | F.col("item_id").isNull()).alias("no id"),
            F.count_if(bad(F.col("profit"))).alias("bad profit"),
            F.count_if(F.col("needs").isNull() | (F.size("needs") != self.k) | F.exists("needs", bad)).alias("bad need"),
            F.count_if(F.col("max_units") <= 0).alias("units not positive"),
            F.count_if(F.col("max_units").isNull()).alias("unbounded units"),
        ).first()
        wrong = [name for name in ("no id", "bad profit", "bad need", "units not positive") if row[name]]
        if row["unbounded units"] and not (self.hierarchy.covers_all() or any(c is None for c, _ in self.levels)):
            wrong.append("unbounded units under no cap")
        if self.items.groupBy("group_id", "item_id").count().where("count > 1").limit(1).count():
            wrong.append("repeated (group, item)")
        if wrong:
            raise ValueError("; ".join(wrong))
        return self

    def pack(self, partitions: int | None = None, path: str | None = None, as_blocks: bool = False) -> KnapsackProblem:
        """One row per group: item_ids, profits, needs (item-major, flattened; if sparse, one_knapsack and one_need in
        their place), units; one shuffle by group.

        Written as Parquet to `path`, or to the shared checkpoint folder, and read back: each iteration is
        then a narrow scan, and lost executors lose nothing. as_blocks: one row per block of groups of like size, whose
        arrays are bytes in narrow types, for dense problems that are read many times."""
        if as_blocks:
            return replace(self, packed=written(self._blocks(partitions), path, ROW_GROUP))
        named = [c for c, _ in self.levels if c is not None]
        needs = [F.col("e.knapsack").alias("one_knapsack"), F.col("e.need").alias("one_need")] if self.sparse else [F.flatten("e.needs").alias("needs")]
        entry = F.struct("item_id", "profit", *(["knapsack", "need"] if self.sparse else ["needs"]), F.coalesce("max_units", F.lit(2**31 - 1)).alias("units"), *(F.col(c).cast("string").alias(f"node{i}") for i, c in enumerate(named)))
        rows = self.items.groupBy("group_id").agg(F.sort_array(F.collect_list(entry)).alias("e"))
        nodes = [_codes(F.col(f"e.node{i}")).alias(f"node{i}") for i in range(len(named))]
        rows = rows.select("group_id", F.col("e.item_id").alias("item_ids"), F.col("e.profit").alias("profits"), *needs, F.col("e.units").alias("units"), *nodes)
        if partitions:
            rows = rows.repartition(partitions, "group_id")
        return replace(self, packed=written(rows, path))

    def _blocks(self, partitions: int | None) -> DataFrame:
        """Rows of groups, width and stored_columns: items lie in tasks group by group, and are cut into blocks there."""
        if self.sparse:
            raise ValueError("blocks are stored of dense problems only")
        ship_package(self.items.sparkSession)
        k, named = self.k, [c for c, _ in self.levels if c is not None]
        columns = stored_columns(k, len(named))
        nodes = [F.col(c).cast("string").alias(f"node{i}") for i, c in enumerate(named)]
        rows = self.items.select("group_id", "item_id", "profit", "needs", F.coalesce("max_units", F.lit(2**31 - 1)).alias("units"), *nodes)
        if partitions:
            rows = rows.repartition(partitions, "group_id")
        w = Window.partitionBy("group_id").orderBy("item_id", "profit", "needs", "units", *(f"node{i}" for i in range(len(named))))
        rows = rows.withColumn("place", F.row_number().over(w))

        def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for table in _whole_groups(batches):
                out: list[list] = []
                for block in blocks(_by_group(table, k), k, most=STORED_GROUPS):
                    out.append([block.group.size, block.ids.shape[1], *stored(block, k)])
                for row in out:
                    yield pa.RecordBatch.from_arrays([pa.array([row[0]], pa.int32()), pa.array([row[1]], pa.int32()), *(pa.array([x], pa.binary()) for x in row[2:])], ["groups", "width", *columns])

        return rows.mapInArrow(kernel, "groups int, width int, " + ", ".join(f"{c} binary" for c in columns))

    def with_budgets(self, budgets: list[float]) -> KnapsackProblem:
        return replace(self, budgets=[float(b) for b in budgets])


def _whole_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Rows that lie group by group (place 1 begins one), in tables that no group reaches beyond."""
    part: list[pa.RecordBatch] = []
    for batch in batches:
        if sum(b.num_rows for b in part) >= PACKED_ITEMS:
            begins = np.flatnonzero(batch.column("place").to_numpy() == 1)
            if begins.size:
                yield pa.Table.from_batches([*part, batch.slice(0, int(begins[0]))])
                part, batch = [], batch.slice(int(begins[0]))
        part.append(batch)
    if part:
        yield pa.Table.from_batches(part)


def _by_group(table: pa.Table, k: int) -> pa.RecordBatch:
    """One row per group, with arrays, from rows that lie group by group."""
    table = table.combine_chunks()
    begins = np.flatnonzero(table.column("place").to_numpy() == 1)
    ends = pa.array(np.append(begins, table.num_rows).astype(np.int32))
    group = np.repeat(np.arange(begins.size), np.diff(np.append(begins, table.num_rows)))

    def lists(values) -> pa.ListArray:
        return pa.ListArray.from_arrays(ends, values)

    out = {"group_id": pa.array(table.column("group_id").to_numpy()[begins])}
    out |= {name: lists(pa.array(table.column(c).to_numpy())) for name, c in (("item_ids", "item_id"), ("profits", "profit"), ("units", "units"))}
    needs = pa.array(table.column("needs").combine_chunks().flatten().to_numpy(zero_copy_only=False)) if table.num_rows else pa.array([], pa.float64())
    out["needs"] = pa.ListArray.from_arrays(pa.array((np.append(begins, table.num_rows) * k).astype(np.int32)), needs)
    for name in (c for c in table.column_names if c.startswith("node")):
        # an item's code is the place of the first one of its group with the same value
        values = table.column(name).combine_chunks().dictionary_encode()
        values = values.combine_chunks() if isinstance(values, pa.ChunkedArray) else values
        codes = values.indices.fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)
        _, first, of = np.unique(group * (len(values.dictionary) + 1) + codes + 1, return_index=True, return_inverse=True)
        out[name] = lists(pa.array(np.where(codes < 0, -1, first[of] - begins[group]).astype(np.int32)))
    return pa.RecordBatch.from_arrays(list(out.values()), list(out))


def _codes(values: Column) -> Column:
    """Small numbers for the distinct values of an array, in order of appearance."""
    return F.transform(values, lambda x: (F.array_position(F.array_distinct(values), x) - 1).cast("int"))


_WRITTEN: list[tuple[SparkSession, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or a folder of our own where it is unset (a single machine)."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        folder = known.get() if known.isDefined() else None
    if not folder:
        folder = "file://" + tempfile.mkdtemp(prefix="shadowpack_")
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def written(df: DataFrame, path: str | None = None, row_group: int | None = None) -> DataFrame:
    """df, written once as Parquet (in row groups of about so many bytes) and read back."""
    spark = df.sparkSession
    own = path is None
    path = path or f"{shared_folder(spark)}/packed-{uuid.uuid4().hex}"
    writer = df.write.mode("overwrite")
    (writer.option("parquet.block.size", row_group).option("parquet.block.size.row.check.min", 8).option("parquet.page.size.row.check.min", 8) if row_group else writer).parquet(path)
    if own:
        _WRITTEN.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._written_path = path
    return out


def discard(df: DataFrame) -> None:
    """Deletes a table of written() that nothing reads any more."""
    _remove([x for x in _WRITTEN if x[1] == getattr(df, "_written_path", None)])


@atexit.register
def _remove_written() -> None:
    _remove(list(_WRITTEN))


def _remove(tables: list[tuple[SparkSession, str]]) -> None:
    for spark, path in tables:
        _WRITTEN.remove((spark, path))
        try:
            target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
        except Exception:  # the session may be gone  # noqa: BLE001
            continue
