"""Helpers shared by the corpus operators: shared staging folders, unique ids, code shipping."""

from __future__ import annotations

import atexit
import io
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_SHIPPED: set[str] = set()
_STAGED: list[tuple[SparkSession, str]] = []


def ship_package(spark: SparkSession) -> None:
    """Give every executor this package's source, once per application (kernels are imported there)."""
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = Path(__file__).resolve().parent.parent
    buffer = io.BytesIO()
    with zipfile.ZipFile(buffer, "w") as archive:
        for path in sorted(root.rglob("*.py")):
            archive.write(path, f"{root.name}/{path.relative_to(root)}")
    folder = tempfile.mkdtemp(prefix="shadowpack_src_")
    target = os.path.join(os.path.abspath(folder), "shadowpack_src.zip")
    Path(target).write_bytes(buffer.getvalue())
    spark.sparkContext.addPyFile(target)
    _SHIPPED.add(app)


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a folder of our own where it is unset."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        folder = known.get() if known.isDefined() else None
    if not folder:
        folder = "file://" + tempfile.mkdtemp(prefix="shadowpack_stage_")
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: lineage ends there and lost
    executors cost nothing. Folders are deleted by unstage or release once nothing reads them, or else
    when the driver ends."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/stage-{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    _STAGED.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_path = path
    return out


def unstage(*frames: DataFrame) -> None:
    """Delete the folders of staged tables that no result still to be computed reads."""
    paths = {getattr(f, "_staged_path", None) for f in frames}
    _delete([x for x in _STAGED if x[1] in paths])


def stage_mark() -> int:
    return len(_STAGED)


def release(mark: int, *keep: DataFrame) -> None:
    """Delete all folders staged since the mark, but for those of `keep`."""
    paths = {getattr(f, "_staged_path", None) for f in keep}
    _delete([x for x in _STAGED[mark:] if x[1] not in paths])


def clear_stages() -> None:
    """Delete every staged folder (at the end of the driver)."""
    _delete(list(_STAGED))


def _delete(staged: list[tuple[SparkSession, str]]) -> None:
    for spark, path in staged:
        _STAGED.remove((spark, path))
        try:
            if spark.sparkContext._jsc is None:
                continue
            hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)
        except Exception:  # the session may be gone by now  # noqa: BLE001
            continue


atexit.register(clear_stages)


def unique_ids(docs: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """docs with a column `_uid`: equal to the id where all ids are set and unique.

    Otherwise every row is a document of its own: rows with a null or repeated id get negative
    numbers, dealt by a hash of the id and the row's place among those of the same id and text."""
    twice = docs.groupBy(id_col).agg(F.count(F.lit(1)).alias("n")).where(F.col(id_col).isNull() | (F.col("n") > 1))
    if twice.limit(1).count() == 0:
        return docs.withColumn("_uid", F.col(id_col).cast("long"))
    w = Window.partitionBy(id_col, F.xxhash64("text")).orderBy(F.lit(0))
    numbered = docs.withColumn("_nth", F.row_number().over(w))
    n = F.count(F.lit(1)).over(Window.partitionBy(id_col))
    other = -F.abs(F.xxhash64(F.coalesce(F.col(id_col).cast("string"), F.lit("null")), "text", "_nth")) - F.lit(1)
    return stage(numbered.withColumn("_uid", F.when(F.col(id_col).isNull() | (n > 1), other).otherwise(F.col(id_col).cast("long"))).drop("_nth"), "ids")


def is_numbered(ids: DataFrame) -> bool:
    """Whether unique_ids had to number rows (their ids then come from a staged table)."""
    return "stage-ids" in "".join(ids.inputFiles()[:1])


def count_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
