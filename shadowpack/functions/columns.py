"""Column expressions for priced items: net profit, bucket numbers, printable prices."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def net_profit(profit: Column, needs: list[Column], prices: list[float | Column]) -> Column:
    """profit - price_1*need_1 - price_2*need_2 ..., strictly left to right, so that every engine with
    IEEE doubles gives the same bits."""
    return reduce(lambda acc, pair: acc - pair[0] * pair[1], zip([p if isinstance(p, Column) else F.lit(float(p)) for p in prices], needs, strict=True), profit)


def net_profit_arrays(profit: Column, needs: Column, prices: Column) -> Column:
    """The same over two arrays of equal length (first price first)."""
    return F.aggregate(F.zip_with(prices, needs, lambda p, b: p * b), profit, lambda acc, x: acc - x)


def bucket_id(v: Column, price: Column, delta: Column, base: float | None = None, shifted: bool = False) -> Column:
    """Uneven bucket around the previous price: sign(d) * floor(log(max(|d|/delta, 1))), which is bucket 0
    within base*delta of the price and monotone in v. shifted: buckets outside delta move one away from
    0, so that bucket 0 is exactly |d| < delta. base None is e."""
    d = v - price
    ratio = F.abs(d) / delta
    logarithm = F.log(F.greatest(ratio, F.lit(1.0)))
    if base is not None:
        logarithm = logarithm / F.log(F.lit(float(base)))
    steps = F.floor(logarithm)
    if shifted:
        steps = F.when(ratio < 1.0, F.lit(0)).otherwise(steps + 1)
    return (F.signum(d).cast("int") * steps).cast("long")


def even_bucket_id(v: Column, width: float) -> Column:
    return F.floor(v / F.lit(float(width))).cast("long")


def price_micros(price: Column) -> Column:
    """A price as whole millionths, by floor(x*1e6+0.5), which all engines compute alike."""
    return F.floor(price * 1e6 + 0.5).cast("bigint")


def row_hash(column: Column, seed: int = 0) -> Column:
    """A uniform number in [0, 1) from the column's value alone, independent of partitions."""
    return F.shiftrightunsigned(F.xxhash64(column, F.lit(seed)), 11) / F.lit(float(1 << 53))


def register_sql_functions(spark: SparkSession) -> None:
    """net_profit(profit, needs, prices) and bucket_number(v, price, delta) as session SQL functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION net_profit(profit DOUBLE, needs ARRAY<DOUBLE>, prices ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(prices, needs, (p, b) -> p * b), profit, (acc, x) -> acc - x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bucket_number(v DOUBLE, price DOUBLE, delta DOUBLE) RETURNS BIGINT RETURN CAST(signum(v - price) AS INT) * floor(ln(greatest(abs(v - price) / delta, 1.0D)))")


def price_row(spark: SparkSession, prices: list[float]) -> DataFrame:
    """Prices as one broadcast row: plans keep their shape from one iteration to the next."""
    return F.broadcast(spark.createDataFrame([([float(p) for p in prices],)], "prices array<double>"))
