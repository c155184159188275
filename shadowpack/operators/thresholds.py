"""The reduce step: from emissions (knapsack, v1, v2) to each knapsack's next price.

An emission says that the use of the knapsack grows by v2 once its price falls below v1. The price that just
fits is 0 if everything fits, else a critical value: 'crossing' is the largest v1 at which the mass of
all emissions at or above it exceeds the budget (at that very price the crossing item is not taken,
as nets must be positive), 'last_fit' the smallest v1 at which the mass still fits."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import bucket_id, even_bucket_id
from ..plans.problem import discard, written


def running_mass(emissions: DataFrame) -> DataFrame:
    """emissions with `mass`: the sum of v2 at or above v1, equal values together."""
    by_value = emissions.groupBy("knapsack", "v1").agg(F.sum("v2").alias("v2"))
    return by_value.withColumn("mass", F.sum("v2").over(Window.partitionBy("knapsack").orderBy(F.desc("v1")).rangeBetween(Window.unboundedPreceding, Window.currentRow)))


def threshold_exact(emissions: DataFrame, budgets: DataFrame, threshold: str = "crossing") -> DataFrame:
    """(knapsack, price) for every knapsack of budgets (knapsack, budget). One window per knapsack: fit for
    emissions of moderate number; threshold_ranged and threshold_bucketed scale further."""
    table = running_mass(emissions).join(F.broadcast(budgets), "knapsack")
    over, fits = F.col("mass") > F.col("budget"), F.col("mass") <= F.col("budget")
    per = table.groupBy("knapsack").agg(F.max(F.when(over, F.col("v1"))).alias("crossing"), F.min(F.when(fits, F.col("v1"))).alias("last_fit"))
    price = F.col("crossing") if threshold == "crossing" else F.coalesce("last_fit", "crossing")
    return budgets.join(per, "knapsack", "left").select("knapsack", F.when(F.col("crossing").isNull(), F.lit(0.0)).otherwise(price).alias("price"))


def threshold_ranged(emissions: DataFrame, budgets: dict[int, float], partitions: int = 64, threshold: str = "crossing") -> dict[int, float]:
    """Exact thresholds without a window over a whole knapsack: emissions are dealt out by ranges of (knapsack, v1
    descending), summed per range, prefixed on the driver (a row per range and knapsack), and only the ranges
    that cross, or that last fit, are scanned."""
    dealt = written(emissions.groupBy("knapsack", "v1").agg(F.sum("v2").alias("v2")).repartitionByRange(partitions, "knapsack", F.desc("v1")).withColumn("part", F.spark_partition_id()))
    sums = dealt.groupBy("knapsack", "part").agg(F.sum("v2").alias("mass"), F.min("v1").alias("lo")).orderBy("knapsack", "part").collect()
    out = {k: 0.0 for k in budgets}
    above: dict[int, float] = {}
    fit: dict[int, float] = {}
    target: dict[int, tuple[int, float]] = {}
    for r in sums:
        k = r["knapsack"]
        if k in budgets and k not in target:
            if above.get(k, 0.0) + r["mass"] > budgets[k]:
                target[k] = (r["part"], budgets[k] - above.get(k, 0.0))
            else:
                above[k], fit[k] = above.get(k, 0.0) + r["mass"], r["lo"]
    for k, (part, left) in target.items():
        one = running_mass(dealt.where((F.col("knapsack") == k) & (F.col("part") == part)))
        r = one.agg(F.max(F.when(F.col("mass") > left, F.col("v1"))).alias("crossing"), F.min(F.when(F.col("mass") <= left, F.col("v1"))).alias("fit")).first()
        last = fit.get(k) if r["fit"] is None else r["fit"]
        out[k] = float(r["crossing"] if threshold == "crossing" or last is None else last)
    discard(dealt)
    return out


def _bucket(delta: float | None, base: float | None, shifted: bool, even_width: float | None) -> Column:
    """Bucket of v1 around `price`; without a delta, a hundred-thousandth of the price (at least of 1)."""
    if even_width:
        return even_bucket_id(F.col("v1"), even_width)
    return bucket_id(F.col("v1"), F.col("price"), F.greatest(F.lit(1.0), F.col("price")) * 1e-5 if delta is None else F.lit(float(delta)), base, shifted)


def bucket_histogram(emissions: DataFrame, prices: DataFrame, delta: float | None, base: float | None = None, shifted: bool = False, even_width: float | None = None) -> DataFrame:
    """(knapsack, bucket, mass, lo, hi, n). Buckets are uneven around the previous price of `prices`
    (knapsack, price): smallest next to it and growing exponentially; or even, of a given width.
    Partial aggregation bounds what is shuffled to partitions x knapsacks x buckets."""
    joined = emissions.join(F.broadcast(prices), "knapsack")
    return joined.groupBy("knapsack", _bucket(delta, base, shifted, even_width).alias("bucket")).agg(F.sum("v2").alias("mass"), F.min("v1").alias("lo"), F.max("v1").alias("hi"), F.count(F.lit(1)).alias("n"))


def locate(rows: list, budgets: dict[int, float], interpolate: str = "linear") -> dict[int, tuple[float, int | None, float]]:
    """From histogram rows to (price, crossing bucket or None, mass left for it) per knapsack."""
    out: dict[int, tuple[float, int | None, float]] = {k: (0.0, None, 0.0) for k in budgets}
    by: dict[int, list] = {}
    for r in rows:
        by.setdefault(r["knapsack"], []).append(r)
    for k, buckets in by.items():
        if k not in budgets:
            continue
        above = 0.0
        for r in sorted(buckets, key=lambda r: -r["hi"]):
            if above + r["mass"] > budgets[k]:
                share = (budgets[k] - above) / r["mass"]
                price = r["hi"] if interpolate == "upper" else r["hi"] - share * (r["hi"] - r["lo"])
                out[k] = (float(price), r["bucket"], budgets[k] - above)
                break
            above += r["mass"]
    return out


def threshold_bucketed(emissions: DataFrame, prices: dict[int, float], budgets: dict[int, float], delta: float | None = None, base: float | None = None, interpolate: str = "linear", shifted: bool = False, even_width: float | None = None) -> dict[int, float]:
    """Thresholds from a histogram; interpolate: 'linear' on mass within the crossing bucket, 'upper' (its
    highest value: never over budget), 'exact' (that bucket alone is read again)."""
    spark = emissions.sparkSession
    table = spark.createDataFrame([(k, float(p)) for k, p in prices.items()], "knapsack int, price double")
    found = locate(bucket_histogram(emissions, table, delta, base, shifted, even_width).collect(), budgets, interpolate)
    out = {k: p for k, (p, _, _) in found.items()}
    if interpolate == "exact":
        targets = [(k, b, left) for k, (_, b, left) in found.items() if b is not None]
        if targets:
            wanted = spark.createDataFrame(targets, "knapsack int, target long, left double")
            rows = emissions.join(F.broadcast(table), "knapsack").withColumn("bucket", _bucket(delta, base, shifted, even_width)).join(F.broadcast(wanted), "knapsack").where("bucket = target")
            left = wanted.select("knapsack", F.col("left").alias("budget"))
            for r in threshold_exact(rows.select("knapsack", "v1", "v2"), left).collect():
                out[r["knapsack"]] = r["price"]
    return out


def crossing(values: list[tuple[float, float]], budget: float, threshold: str = "crossing") -> float:
    """The same on a driver-side list of (v1, v2): for samples and tests."""
    mass, fit, by = 0.0, None, {}
    for v1, v2 in values:
        by[v1] = by.get(v1, 0.0) + v2
    if math.fsum(by.values()) <= budget:
        return 0.0
    for v1 in sorted(by, reverse=True):
        mass += by[v1]
        if mass > budget:
            return fit if threshold == "last_fit" and fit is not None else v1
        fit = v1
    return 0.0
