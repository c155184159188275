"""Table and aggregate functions for the SQL surface."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


@udtf(returnType="group_id bigint, item_id int")
class BestItems:
    """best_items(TABLE(group_id, item_id, net, cap) PARTITION BY group_id): the `cap` best positive nets."""

    def __init__(self):
        self.rows, self.cap = [], 0

    def eval(self, row):
        self.cap = row["cap"]
        if row["net"] > 0:
            self.rows.append((-row["net"], row["item_id"], row["group_id"]))

    def terminate(self):
        for _, item, group in sorted(self.rows)[: self.cap]:
            yield group, item


@pandas_udf("double")
def threshold_udaf(v1: pd.Series, v2: pd.Series, budget: pd.Series) -> float:
    """Crossing threshold of one knapsack's emissions."""
    mass = v2.groupby(v1).sum().sort_index(ascending=False).cumsum()
    over = mass[mass > budget.iloc[0]]
    return float(over.index.max()) if len(over) else 0.0


def register(spark: SparkSession) -> None:
    spark.udtf.register("best_items", BestItems)
    spark.udf.register("threshold_udaf", threshold_udaf)
