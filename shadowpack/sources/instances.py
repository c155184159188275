"""Selection instances on the given tables. Profits and needs are whole numbers, so sums are exact."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.hierarchy import Hierarchy
from ..plans.problem import KnapsackProblem

# Event types, order priorities and languages, in order of their knapsack numbers.
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
LANGUAGES = ("de", "en", "es", "fr")
ROLES = ("assistant", "system", "user")
# End of fixed values.


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(column: Column) -> Column:
    return F.floor(column * 100 + 0.5).cast("bigint")


def number_in(column: str, values: tuple[str, ...]):
    return F.array_position(F.array(*[F.lit(v) for v in values]), F.col(column)).cast("int")


def user_offers(spark: SparkSession, sf_dir: str, day: str | None = None) -> DataFrame:
    """Per user and event type: profit (summed cents, at least 0), need (events), one knapsack per type."""
    e = table(spark, sf_dir, "events").select("user_id", "event_type", "value", "ts")
    if day:
        e = e.where((F.col("ts") >= F.lit(day).cast("timestamp")) & (F.col("ts") < F.lit(day).cast("timestamp") + F.expr("INTERVAL 1 DAY")))
    per = e.groupBy("user_id", "event_type").agg(F.sum(F.greatest(cents(F.col("value")), F.lit(0))).alias("profit"), F.count(F.lit(1)).alias("need"))
    k = number_in("event_type", EVENT_TYPES)
    return per.where(k > 0).select(F.col("user_id").alias("group_id"), k.alias("item_id"), F.col("profit").cast("double"), k.alias("knapsack_id"), F.col("need").cast("double"))


def order_lines(spark: SparkSession, sf_dir: str, k: int = 5) -> DataFrame:
    """Per order and line: profit (net cents), k dense needs of quantity, tax points, discount points, part size
    and days between order and shipment. Lines are numbered by all their columns (no key is unique)."""
    l = table(spark, sf_dir, "lineitem")
    p = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_size")
    o = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_orderdate")
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity", "l_discount", "l_tax", "l_shipdate")
    rows = l.withColumn("item_id", F.row_number().over(w)).join(p, "l_partkey").join(o, "l_orderkey")
    needs = [F.col("l_quantity"), cents(F.col("l_tax")), cents(F.col("l_discount")), F.col("p_size"), F.abs(F.datediff("l_shipdate", "o_orderdate"))]
    return rows.select(
        F.col("l_orderkey").alias("group_id"), "item_id", cents(F.col("l_extendedprice") * (1 - F.col("l_discount"))).cast("double").alias("profit"),
        F.array(*[n.cast("double") for n in needs[:k]]).alias("needs"), "l_linestatus", F.concat_ws("|", "l_linestatus", "l_returnflag").alias("status_flag"), "l_suppkey",
    )


def customer_priority(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").groupBy("o_custkey", "o_orderpriority").agg(F.sum(cents(F.col("o_totalprice"))).alias("profit"), F.count(F.lit(1)).alias("need"))
    k = number_in("o_orderpriority", PRIORITIES)
    return o.where(k > 0).select(F.col("o_custkey").alias("group_id"), k.alias("item_id"), F.col("profit").cast("double"), k.alias("knapsack_id"), F.col("need").cast("double"))


def part_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per part and supplier: revenue cents and quantity; one item per part may be chosen."""
    l = table(spark, sf_dir, "lineitem").groupBy("l_partkey", "l_suppkey").agg(F.sum(cents(F.col("l_extendedprice") * (1 - F.col("l_discount")))).alias("profit"), F.sum(F.col("l_quantity").cast("bigint")).alias("need"))
    return l.select(F.col("l_partkey").alias("group_id"), F.col("l_suppkey").cast("int").alias("item_id"), F.col("profit").cast("double"), F.col("need").cast("double"))


def doc_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: profit (distinct words, doubled for quality 1), needs by map: characters of its language
    (1-4), all characters (5), toxic documents (6)."""
    labels = table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.max("quality").alias("quality"), F.max("toxic").alias("toxic"))
    d = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "n_chars").join(labels, "doc_id", "left")
    words = F.size(F.array_distinct(F.split("text", " ")))
    lang = number_in("lang", LANGUAGES)
    need = F.map_concat(F.create_map(lang, F.col("n_chars").cast("double")), F.create_map(F.lit(5), F.col("n_chars").cast("double")), F.create_map(F.lit(6), F.coalesce("toxic", F.lit(0)).cast("double")))
    return d.where(lang > 0).select(F.col("doc_id").alias("group_id"), F.lit(0).alias("item_id"), (words * (1 + F.coalesce("quality", F.lit(0)))).cast("double").alias("profit"), need.alias("need_map"))


def turn_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per conversation turn: profit (characters), need (words) in the knapsack of its role."""
    c = table(spark, sf_dir, "conversations")
    k = number_in("role", ROLES)
    return c.where(k > 0).select(F.col("conv_id").cast("long").alias("group_id"), F.col("turn").cast("int").alias("item_id"), F.char_length("text").cast("double").alias("profit"), k.alias("knapsack_id"), F.size(F.split("text", " ")).cast("double").alias("need"), "role")


def crawl_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per host and page: profit (characters outside tags), needs (html bytes, 1 page)."""
    p = table(spark, sf_dir, "pages")
    host = F.regexp_extract("url", "^https?://([^/]+)", 1)
    text = F.char_length(F.regexp_replace("html", "<[^>]*>", ""))
    ids = F.conv(F.substring(F.md5("host"), 1, 15), 16, 10).cast("bigint")
    return p.select(host.alias("host"), F.col("page_id").cast("int").alias("item_id"), text.cast("double").alias("profit"), F.array(F.octet_length("html").cast("double"), F.lit(1.0)).alias("needs")).withColumn("group_id", ids)


def class_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per vector and class 0-9: profit (whole-number similarity to the class sum, shifted to at least 0), need
    1 in the class's knapsack. Components are floored thousandths, so sums are exact."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.transform("embedding", lambda x: F.floor(x.cast("double") * 1000).cast("bigint")).alias("q"))
    parts = e.select("label", F.posexplode("q").alias("i", "x")).groupBy("label", "i").agg(F.sum("x").alias("s"), F.count(F.lit(1)).alias("n"))
    means = parts.groupBy("label").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", F.floor(F.col("s") / F.col("n")).cast("bigint").alias("m")))), lambda s: s["m"]).alias("mean"))
    sim = F.aggregate(F.zip_with("q", "mean", lambda a, b: a * b), F.lit(0).cast("bigint"), lambda s, x: s + x)
    pairs = e.select("vec_id", "q").join(F.broadcast(means), how="cross").select("vec_id", "label", sim.alias("sim"))
    least = pairs.agg(F.min("sim").alias("least"))
    return pairs.crossJoin(F.broadcast(least)).select(F.col("vec_id").alias("group_id"), F.col("label").cast("int").alias("item_id"), (F.col("sim") - F.col("least")).cast("double").alias("profit"), (F.col("label") + 1).cast("int").alias("knapsack_id"), F.lit(1.0).alias("need"))


def order_nations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """order_lines with the supplier's nation and region, two needs."""
    s = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("n_nationkey"))
    n = table(spark, sf_dir, "nation").select("n_nationkey", F.col("n_regionkey").alias("region"))
    return order_lines(spark, sf_dir, 2).join(F.broadcast(s), "l_suppkey").join(F.broadcast(n), "n_nationkey").withColumnRenamed("n_nationkey", "nation")


def benchmark_pick(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = table(spark, sf_dir, "benchmark")
    return b.select(F.col("item_id").cast("int").alias("item_id"), F.size(F.split("text", " ")).cast("double").alias("profit"), F.char_length("text").cast("double").alias("need"))


def offers_problem(spark: SparkSession, sf_dir: str, q: int = 1, numerator: int = 1, denominator: int = 2, day: str | None = None) -> KnapsackProblem:
    from ..operators.measures import scaled_budgets

    p = KnapsackProblem.from_long(user_offers(spark, sf_dir, day), [1.0] * 5, Hierarchy.root(q)).pack()
    return p.with_budgets(scaled_budgets(p, numerator, denominator))


ORDER_LEVELS = {"C1": [(None, 1)], "C2": [(None, 2)], "hier": [("status_flag", 1), ("l_linestatus", 2), (None, 3)]}


def orders_problem(spark: SparkSession, sf_dir: str, k: int = 2, scenario: str = "hier") -> KnapsackProblem:
    from ..operators.measures import scaled_budgets

    p = KnapsackProblem.from_long(order_lines(spark, sf_dir, k), [1.0] * k, levels=ORDER_LEVELS[scenario]).pack()
    return p.with_budgets(scaled_budgets(p))


def orders_problems(spark: SparkSession, sf_dir: str, ks: tuple[int, ...], scenarios: tuple[str, ...]) -> dict[tuple[int, str], KnapsackProblem]:
    """orders_problem of every number of knapsacks and scenario, all on one packed table: it holds the needs of the
    largest number and the nodes of all scenarios."""
    from ..operators.measures import scaled_budgets

    most = max(ks)
    named = list(dict.fromkeys(level for c in scenarios for level in ORDER_LEVELS[c] if level[0] is not None))
    packed = KnapsackProblem.from_long(order_lines(spark, sf_dir, most), [1.0] * most, levels=named).pack(as_blocks=True)
    out = {}
    for c in scenarios:
        table = packed.packed
        if all(level is None for level, _ in ORDER_LEVELS[c]):
            table = table.drop(*[x for x in table.columns if x.startswith("node")])
        # knapsacks that have no price yet use the same, however many there are
        budgets = scaled_budgets(replace(packed, levels=ORDER_LEVELS[c], packed=table))
        for k in ks:
            own = table.drop(*(f"need{x}" for x in range(k, most)))
            own._written_path = packed.packed._written_path
            out[k, c] = replace(KnapsackProblem.from_long(order_lines(spark, sf_dir, k), budgets[:k], levels=ORDER_LEVELS[c]), packed=own)
    return out
