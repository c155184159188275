"""Registered queries of the selection engine: name -> (Spark callable, DuckDB text or None)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles as O
from . import workloads
from .functions.columns import bucket_id, even_bucket_id, net_profit, price_micros, register_sql_functions
from .operators import candidates as C
from .operators import feasibility, groundtruth, measures, solvers, subproblem, thresholds
from .plans.facades import mckp, mdkp
from .plans.hierarchy import Hierarchy
from .plans.problem import KnapsackProblem
from .sources import instances as I
from .streaming import pacing

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_QUERIES: dict[str, str] = {}

#: Prices at which fixed-price queries are run.
LINE_PRICES = [120000.0, 350000.0]
OFFER_PRICE, OFFER_START, OFFER_ALPHA = 4000.0, 1000.0, 5.0


def query(oracle: str | None = None):
    def register(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if oracle:
            ORACLE_QUERIES[f.__name__] = oracle
        return f

    return register


def price_table(spark: SparkSession, prices: list[float]) -> DataFrame:
    rows = spark.createDataFrame([(k + 1, float(p)) for k, p in enumerate(prices)], "knapsack_id int, price double")
    return rows.select("knapsack_id", price_micros(F.col("price")).alias("price_micros"))


def budget_table(spark: SparkSession, budgets: list[float]) -> DataFrame:
    return spark.createDataFrame([(k + 1, float(b)) for k, b in enumerate(budgets)], "knapsack int, budget double")


def _offers(spark, sf_dir, q=1):
    return I.offers_problem(spark, sf_dir, q)


def _entries(spark, sf_dir):
    return C.sparse_packed(KnapsackProblem.from_long(I.user_offers(spark, sf_dir), [1.0] * 5, Hierarchy.root(1)))


# ---------------------------------------------------------------- instances and sources


@query(f"WITH {O.OFFERS} SELECT g AS group_id, item AS item_id, profit, k AS knapsack_id, need FROM offers")
def scan_items(spark, sf_dir):
    return I.user_offers(spark, sf_dir)


@query(f"WITH {O.LINES} SELECT g AS group_id, item AS item_id, profit, b1, b2, b3, b4, b5, ls, sf FROM lines")
def order_lines_items(spark, sf_dir):
    df = I.order_lines(spark, sf_dir, 5)
    return df.select("group_id", "item_id", "profit", *[F.element_at("needs", i).alias(f"b{i}") for i in range(1, 6)], F.col("l_linestatus").alias("ls"), F.col("status_flag").alias("sf"))


@query(f"WITH {O.CUSTOMERS} SELECT g AS group_id, item AS item_id, profit, k AS knapsack_id, need FROM offers")
def customer_priority_items(spark, sf_dir):
    return I.customer_priority(spark, sf_dir)


@query("SELECT l_partkey AS group_id, CAST(l_suppkey AS INT) AS item_id, CAST(sum(CAST(floor(l_extendedprice * (1 - l_discount) * 100 + 0.5) AS BIGINT)) AS DOUBLE) AS profit, CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS need FROM lineitem GROUP BY 1, 2")
def part_supplier_items(spark, sf_dir):
    return I.part_supplier(spark, sf_dir)


DOCS = """docs AS (SELECT d.doc_id AS g, CAST(len(list_distinct(string_split(d.text, ' '))) * (1 + coalesce(l.quality, 0)) AS DOUBLE) AS profit, list_position(['de', 'en', 'es', 'fr'], d.lang) AS lang, CAST(n_chars AS DOUBLE) AS chars, CAST(coalesce(l.toxic, 0) AS DOUBLE) AS toxic
  FROM documents d LEFT JOIN (SELECT doc_id, max(quality) AS quality, max(toxic) AS toxic FROM labels GROUP BY 1) l USING (doc_id))"""


@query(f"WITH {DOCS} SELECT g AS group_id, profit, CAST(lang AS INT) AS lang, chars, toxic FROM docs WHERE lang > 0")
def doc_items(spark, sf_dir):
    df = I.doc_budget(spark, sf_dir)
    lang = F.filter(F.map_keys("need_map"), lambda k: k <= 4)
    return df.select("group_id", "profit", F.element_at(lang, 1).cast("int").alias("lang"), F.element_at("need_map", F.lit(5)).alias("chars"), F.element_at("need_map", F.lit(6)).alias("toxic"))


TURNS = "turns AS (SELECT CAST(conv_id AS BIGINT) AS g, CAST(turn AS INT) AS item, CAST(length(text) AS DOUBLE) AS profit, CAST(list_position(['assistant', 'system', 'user'], role) AS INT) AS k, CAST(len(string_split(text, ' ')) AS DOUBLE) AS need, role FROM conversations)"


@query(f"WITH {TURNS} SELECT g AS group_id, item AS item_id, profit, k AS knapsack_id, need, role FROM turns WHERE k > 0")
def turn_items(spark, sf_dir):
    return I.turn_budget(spark, sf_dir)


@query("SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, CAST(page_id AS INT) AS item_id, CAST(length(regexp_replace(html, '<[^>]*>', '', 'g')) AS DOUBLE) AS profit, CAST(strlen(html) AS DOUBLE) AS bytes FROM pages")
def crawl_items(spark, sf_dir):
    return I.crawl_budget(spark, sf_dir).select("host", "item_id", "profit", F.element_at("needs", 1).alias("bytes"))


@query(
    """WITH q AS (SELECT vec_id, label, i, CAST(floor(CAST(embedding[i] AS DOUBLE) * 1000) AS BIGINT) AS x FROM embeddings, range(1, 65) t(i)),
m AS (SELECT label, i, CAST(floor(sum(x) / count(*)) AS BIGINT) AS m FROM q GROUP BY 1, 2),
s AS (SELECT q.vec_id, m.label, sum(q.x * m.m) AS sim FROM q JOIN m USING (i) GROUP BY 1, 2)
SELECT vec_id AS group_id, CAST(label AS INT) AS item_id, CAST(sim - (SELECT min(sim) FROM s) AS DOUBLE) AS profit FROM s"""
)
def class_items(spark, sf_dir):
    return I.class_assign(spark, sf_dir).select("group_id", "item_id", "profit")


@query(f"WITH {O.LINES} SELECT g AS group_id, item AS item_id, profit, s_nationkey AS nation, n_regionkey AS region FROM lines JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey")
def order_nation_items(spark, sf_dir):
    return I.order_nations(spark, sf_dir).select("group_id", "item_id", "profit", "nation", "region")


LATTICE = """lat AS (SELECT o, g, CAST(j AS INT) AS j, CAST((g * 7919 + j * 104729 + g * j * 31) % 10007 + 1 AS DOUBLE) AS profit, CAST(j % 5 + 1 AS INT) AS k, (g * 6101 + j * 15485863 + g * j * 17) % 1009 AS raw FROM (SELECT CAST(o_orderkey AS BIGINT) AS o, CAST(o_orderkey + coalesce(min(o_custkey), 0) AS BIGINT) AS g FROM orders WHERE o_orderkey IS NOT NULL GROUP BY o_orderkey) a, range(5) b(j))"""


@query(f"WITH {LATTICE} SELECT o AS group_id, j AS item_id, profit, k AS knapsack_id, CAST(CASE WHEN (g + j) % 2 = 0 THEN raw % 100 + 1 ELSE raw + 1 END AS DOUBLE) AS need FROM lat")
def lattice_items(spark, sf_dir):
    from .sources.lattice import lattice_items as build

    orders = I.table(spark, sf_dir, "orders").where("o_orderkey IS NOT NULL").groupBy(F.col("o_orderkey").cast("long").alias("group_id"))
    groups = orders.agg(F.min("o_custkey").alias("customer")).select("group_id", (F.col("group_id") + F.coalesce("customer", F.lit(0))).cast("long").alias("place"))
    return build(spark, groups, 5, 5, True)


# ---------------------------------------------------------------- subproblem at fixed prices

NET2 = "profit" + "".join(f" - {O.dbl(p)} * b{i + 1}" for i, p in enumerate(LINE_PRICES))


def _line_net(spark, sf_dir):
    return subproblem.with_net(I.order_lines(spark, sf_dir, 2), LINE_PRICES)


@query(f"WITH {O.LINES} SELECT g AS group_id, item AS item_id, {NET2} AS net FROM lines")
def net_profit_lines(spark, sf_dir):
    return _line_net(spark, sf_dir).select("group_id", "item_id", "net")


@query(f"WITH {O.LINES} SELECT count(*) AS n, CAST(sum(profit) AS DOUBLE) AS profit FROM lines WHERE {NET2} > 0")
def positive_items(spark, sf_dir):
    return _line_net(spark, sf_dir).where("net > 0").agg(F.count(F.lit(1)).alias("n"), F.sum("profit").alias("profit"))


def _greedy_lines(spark, sf_dir, scenario):
    p = KnapsackProblem.from_long(I.order_lines(spark, sf_dir, 2), [1.0, 1.0], levels=I.ORDER_LEVELS[scenario]).pack()
    return subproblem.greedy_take(p, LINE_PRICES)


@query(O.greedy_sql([("", 1)], LINE_PRICES))
def greedy_c1(spark, sf_dir):
    return _greedy_lines(spark, sf_dir, "C1")


@query(O.greedy_sql([("", 2)], LINE_PRICES))
def greedy_c2(spark, sf_dir):
    return _greedy_lines(spark, sf_dir, "C2")


@query(O.greedy_sql([("sf", 1), ("ls", 2), ("", 3)], LINE_PRICES))
def greedy_hier(spark, sf_dir):
    return _greedy_lines(spark, sf_dir, "hier")


@query(O.greedy_sql([("nation", 1), ("region", 2), ("", 3)], LINE_PRICES, O.LINES + ", nl AS (SELECT lines.*, s_nationkey AS nation, n_regionkey AS region FROM lines JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey)", "nl"))
def greedy_nation3(spark, sf_dir):
    items = subproblem.with_net(I.order_nations(spark, sf_dir), LINE_PRICES)
    kept = subproblem.greedy_levels(items, [(["nation"], 1), (["region"], 2), ([], 3)])
    return kept.select("group_id", "item_id", F.lit(1).cast("int").alias("units"))


@query(f"WITH {TURNS}, n AS (SELECT *, profit - 2.0::DOUBLE * need AS net FROM turns WHERE k > 0), a AS (SELECT *, row_number() OVER (PARTITION BY g, role ORDER BY net DESC, item) AS r1 FROM n WHERE net > 0), b AS (SELECT *, row_number() OVER (PARTITION BY g ORDER BY net DESC, item) AS r2 FROM a WHERE r1 <= 2) SELECT g AS group_id, item AS item_id, CAST(1 AS INT) AS units FROM b WHERE r2 <= 3")
def turn_greedy(spark, sf_dir):
    p = KnapsackProblem.from_long(I.turn_budget(spark, sf_dir), [1.0] * 3, levels=[("role", 2), (None, 3)]).pack()
    return subproblem.greedy_take(p, [2.0] * 3)


@query("WITH i AS (SELECT l_partkey AS g, l_suppkey AS item, CAST(sum(CAST(floor(l_extendedprice * (1 - l_discount) * 100 + 0.5) AS BIGINT)) AS DOUBLE) AS profit, CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS need FROM lineitem GROUP BY 1, 2), n AS (SELECT *, profit - 90000.0::DOUBLE * need AS net FROM i) SELECT g AS group_id, CAST(item AS INT) AS item_id, CAST(1 AS INT) AS units FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY net DESC, item) AS r FROM n WHERE net > 0) WHERE r = 1")
def mckp_choice(spark, sf_dir):
    return subproblem.greedy_take(mckp(I.part_supplier(spark, sf_dir), 1.0).pack(), [90000.0])


@query(f"WITH {DOCS} SELECT g AS group_id, CAST(0 AS INT) AS item_id, CAST(1 AS INT) AS units FROM docs WHERE lang > 0 AND profit - 0.05::DOUBLE * chars - 0.02::DOUBLE * chars - 5.0::DOUBLE * toxic > 0")
def mdkp_take(spark, sf_dir):
    return subproblem.greedy_take(mdkp(I.doc_budget(spark, sf_dir), [1.0] * 6).pack(), [0.05] * 4 + [0.02, 5.0])


@query(f"WITH {O.OFFERS}, n AS (SELECT *, profit - {O.dbl(OFFER_PRICE)} * need AS net FROM offers), c AS (SELECT *, coalesce(sum(CAST(need AS BIGINT)) OVER (PARTITION BY g ORDER BY net DESC, item ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM n WHERE net > 0) SELECT g AS group_id, item AS item_id, CAST(greatest(0, least(need, 12 - before)) AS INT) AS units FROM c WHERE before < 12")
def integer_units_greedy(spark, sf_dir):
    items = I.user_offers(spark, sf_dir).withColumn("max_units", F.col("need").cast("int"))
    p = KnapsackProblem.from_long(items, [1.0] * 5, Hierarchy.root(12)).pack()
    return subproblem.greedy_take(p, [OFFER_PRICE] * 5)


@query(f"WITH {O.OFFERS} SELECT g AS group_id, item AS item_id FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY profit - {O.dbl(OFFER_PRICE)} * need DESC, item) AS r FROM offers WHERE profit - {O.dbl(OFFER_PRICE)} * need > 0) WHERE r <= 2")
def topq_take(spark, sf_dir):
    items = I.user_offers(spark, sf_dir).withColumn("net", net_profit(F.col("profit"), [F.col("need")], [OFFER_PRICE]))
    return subproblem.topq_take(items, 2).select("group_id", "item_id")


@query(f"WITH {O.OFFERS}, n AS (SELECT *, profit - {O.dbl(OFFER_PRICE)} * need AS net FROM offers) SELECT g AS group_id, CAST(floor(sum(net) * 100 + 0.5) AS BIGINT) AS value_cents FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY net DESC, item) AS r FROM n WHERE net > 0) WHERE r <= 2 GROUP BY g")
def group_values(spark, sf_dir):
    p = KnapsackProblem.from_long(I.user_offers(spark, sf_dir), [1.0] * 5, Hierarchy.root(2)).pack()
    decisions = subproblem.greedy_take(p, [OFFER_PRICE] * 5)
    return subproblem.group_value(decisions, p.items, [OFFER_PRICE] * 5).select("group_id", F.floor(F.col("group_value") * 100 + 0.5).cast("bigint").alias("value_cents"))


# ---------------------------------------------------------------- candidates and emissions

LINE_INTERCEPT = f"profit - {O.dbl(LINE_PRICES[1])} * b2"


@query(f"WITH {O.LINES}, z AS (SELECT g, {LINE_INTERCEPT} AS i, b1 AS s FROM lines), c AS (SELECT g, i / s AS v FROM z WHERE s > 0 UNION SELECT a.g, (a.i - b.i) / (a.s - b.s) FROM z a JOIN z b ON a.g = b.g AND b.s < a.s) SELECT g AS group_id, {O.MICROS.format(x='v')} AS v_micros FROM c WHERE v > 0")
def candidates_array(spark, sf_dir):
    items = I.order_lines(spark, sf_dir, 2)
    lines = items.select("group_id", (F.col("profit") - LINE_PRICES[1] * F.element_at("needs", 2)).alias("i"), F.element_at("needs", 1).alias("s"))
    packed = lines.groupBy("group_id").agg(F.collect_list(F.struct("i", "s")).alias("l"))
    return packed.select("group_id", F.explode(C.candidate_prices(F.col("l.i"), F.col("l.s"))).alias("v")).select("group_id", price_micros(F.col("v")).alias("v_micros"))


@query(f"WITH {O.LINES}, z AS (SELECT g, item, {LINE_INTERCEPT} AS i, b1 AS s FROM lines) SELECT a.g AS group_id, a.item AS item_a, b.item AS item_b, {O.MICROS.format(x='(a.i - b.i) / (a.s - b.s)')} AS v_micros FROM z a JOIN z b ON a.g = b.g AND a.item < b.item AND a.s <> b.s WHERE (a.i - b.i) / (a.s - b.s) > 0")
def pairwise_intersections(spark, sf_dir):
    z = I.order_lines(spark, sf_dir, 2).select("group_id", "item_id", (F.col("profit") - LINE_PRICES[1] * F.element_at("needs", 2)).alias("i"), F.element_at("needs", 1).alias("s"))
    a, b = z.alias("a"), z.alias("b")
    v = F.try_divide(F.col("a.i") - F.col("b.i"), F.col("a.s") - F.col("b.s"))
    joined = a.join(b, (F.col("a.group_id") == F.col("b.group_id")) & (F.col("a.item_id") < F.col("b.item_id")) & (F.col("a.s") != F.col("b.s")))
    return joined.where(v > 0).select(F.col("a.group_id").alias("group_id"), F.col("a.item_id").alias("item_a"), F.col("b.item_id").alias("item_b"), price_micros(v).alias("v_micros"))


@query(f"WITH {O.LINES}, z AS (SELECT g, {LINE_INTERCEPT} AS i, b1 AS s FROM lines) SELECT g AS group_id, count(*) AS n FROM (SELECT g, i / s AS v FROM z WHERE s > 0 AND i / s > 0 UNION SELECT a.g, (a.i - b.i) / (a.s - b.s) FROM z a JOIN z b ON a.g = b.g AND b.s < a.s WHERE (a.i - b.i) / (a.s - b.s) > 0) GROUP BY g")
def candidates_union(spark, sf_dir):
    z = I.order_lines(spark, sf_dir, 2).select("group_id", (F.col("profit") - LINE_PRICES[1] * F.element_at("needs", 2)).alias("i"), F.element_at("needs", 1).alias("s"))
    a, b = z.alias("a"), z.alias("b")
    cross = a.join(b, (F.col("a.group_id") == F.col("b.group_id")) & (F.col("b.s") < F.col("a.s"))).select(F.col("a.group_id").alias("group_id"), F.try_divide(F.col("a.i") - F.col("b.i"), F.col("a.s") - F.col("b.s")).alias("v"))
    zero = z.where("s > 0").select("group_id", F.try_divide("i", "s").alias("v"))
    return zero.union(cross).where("v > 0").distinct().groupBy("group_id").agg(F.count(F.lit(1)).alias("n"))


SCD_C1 = f"""WITH {O.LINES}, z AS MATERIALIZED (SELECT g, item, profit - {O.dbl(LINE_PRICES[1])} * b2 AS i, b1 AS s FROM lines),
c AS (SELECT g, i / s AS v FROM z WHERE s > 0 UNION SELECT a.g, (a.i - b.i) / (a.s - b.s) FROM z a JOIN z b ON a.g = b.g AND a.s <> b.s),
d AS MATERIALIZED (SELECT g, v, (v + coalesce(lead(v) OVER (PARTITION BY g ORDER BY v DESC), 0.0)) / 2 AS probe FROM c WHERE v > 0),
u AS (SELECT g, v, s AS used FROM (SELECT d.g, d.v, z.s, row_number() OVER (PARTITION BY d.g, d.v ORDER BY z.i - d.probe * z.s DESC, z.item) AS r FROM d JOIN z USING (g) WHERE z.i - d.probe * z.s > 0) WHERE r = 1),
w AS (SELECT d.g, d.v, coalesce(u.used, 0.0) AS used FROM d LEFT JOIN u ON d.g = u.g AND d.v = u.v),
x AS (SELECT v, used - coalesce(max(used) OVER (PARTITION BY g ORDER BY v DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0) AS v2 FROM w)
SELECT CAST(1 AS INT) AS knapsack_id, {O.MICROS.format(x='v')} AS v1_micros, v2 FROM x WHERE v2 > 0"""


@query(SCD_C1)
def scd_emissions_c1(spark, sf_dir):
    p = KnapsackProblem.from_long(I.order_lines(spark, sf_dir, 2), [1.0, 1.0], levels=[(None, 1)]).pack()
    out = C.scd_emissions(p, LINE_PRICES, [1])
    return out.select(F.col("knapsack").alias("knapsack_id"), price_micros(F.col("v1")).alias("v1_micros"), "v2")


def _sparse_sql(q: int) -> str:
    return f"WITH {O.OFFERS}, p0 AS (SELECT DISTINCT k, {O.dbl(OFFER_PRICE)} AS price FROM offers), {O.emissions(0, q)} SELECT k AS knapsack_id, {O.MICROS.format(x='v1')} AS v1_micros, v2 FROM em0"


def _sparse_query(q: int):
    def f(spark, sf_dir):
        out = C.sparse_emissions(_entries(spark, sf_dir), [OFFER_PRICE] * 5, q)
        return out.select(F.col("knapsack").alias("knapsack_id"), price_micros(F.col("v1")).alias("v1_micros"), "v2")

    f.__name__ = f"sparse_emissions_q{q}"
    return f


for _q in (1, 2, 3):
    query(_sparse_sql(_q))(_sparse_query(_q))


@query(f"WITH {O.OFFERS}, a AS (SELECT g, greatest(profit - {O.dbl(OFFER_PRICE)} * need, 0.0::DOUBLE) AS a FROM offers), r AS (SELECT g, a, row_number() OVER (PARTITION BY g ORDER BY a DESC) AS r FROM a) SELECT g AS group_id, CAST(floor(coalesce(max(a) FILTER (WHERE r = 1), 0) * 100 + 0.5) AS BIGINT) AS first_cents, CAST(floor(coalesce(max(a) FILTER (WHERE r = 2), 0) * 100 + 0.5) AS BIGINT) AS second_cents FROM r GROUP BY g")
def qth_values(spark, sf_dir):
    adj = I.user_offers(spark, sf_dir).select("group_id", F.greatest(F.col("profit") - OFFER_PRICE * F.col("need"), F.lit(0.0)).alias("a"))
    top = adj.groupBy("group_id").agg(F.sort_array(F.collect_list("a"), asc=False).alias("s"))
    cents = lambda i: F.floor(F.coalesce(F.get("s", F.lit(i)), F.lit(0.0)) * 100 + 0.5).cast("bigint")
    return top.select("group_id", cents(0).alias("first_cents"), cents(1).alias("second_cents"))


# ---------------------------------------------------------------- thresholds and buckets


def _threshold_sql(last_fit: bool) -> str:
    parts = [O.OFFERS, O.budgets(1), O.start_prices(OFFER_PRICE), O.emissions(0, 1), O.masses(0), O.next_prices(0, None, last_fit)]
    return f"WITH {', '.join(parts)} SELECT k AS knapsack_id, {O.MICROS.format(x='price')} AS price_micros FROM p1"


def _thresholds(spark, sf_dir, kind):
    p = _offers(spark, sf_dir)
    out = C.sparse_emissions(C.sparse_packed(p), [OFFER_PRICE] * 5, 1)
    found = thresholds.threshold_exact(out, budget_table(spark, p.budgets), kind)
    return found.select(F.col("knapsack").alias("knapsack_id"), price_micros(F.col("price")).alias("price_micros"))


@query(_threshold_sql(False))
def threshold_exact(spark, sf_dir):
    return _thresholds(spark, sf_dir, "crossing")


@query(_threshold_sql(True))
def threshold_last_fit(spark, sf_dir):
    return _thresholds(spark, sf_dir, "last_fit")


@query(_threshold_sql(False))
def threshold_ranged(spark, sf_dir):
    p = _offers(spark, sf_dir)
    out = C.sparse_emissions(C.sparse_packed(p), [OFFER_PRICE] * 5, 1)
    found = thresholds.threshold_ranged(out, {k + 1: b for k, b in enumerate(p.budgets)}, 8)
    return price_table(spark, [found[k] for k in range(1, 6)])


@query(_threshold_sql(False))
def threshold_bucketed_exact(spark, sf_dir):
    p = _offers(spark, sf_dir)
    out = C.sparse_emissions(C.sparse_packed(p), [OFFER_PRICE] * 5, 1)
    found = thresholds.threshold_bucketed(out, {k: OFFER_PRICE for k in range(1, 6)}, {k + 1: b for k, b in enumerate(p.budgets)}, 1.0, interpolate="exact")
    return price_table(spark, [found[k] for k in range(1, 6)])


@query(f"WITH {O.OFFERS}, p0 AS (SELECT DISTINCT k, {O.dbl(OFFER_PRICE)} AS price FROM offers), {O.emissions(0, 1)}, {O.masses(0)} SELECT k AS knapsack_id, {O.MICROS.format(x='v1')} AS v1_micros, CAST(mass AS DOUBLE) AS mass FROM ms0")
def running_mass(spark, sf_dir):
    out = thresholds.running_mass(C.sparse_emissions(_entries(spark, sf_dir), [OFFER_PRICE] * 5, 1))
    return out.select(F.col("knapsack").alias("knapsack_id"), price_micros(F.col("v1")).alias("v1_micros"), "mass")


BUCKET = f"CAST(sign(v1 - {O.dbl(OFFER_PRICE)}) AS BIGINT) * CAST(floor(ln(greatest(abs(v1 - {O.dbl(OFFER_PRICE)}) / 1.0::DOUBLE, 1.0::DOUBLE))) AS BIGINT)"
EM0 = f"WITH {O.OFFERS}, p0 AS (SELECT DISTINCT k, {O.dbl(OFFER_PRICE)} AS price FROM offers), {O.emissions(0, 1)}"


@query(f"{EM0} SELECT k AS knapsack_id, {O.MICROS.format(x='v1')} AS v1_micros, {BUCKET} AS bucket FROM em0")
def bucket_ids(spark, sf_dir):
    out = C.sparse_emissions(_entries(spark, sf_dir), [OFFER_PRICE] * 5, 1)
    return out.select(F.col("knapsack").alias("knapsack_id"), price_micros(F.col("v1")).alias("v1_micros"), bucket_id(F.col("v1"), F.lit(OFFER_PRICE), F.lit(1.0)).alias("bucket"))


@query(f"{EM0} SELECT k AS knapsack_id, CAST(floor(v1 / 250.0::DOUBLE) AS BIGINT) AS bucket, sum(v2) AS mass FROM em0 GROUP BY 1, 2")
def even_buckets(spark, sf_dir):
    out = C.sparse_emissions(_entries(spark, sf_dir), [OFFER_PRICE] * 5, 1)
    return out.groupBy(F.col("knapsack").alias("knapsack_id"), even_bucket_id(F.col("v1"), 250.0).alias("bucket")).agg(F.sum("v2").alias("mass"))


@query(f"{EM0} SELECT k AS knapsack_id, {BUCKET} AS bucket, sum(v2) AS mass, {O.MICROS.format(x='min(v1)')} AS lo_micros, {O.MICROS.format(x='max(v1)')} AS hi_micros, count(*) AS n FROM em0 GROUP BY 1, 2")
def bucket_hist(spark, sf_dir):
    out = C.sparse_emissions(_entries(spark, sf_dir), [OFFER_PRICE] * 5, 1)
    prices = spark.createDataFrame([(k, OFFER_PRICE) for k in range(1, 6)], "knapsack int, price double")
    h = thresholds.bucket_histogram(out, prices, 1.0)
    return h.select(F.col("knapsack").alias("knapsack_id"), "bucket", "mass", price_micros(F.col("lo")).alias("lo_micros"), price_micros(F.col("hi")).alias("hi_micros"), "n")


def _bucketed_sql() -> str:
    parts = [O.OFFERS, O.budgets(1), O.start_prices(OFFER_PRICE), O.emissions(0, 1)]
    return f"""WITH {', '.join(parts)}, h AS (SELECT k, {BUCKET} AS bucket, sum(v2) AS mass, min(v1) AS lo, max(v1) AS hi FROM em0 GROUP BY 1, 2),
c AS (SELECT h.*, budget, coalesce(sum(mass) OVER (PARTITION BY h.k ORDER BY hi DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS above FROM h JOIN budgets USING (k)),
x AS (SELECT k, hi - (budget - above) / mass * (hi - lo) AS price, row_number() OVER (PARTITION BY k ORDER BY hi DESC) AS r FROM c WHERE above + mass > budget)
SELECT b.k AS knapsack_id, {O.MICROS.format(x='coalesce(x.price, 0)')} AS price_micros FROM budgets b LEFT JOIN x ON x.k = b.k AND r = 1"""


@query(_bucketed_sql())
def threshold_bucketed(spark, sf_dir):
    p = _offers(spark, sf_dir)
    out = C.sparse_emissions(C.sparse_packed(p), [OFFER_PRICE] * 5, 1)
    found = thresholds.threshold_bucketed(out, {k: OFFER_PRICE for k in range(1, 6)}, {k + 1: b for k, b in enumerate(p.budgets)}, 1.0)
    return price_table(spark, [found[k] for k in range(1, 6)])


# ---------------------------------------------------------------- solver steps with unrolled oracles


def _scd_query(name: str, q: int, steps: list, start: float, customers: bool = False, **options):
    def f(spark, sf_dir):
        if customers:
            p = KnapsackProblem.from_long(I.customer_priority(spark, sf_dir), [1.0] * 5, Hierarchy.root(q)).pack()
            p = p.with_budgets(measures.scaled_budgets(p))
        else:
            p = _offers(spark, sf_dir, q)
        out = solvers.scd(p, start, solver="linear", reduce="exact", trace=False, tol=-1.0, damping=False, **options)
        return price_table(spark, out.prices)

    f.__name__ = name
    query(O.scd_chain(O.CUSTOMERS if customers else O.OFFERS, q, steps, start))(f)


_scd_query("scd_sparse_1_iter", 1, [None], OFFER_START, max_iter=1)
_scd_query("scd_sparse_3_iters", 1, [None] * 3, OFFER_START, max_iter=3)
_scd_query("scd_sparse_8_iters", 1, [None] * 8, OFFER_START, max_iter=8)
_scd_query("scd_sparse_q2_3_iters", 2, [None] * 3, OFFER_START, max_iter=3)
_scd_query("scd_customers_3_iters", 1, [None] * 3, OFFER_START, customers=True, max_iter=3)
_scd_query("scd_cyclic_1_cycle", 1, [[1], [2], [3], [4], [5]], OFFER_START, mode="cyclic", max_iter=1)
_scd_query("scd_block_1_cycle", 1, [[1, 3], [2, 4, 5]], OFFER_START, mode="block", blocks=[[1, 3], [2, 4, 5]], max_iter=1)


def _dd_query(name: str, q: int, steps: int, alpha: float):
    def f(spark, sf_dir):
        p = _offers(spark, sf_dir, q)
        return price_table(spark, solvers.dual_descent(p, alpha, OFFER_START, steps, tol=-1.0).prices)

    f.__name__ = name
    query(O.dd_chain(O.OFFERS, q, steps, OFFER_START, alpha))(f)


_dd_query("dd_step", 1, 1, OFFER_ALPHA)
_dd_query("dd_5_iters", 1, 5, OFFER_ALPHA)
_dd_query("dd_q2_5_iters", 2, 5, 2 * OFFER_ALPHA)


@query(O.dd_lines(2, 3, 100000.0, 0.5))
def dd_lines_3_iters(spark, sf_dir):
    p = I.orders_problem(spark, sf_dir, 2, "C2")
    return price_table(spark, solvers.dual_descent(p, 0.5, 100000.0, 3, tol=-1.0).prices)


@query()
def dd_sweep(spark, sf_dir):
    """Largest violation of the last iterate for several step sizes, all evaluated in the same passes."""
    out = solvers.dd_sweep(_offers(spark, sf_dir), [1.0, 5.0, 25.0], OFFER_START, 6)
    return spark.createDataFrame([(a, s.history[-1]["max_violation"], s.history[-1]["dual"]) for a, s in out.items()], "alpha double, max_violation double, dual double")


# ---------------------------------------------------------------- measures and repair


@query("SELECT CAST(0 AS BIGINT) AS violations")
def local_violations(spark, sf_dir):
    """Groups and nodes over their cap in a nested greedy solution: none."""
    p = KnapsackProblem.from_long(I.order_lines(spark, sf_dir, 2), [1.0, 1.0], levels=I.ORDER_LEVELS["hier"]).pack()
    n = measures.local_violations(p, subproblem.greedy_take(p, LINE_PRICES))
    return spark.createDataFrame([(n,)], "violations long")


@query()
def lp_bounds(spark, sf_dir):
    """Upper and lower bound of the relaxation of the user offers by column generation."""
    from .operators.lp_bound import lp_bound

    upper, lower = lp_bound(_offers(spark, sf_dir), 1e-4, 60)
    return spark.createDataFrame([(upper, lower)], "upper double, lower double")


@query()
def emission_cost(spark, sf_dir):
    """Rows an exact reduce would shuffle, and rows of the histogram, in one general iteration."""
    cost = measures.emission_cost(I.orders_problem(spark, sf_dir, 2, "hier"), LINE_PRICES)
    return spark.createDataFrame([(cost["emitted_rows"], cost["histogram_rows"])], "emitted_rows long, histogram_rows long")


FIXED = f"p0 AS (SELECT k, {O.dbl(OFFER_PRICE)} AS price FROM budgets)"
TAKEN = f"WITH {O.OFFERS}, {O.budgets(1)}, {FIXED}, t AS MATERIALIZED ({O.top_take('p0', 1)})"


@query(f"{TAKEN} SELECT CAST(sum(profit) AS DOUBLE) AS primal, CAST(floor((sum(net) + (SELECT sum(price * budget) FROM p0 JOIN budgets USING (k))) * 100 + 0.5) AS BIGINT) AS dual_cents, count(*) AS taken FROM t")
def metrics_primal_dual(spark, sf_dir):
    e = measures.evaluate(_offers(spark, sf_dir), [OFFER_PRICE] * 5)
    return spark.createDataFrame([(e.primal, e.dual, e.taken)], "primal double, dual double, taken long").select("primal", F.floor(F.col("dual") * 100 + 0.5).cast("bigint").alias("dual_cents"), "taken")


@query(f"{TAKEN}, u AS (SELECT b.k, coalesce(sum(need), 0) AS used, max(budget) AS budget FROM budgets b LEFT JOIN t USING (k) GROUP BY b.k) SELECT k AS knapsack_id, budget, used, greatest(used - budget, 0) / budget AS ratio FROM u")
def violations(spark, sf_dir):
    p = _offers(spark, sf_dir)
    used = measures.used_by_knapsack(subproblem.greedy_take(p, [OFFER_PRICE] * 5), p.items, p.budgets)
    return measures.violation_ratios(used).select("knapsack_id", "budget", "used", "ratio")


@query(f"{TAKEN}, u AS (SELECT b.k, coalesce(sum(need), 0) AS used, max(budget) AS budget FROM budgets b LEFT JOIN t USING (k) GROUP BY b.k) SELECT k AS knapsack_id, {O.dbl(OFFER_PRICE)} * (used - budget) AS slackness FROM u")
def kkt(spark, sf_dir):
    e = measures.evaluate(_offers(spark, sf_dir), [OFFER_PRICE] * 5)
    return spark.createDataFrame([(k + 1, s) for k, s in enumerate(e.slackness)], "knapsack_id int, slackness double")


@query(f"WITH {O.OFFERS}, {O.budgets(1)} SELECT k AS knapsack_id, budget FROM budgets")
def default_budgets(spark, sf_dir):
    return budget_table(spark, _offers(spark, sf_dir).budgets).withColumnRenamed("knapsack", "knapsack_id")


@query(f"WITH {O.OFFERS} SELECT k AS knapsack_id, sum(need) AS demand FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY profit DESC, item) AS r FROM offers WHERE profit > 0) WHERE r <= 2 GROUP BY k")
def unpriced_demand(spark, sf_dir):
    p = KnapsackProblem.from_long(I.user_offers(spark, sf_dir), [1.0] * 5, Hierarchy.root(2)).pack()
    e = measures.evaluate(p, [0.0] * 5)
    return spark.createDataFrame([(k + 1, u) for k, u in enumerate(e.used)], "knapsack_id int, demand double")


REPAIR_PRICE = 2500.0
REPAIR = f"""WITH {O.OFFERS}, {O.budgets(1)}, p0 AS (SELECT k, {O.dbl(REPAIR_PRICE)} AS price FROM budgets), t AS MATERIALIZED ({O.top_take('p0', 1)}),
gv AS MATERIALIZED (SELECT g, sum(net) AS value FROM t GROUP BY g),
x AS (SELECT k, coalesce(sum(need), 0) - max(budget) AS excess FROM budgets LEFT JOIN t USING (k) GROUP BY k),
r AS (SELECT gv.g, gv.value, b.k, sum(coalesce(t.need, 0)) OVER (PARTITION BY b.k ORDER BY gv.value, gv.g) AS removed FROM gv CROSS JOIN budgets b LEFT JOIN t ON t.g = gv.g AND t.k = b.k),
ok AS (SELECT r.g, r.value FROM r JOIN x USING (k) GROUP BY 1, 2 HAVING bool_and(removed >= excess)),
cut AS (SELECT g, value FROM ok ORDER BY value, g LIMIT 1)"""


def _repair(spark, sf_dir):
    p = _offers(spark, sf_dir)
    prices = [REPAIR_PRICE] * 5
    e = measures.evaluate(p, prices)
    groups = subproblem.group_results(p, prices)
    return groups, feasibility.repair(groups, e.used, p.budgets)


@query(f"{REPAIR} SELECT gv.g AS group_id FROM gv, cut WHERE (gv.value, gv.g) > (cut.value, cut.g)")
def repair_survivors(spark, sf_dir):
    return _repair(spark, sf_dir)[1].keep.select("group_id")


@query(f"{REPAIR} SELECT count(*) AS dropped, CAST(sum(t.need) AS DOUBLE) AS need FROM t JOIN gv USING (g), cut WHERE (gv.value, gv.g) <= (cut.value, cut.g)")
def repair_groups(spark, sf_dir):
    groups, fixed = _repair(spark, sf_dir)
    gone = groups.join(fixed.keep.select("group_id"), "group_id", "left_anti")
    return gone.agg(F.count(F.lit(1)).alias("dropped"), F.sum(F.aggregate("used", F.lit(0.0), lambda a, x: a + x)).alias("need"))


@query(f"WITH {O.OFFERS} SELECT DISTINCT g AS group_id FROM offers WHERE g NOT IN (SELECT g FROM offers WHERE profit - 9000.0::DOUBLE * need > 0)")
def idle_groups(spark, sf_dir):
    p = KnapsackProblem.from_long(I.user_offers(spark, sf_dir), [1.0] * 5, Hierarchy.root(1)).pack()
    return p.packed.select("group_id").join(subproblem.greedy_take(p, [9000.0] * 5), "group_id", "left_anti")


@query("WITH i AS (SELECT CAST(item_id AS INT) AS item, CAST(len(string_split(text, ' ')) AS DOUBLE) AS profit, CAST(length(text) AS DOUBLE) AS need FROM benchmark), r AS (SELECT *, coalesce(sum(need) OVER (ORDER BY profit / need DESC, item ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM i) SELECT item AS item_id, greatest(0.0, least(1.0, (3000.0::DOUBLE - before) / need)) AS part FROM r")
def fractional_kp(spark, sf_dir):
    return groundtruth.fractional_knapsack(I.benchmark_pick(spark, sf_dir), 3000.0).select("item_id", "part")


@query("WITH i AS (SELECT CAST(item_id AS INT) AS item, CAST(len(string_split(text, ' ')) AS DOUBLE) AS profit, CAST(length(text) AS DOUBLE) AS need FROM benchmark), r AS (SELECT *, sum(need) OVER (ORDER BY profit / need DESC, item ROWS UNBOUNDED PRECEDING) AS running FROM i) SELECT item AS item_id FROM r WHERE running <= 3000")
def density_greedy(spark, sf_dir):
    return groundtruth.density_greedy(I.benchmark_pick(spark, sf_dir), 3000.0).select("item_id")


@query(f"WITH {O.OFFERS}, {O.budgets(1)}, s AS (SELECT DISTINCT g FROM offers WHERE (g * 7919) % 1000 < 300) SELECT k AS knapsack_id, budget * (SELECT count(*) FROM s) / (SELECT count(DISTINCT g) FROM offers) AS budget FROM budgets")
def presolve_budgets(spark, sf_dir):
    p = _offers(spark, sf_dir)
    counts = p.packed.agg(F.count_if((F.col("group_id") * 7919) % 1000 < 300).alias("n"), F.count(F.lit(1)).alias("all"))
    return budget_table(spark, p.budgets).crossJoin(F.broadcast(counts)).select(F.col("knapsack").alias("knapsack_id"), (F.col("budget") * F.col("n") / F.col("all")).alias("budget"))


# ---------------------------------------------------------------- surrounding operators


@query(f"WITH {O.OFFERS} SELECT o.g AS group_id, o.item AS item_id, t.tier FROM offers o JOIN (VALUES (1, 0.0, 20000.0), (2, 20000.0, 60000.0), (3, 60000.0, 1e12)) t(tier, lo, hi) ON o.profit >= t.lo AND o.profit < t.hi")
def budget_tiers(spark, sf_dir):
    tiers = spark.createDataFrame([(1, 0.0, 2e4), (2, 2e4, 6e4), (3, 6e4, 1e12)], "tier int, lo double, hi double")
    o = I.user_offers(spark, sf_dir)
    return o.join(F.broadcast(tiers), (o.profit >= tiers.lo) & (o.profit < tiers.hi)).select("group_id", "item_id", "tier")


@query("SELECT e.event_id, CAST(day_of AS INT) AS price_day FROM (SELECT event_id, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS d FROM events) e ASOF JOIN (SELECT unnest([0, 3, 7, 14, 21]) AS day_of) p ON e.d >= p.day_of")
def price_asof_events(spark, sf_dir):
    """The price version in force at each event: versions and events in one timeline, the last version seen."""
    versions = spark.createDataFrame([(d,) for d in (0, 3, 7, 14, 21)], "day_of int")
    e = I.table(spark, sf_dir, "events").select("event_id", F.datediff("ts", F.lit("2024-01-01").cast("date")).alias("d"))
    return pacing.asof_version(e, versions, "d", "day_of").select("event_id", F.col("day_of").alias("price_day"))


@query(f"WITH {O.OFFERS} SELECT k AS knapsack_id, sum(need) AS used, count(DISTINCT g) AS groups FROM offers GROUP BY k")
def used_per_knapsack(spark, sf_dir):
    return I.user_offers(spark, sf_dir).groupBy("knapsack_id").agg(F.sum("need").alias("used"), F.count_distinct("group_id").alias("groups"))


@query()
def value_quantiles(spark, sf_dir):
    """Approximate quantiles of profits and the number of groups (sketches; no exact counterpart)."""
    o = I.user_offers(spark, sf_dir)
    return o.agg(F.percentile_approx("profit", [0.25, 0.5, 0.75], 1000).alias("q"), F.approx_count_distinct("group_id").alias("groups"))


@query("SELECT n_regionkey AS region, s_nationkey AS nation, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS used FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey GROUP BY ROLLUP (n_regionkey, s_nationkey)")
def used_rollup_region(spark, sf_dir):
    return I.order_nations(spark, sf_dir).rollup("region", "nation").agg(F.sum(F.element_at("needs", 1).cast("bigint")).alias("used"))


@query("SELECT role, CAST(turn AS INT) AS turn, count(*) AS n, CAST(sum(len(string_split(text, ' '))) AS BIGINT) AS words FROM conversations GROUP BY CUBE (role, turn)")
def used_cube_role(spark, sf_dir):
    return I.turn_budget(spark, sf_dir).cube("role", F.col("item_id").alias("turn")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("need").cast("bigint")).alias("words"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def used_grouping_sets(spark, sf_dir):
    I.table(spark, sf_dir, "orders").createOrReplaceTempView("shadowpack_orders")
    return spark.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM shadowpack_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


@query(f"WITH {O.OFFERS} SELECT g AS group_id, " + ", ".join(f"coalesce(sum(need) FILTER (WHERE k = {k}), 0) AS b{k}" for k in range(1, 6)) + " FROM offers GROUP BY g")
def needs_pivot(spark, sf_dir):
    p = I.user_offers(spark, sf_dir).groupBy("group_id").pivot("knapsack_id", [1, 2, 3, 4, 5]).agg(F.sum("need"))
    return p.select("group_id", *[F.coalesce(F.col(str(k)), F.lit(0.0)).alias(f"b{k}") for k in range(1, 6)])


DAILY = "d AS (SELECT CAST(ts AS DATE) AS day, event_type, count(*) AS n, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY 1, 2)"


@query(f"WITH {DAILY} SELECT strftime(day, '%Y-%m-%d') AS day, event_type, n, cents FROM d")
def daily_items(spark, sf_dir):
    e = I.table(spark, sf_dir, "events")
    return e.groupBy(F.date_format(F.to_date("ts"), "yyyy-MM-dd").alias("day"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(I.cents(F.col("value"))).alias("cents"))


@query(f"WITH {DAILY} SELECT strftime(day, '%Y-%m-%d') AS day, event_type, cents - lag(cents) OVER (PARTITION BY event_type ORDER BY day) AS change FROM d")
def price_delta(spark, sf_dir):
    d = daily_items(spark, sf_dir)
    return d.select("day", "event_type", (F.col("cents") - F.lag("cents").over(Window.partitionBy("event_type").orderBy("day"))).alias("change"))


@query(f"WITH {O.OFFERS} SELECT g AS group_id, CAST(sum(profit) AS DOUBLE) AS value FROM offers GROUP BY g ORDER BY value, g LIMIT 20")
def lowest_value_groups(spark, sf_dir):
    return I.user_offers(spark, sf_dir).groupBy("group_id").agg(F.sum("profit").alias("value")).orderBy("value", "group_id").limit(20)


@query()
def hash_sample(spark, sf_dir):
    from .operators.presolve import hash_sample as sample

    return sample(I.user_offers(spark, sf_dir), 0.3, 7).select("group_id", "item_id")


@query(f"WITH {O.OFFERS}, a AS (SELECT g, item FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY profit - 3000.0::DOUBLE * need DESC, item) AS r FROM offers WHERE profit - 3000.0::DOUBLE * need > 0) WHERE r = 1), b AS (SELECT g, item FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY profit - 5000.0::DOUBLE * need DESC, item) AS r FROM offers WHERE profit - 5000.0::DOUBLE * need > 0) WHERE r = 1) SELECT g AS group_id, item AS item_id FROM a EXCEPT ALL SELECT g, item FROM b")
def decision_diff(spark, sf_dir):
    p = KnapsackProblem.from_long(I.user_offers(spark, sf_dir), [1.0] * 5, Hierarchy.root(1)).pack()
    one, two = (subproblem.greedy_take(p, [x] * 5).select("group_id", "item_id") for x in (3000.0, 5000.0))
    return one.exceptAll(two)


@query(f"WITH {O.OFFERS} SELECT g AS group_id, count(*) AS items, CAST(sum(profit) AS DOUBLE) AS profit, CAST(sum(need) AS DOUBLE) AS need FROM offers GROUP BY g")
def packed_groups(spark, sf_dir):
    p = KnapsackProblem.from_long(I.user_offers(spark, sf_dir), [1.0] * 5, Hierarchy.root(1)).pack()
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda a, x: a + x)
    return p.packed.select("group_id", F.size("item_ids").cast("bigint").alias("items"), total("profits").alias("profit"), total("one_need").alias("need"))


@query("SELECT event_type, count(*) AS n, count(json_extract_string(props, '$.k')) AS with_k FROM events GROUP BY 1")
def props_need(spark, sf_dir):
    e = I.table(spark, sf_dir, "events")
    return e.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.count(F.get_json_object("props", "$.k")).alias("with_k"))


SQL_TOPQ = f"WITH {O.OFFERS} SELECT g AS group_id, item AS item_id FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY profit - {O.dbl(OFFER_PRICE)} * need DESC, item) AS r FROM offers WHERE profit - {O.dbl(OFFER_PRICE)} * need > 0) WHERE r <= 1"


@query(SQL_TOPQ)
def sql_topq(spark, sf_dir):
    register_sql_functions(spark)
    I.user_offers(spark, sf_dir).createOrReplaceTempView("shadowpack_offers")
    return spark.sql("SELECT group_id, item_id FROM (SELECT *, row_number() OVER (PARTITION BY group_id ORDER BY net_profit(profit, array(need), array(:price)) DESC, item_id) AS r FROM shadowpack_offers WHERE net_profit(profit, array(need), array(:price)) > 0) WHERE r <= :q", args={"price": OFFER_PRICE, "q": 1})


@query(SQL_TOPQ)
def greedy_udtf(spark, sf_dir):
    from .functions.table_functions import register

    register(spark)
    I.user_offers(spark, sf_dir).createOrReplaceTempView("shadowpack_offers")
    return spark.sql(f"SELECT group_id, item_id FROM best_items(TABLE(SELECT group_id, item_id, profit - {OFFER_PRICE}D * need AS net, 1 AS cap FROM shadowpack_offers) PARTITION BY group_id)")


@query(_threshold_sql(False))
def threshold_udaf(spark, sf_dir):
    """The exact threshold as a grouped aggregate in pandas (small emissions)."""
    from .functions.table_functions import threshold_udaf as udaf

    p = _offers(spark, sf_dir)
    out = C.sparse_emissions(C.sparse_packed(p), [OFFER_PRICE] * 5, 1)
    per = out.join(F.broadcast(budget_table(spark, p.budgets)), "knapsack").groupBy("knapsack").agg(udaf("v1", "v2", "budget").alias("price"))
    return per.select(F.col("knapsack").alias("knapsack_id"), price_micros(F.col("price")).alias("price_micros"))


@query("SELECT event_type, CAST(date_trunc('day', ts) AS TIMESTAMP) AS day, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY 1, 2")
def window_spend(spark, sf_dir):
    return pacing.window_spend(I.table(spark, sf_dir, "events"), "1 day").select("event_type", F.col("start").cast("timestamp_ntz").alias("day"), "cents")


@query("SELECT event_type, CAST(date_trunc('day', ts) - to_days(CAST(o AS INT)) AS TIMESTAMP) AS day, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents FROM events, range(2) r(o) GROUP BY 1, 2")
def sliding_spend(spark, sf_dir):
    return pacing.window_spend(I.table(spark, sf_dir, "events"), "2 days", "1 day").select("event_type", F.col("start").cast("timestamp_ntz").alias("day"), "cents")


@query("WITH s AS (SELECT user_id, ts, CAST(floor(value * 100 + 0.5) AS BIGINT) AS c, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events), n AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM s) SELECT user_id, min(ts) AS start, count(*) AS n, CAST(sum(c) AS BIGINT) AS cents FROM n GROUP BY user_id, sid")
def session_spend(spark, sf_dir):
    return pacing.session_spend(I.table(spark, sf_dir, "events"), "6 hours").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n", "cents")


# ---------------------------------------------------------------- experiments (measures of converged runs)


def _workload(name: str, f) -> None:
    def run(spark, sf_dir):
        return f(spark, sf_dir)

    run.__name__, run.__doc__ = name, f.__doc__
    query()(run)


for _name, _f in {
    "solve_offers": workloads.solve_offers,
    "opt_ratio_order_lines": workloads.optimality_order_lines,
    "opt_ratio_lattice": workloads.optimality_lattice,
    "gap_sparse": workloads.gap_sparse,
    "presolve_iterations": workloads.presolve_effect,
    "presolve_customers": workloads.presolve_customers,
    "descent_traces": workloads.descent_traces,
    "scd_modes": workloads.modes,
    "bucket_error": workloads.bucket_error,
    "repair_effect": workloads.repair_effect,
    "daily_solve": workloads.daily_solve,
    "linear_speedup": workloads.linear_speedup,
    "greedy_vs_exact": workloads.greedy_against_exact,
    "single_knapsack": workloads.single_knapsack,
}.items():
    _workload(_name, _f)
