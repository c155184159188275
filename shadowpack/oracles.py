"""DuckDB texts that state the same results independently: windows and joins where Spark uses arrays and
Arrow kernels, iterations as chains of common table expressions."""

from __future__ import annotations

OFFERS = """ev AS (SELECT user_id AS g, event_type, sum(greatest(CAST(floor(value * 100 + 0.5) AS BIGINT), 0)) AS profit, count(*) AS need FROM events GROUP BY 1, 2),
offers AS (SELECT g, CAST(k AS INT) AS item, CAST(profit AS DOUBLE) AS profit, CAST(k AS INT) AS k, CAST(need AS DOUBLE) AS need
  FROM (SELECT *, list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) AS k FROM ev) WHERE k > 0)"""

CUSTOMERS = """offers AS (SELECT o_custkey AS g, CAST(k AS INT) AS item, CAST(sum(CAST(floor(o_totalprice * 100 + 0.5) AS BIGINT)) AS DOUBLE) AS profit, CAST(k AS INT) AS k, CAST(count(*) AS DOUBLE) AS need
  FROM (SELECT *, list_position(['1-URGENT', '2-HIGH', '3-MEDIUM', '4-NOT SPECIFIED', '5-LOW'], o_orderpriority) AS k FROM orders) WHERE k > 0 GROUP BY 1, k)"""

LINES = """numbered AS (SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_quantity, l_discount, l_tax, l_shipdate) AS item FROM lineitem),
lines AS (SELECT l_orderkey AS g, CAST(item AS INT) AS item, CAST(floor(l_extendedprice * (1 - l_discount) * 100 + 0.5) AS DOUBLE) AS profit,
  CAST(l_quantity AS DOUBLE) AS b1, CAST(floor(l_tax * 100 + 0.5) AS DOUBLE) AS b2, CAST(floor(l_discount * 100 + 0.5) AS DOUBLE) AS b3, CAST(p_size AS DOUBLE) AS b4,
  CAST(abs(date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE))) AS DOUBLE) AS b5, l_linestatus AS ls, l_linestatus || '|' || l_returnflag AS sf, l_suppkey
  FROM numbered JOIN part ON p_partkey = l_partkey JOIN orders ON o_orderkey = l_orderkey)"""

MICROS = "CAST(floor({x} * 1e6 + 0.5) AS BIGINT)"


def dbl(x: float) -> str:
    return f"CAST({x!r} AS DOUBLE)"


def budgets(q: int, numerator: int = 1, denominator: int = 2) -> str:
    return f"""free AS (SELECT k, need FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY profit DESC, item) AS r FROM offers WHERE profit > 0) WHERE r <= {q}),
budgets AS (SELECT k, CAST(greatest(1, CAST(sum(need) AS BIGINT) * {numerator} // {denominator}) AS DOUBLE) AS budget FROM free GROUP BY k)"""


def start_prices(value: float) -> str:
    return f"p0 AS (SELECT k, {dbl(value)} AS price FROM budgets)"


def emissions(t: int, q: int) -> str:
    return f"""adj{t} AS MATERIALIZED (SELECT o.*, greatest(o.profit - p.price * o.need, 0.0::DOUBLE) AS a FROM offers o JOIN p{t} p USING (k)),
ord{t} AS (SELECT g, a, row_number() OVER (PARTITION BY g ORDER BY a DESC) AS r FROM adj{t}),
top{t} AS (SELECT g, coalesce(max(a) FILTER (WHERE r = {q}), 0) AS qth, coalesce(max(a) FILTER (WHERE r = {q + 1}), 0) AS nxt FROM ord{t} GROUP BY g),
em{t} AS MATERIALIZED (SELECT k, (profit - rival) / need AS v1, need AS v2 FROM (SELECT a.*, CASE WHEN a.a >= top.qth THEN top.nxt ELSE top.qth END AS rival FROM adj{t} a JOIN top{t} top USING (g)) WHERE profit > rival AND need > 0)"""


def masses(t: int) -> str:
    return f"ms{t} AS MATERIALIZED (SELECT k, v1, sum(m) OVER (PARTITION BY k ORDER BY v1 DESC) AS mass FROM (SELECT k, v1, sum(v2) AS m FROM em{t} GROUP BY 1, 2))"


def next_prices(t: int, chosen: list[int] | None = None, last_fit: bool = False) -> str:
    cross = "max(CASE WHEN mass > budget THEN v1 END)"
    new = f"CASE WHEN {cross} IS NULL THEN 0.0 ELSE coalesce(min(CASE WHEN mass <= budget THEN v1 END), {cross}) END" if last_fit else f"coalesce({cross}, 0)"
    if chosen:
        new = f"CASE WHEN b.k IN ({', '.join(map(str, chosen))}) THEN {new} ELSE max(o.price) END"
    return f"p{t + 1} AS MATERIALIZED (SELECT b.k, {new} AS price FROM budgets b JOIN p{t} o USING (k) LEFT JOIN ms{t} USING (k) GROUP BY b.k)"


def scd_chain(source: str, q: int, steps: list[list[int] | None], start: float) -> str:
    parts = [source, budgets(q), start_prices(start)]
    for t, chosen in enumerate(steps):
        parts += [emissions(t, q), masses(t), next_prices(t, chosen)]
    return f"WITH {', '.join(parts)} SELECT k AS knapsack_id, {MICROS.format(x='price')} AS price_micros FROM p{len(steps)}"


def dd_chain(source: str, q: int, steps: int, start: float, alpha: float) -> str:
    parts = [source, budgets(q), start_prices(start)]
    for t in range(steps):
        parts.append(f"""net{t} AS (SELECT o.*, o.profit - p.price * o.need AS net FROM offers o JOIN p{t} p USING (k)),
use{t} AS (SELECT k, sum(need) AS used FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY net DESC, item) AS r FROM net{t} WHERE net > 0) WHERE r <= {q} GROUP BY k),
p{t + 1} AS MATERIALIZED (SELECT b.k, greatest(0.0::DOUBLE, p.price + {dbl(alpha)} * (coalesce(u.used, 0) - b.budget)) AS price FROM budgets b JOIN p{t} p USING (k) LEFT JOIN use{t} u USING (k))""")
    return f"WITH {', '.join(parts)} SELECT k AS knapsack_id, {MICROS.format(x='price')} AS price_micros FROM p{steps}"


def greedy_sql(levels: list[tuple[str, int]], prices: list[float], source: str = LINES, table: str = "lines") -> str:
    """Nested windows, one for each level; nodes are column lists after the group."""
    net = "profit" + "".join(f" - {dbl(p)} * b{i + 1}" for i, p in enumerate(prices))
    sql = f"SELECT *, {net} AS net FROM {table}"
    sql = f"SELECT * FROM ({sql}) WHERE net > 0"
    for node, cap in levels:
        part = "g" + (f", {node}" if node else "")
        sql = f"SELECT * EXCLUDE (r) FROM (SELECT *, row_number() OVER (PARTITION BY {part} ORDER BY net DESC, item) AS r FROM ({sql})) WHERE r <= {cap}"
    return f"WITH {source} SELECT g AS group_id, item AS item_id, CAST(1 AS INT) AS units FROM ({sql})"


def top_take(prices_sql: str, q: int) -> str:
    """Decisions of sparse offers at the prices of a relation (k, price)."""
    return f"SELECT o.g, o.item, o.k, o.need, o.profit, o.net FROM (SELECT o.*, row_number() OVER (PARTITION BY g ORDER BY net DESC, item) AS r FROM (SELECT o.*, o.profit - p.price * o.need AS net FROM offers o JOIN {prices_sql} p USING (k)) o WHERE net > 0) o WHERE r <= {q}"


def dd_lines(cap: int, steps: int, start: float, alpha: float) -> str:
    """Dual descent on order lines with two dense needs and one cap per order."""
    parts = [LINES, "items AS MATERIALIZED (SELECT g, item, profit, b1, b2 FROM lines)"]

    def used(price_sql: str, name: str) -> str:
        return f"""{name} AS MATERIALIZED (SELECT coalesce(sum(b1), 0) AS u1, coalesce(sum(b2), 0) AS u2 FROM (SELECT b1, b2, row_number() OVER (PARTITION BY g ORDER BY net DESC, item) AS r FROM (SELECT i.*, i.profit - p.p1 * i.b1 - p.p2 * i.b2 AS net FROM items i, {price_sql} p) WHERE net > 0) WHERE r <= {cap})"""

    parts += ["zero AS (SELECT 0.0::DOUBLE AS p1, 0.0::DOUBLE AS p2)", used("zero", "free")]
    parts.append("bud AS (SELECT CAST(greatest(1, CAST(u1 AS BIGINT) // 2) AS DOUBLE) AS c1, CAST(greatest(1, CAST(u2 AS BIGINT) // 2) AS DOUBLE) AS c2 FROM free)")
    parts.append(f"q0 AS (SELECT {dbl(start)} AS p1, {dbl(start)} AS p2)")
    for t in range(steps):
        parts.append(used(f"q{t}", f"use{t}"))
        parts.append(f"q{t + 1} AS MATERIALIZED (SELECT greatest(0.0::DOUBLE, p1 + {dbl(alpha)} * (u1 - c1)) AS p1, greatest(0.0::DOUBLE, p2 + {dbl(alpha)} * (u2 - c2)) AS p2 FROM q{t}, use{t}, bud)")
    return f"WITH {', '.join(parts)} SELECT CAST(k AS INT) AS knapsack_id, {MICROS.format(x='CASE WHEN k = 1 THEN p1 ELSE p2 END')} AS price_micros FROM q{steps}, range(1, 3) r(k)"
