"""Registered queries against DuckDB on the smallest tables, and the streaming twins."""

import os

import duckdb
import pytest

import __spark_entry__ as entry_point
from shadowpack.queries import ORACLE_QUERIES, QUERIES
from shadowpack.streaming import pacing

from .conftest import DATA


@pytest.fixture(scope="session")
def duck():
    con = duckdb.connect()
    for f in os.listdir(f"{DATA}/sf0.001"):
        con.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{DATA}/sf0.001/{f}'")
    return con


@pytest.mark.parametrize("name", sorted(ORACLE_QUERIES))
def test_oracle(spark, duck, small, name):
    df = QUERIES[name](spark, small)
    got = duck.execute(ORACLE_QUERIES[name])
    columns = [c[0] for c in got.description]
    assert sorted(columns) == sorted(df.columns)
    key = sorted(columns)
    want = sorted((tuple(r[columns.index(c)] for c in key) for r in got.fetchall()), key=repr)
    have = sorted((tuple(r[c] for c in key) for r in df.collect()), key=repr)
    assert len(have) == len(want)
    for a, b in zip(have, want, strict=True):
        assert [float(x) if isinstance(x, (int, float)) else x for x in a] == [float(x) if hasattr(x, "as_tuple") or isinstance(x, (int, float)) else x for x in b]


def test_lattice_items_are_those_of_the_orders(spark, small, duck):
    df = QUERIES["lattice_items"](spark, small)
    assert [f.rsplit("/", 1)[1] for f in df.inputFiles()] == ["orders.parquet"]
    keys = {g for (g,) in duck.execute("SELECT o_orderkey FROM orders").fetchall()}
    assert {r["group_id"] for r in df.collect()} == keys and df.count() == 5 * len(keys)


def test_entry(spark):
    assert entry_point.entry(spark).count() > 0
    assert set(entry_point.oracle_sql()) <= set(entry_point.queries())


def test_streaming_matches_batch(spark, small, tmp_path):
    events = spark.read.parquet(f"{small}/events.parquet")
    source = str(tmp_path / "in")
    events.write.parquet(source)
    stream = spark.readStream.schema(events.schema).parquet(source)
    q = pacing.window_spend(stream, "1 day").writeStream.format("memory").queryName("spend").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert sorted(map(tuple, spark.table("spend").collect())) == sorted(map(tuple, pacing.window_spend(events, "1 day").collect()))


def test_admission_pacing_and_resolve(spark, small, tmp_path):
    events = spark.read.parquet(f"{small}/events.parquet")
    source = str(tmp_path / "in")
    events.write.parquet(source)
    stream = spark.readStream.schema(events.schema).parquet(source)
    prices = spark.createDataFrame([(t, 3000) for t in ("click", "view")], "event_type string, price long")
    taken = pacing.admit(pacing.deduplicated(stream), prices)
    q = taken.writeStream.format("memory").queryName("admitted").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.table("admitted").count() == pacing.admit(events, prices).count()
    q = pacing.paced_spend(stream, 50_000).writeStream.format("memory").queryName("paced").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert all(r["spent"] <= 50_000 and r["taken"] > 0 for r in spark.table("paced").collect())
    seen = []
    q = pacing.resolve_each_batch(stream, lambda df, _: seen.append(df.count()), str(tmp_path / "ck"))
    q.awaitTermination(120)
    assert sum(seen) == events.count()
