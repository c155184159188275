"""The pipeline's stages, each against brute force on its own input."""

from pyspark.sql import functions as F

import corpus_pipeline
from shadowpack.llm.common import stage

from .test_operators import check_packing, components, contaminated, odd_rows, repeated_words


def rows(df):
    return {r["doc_id"]: r["text"] for r in df.collect()}


def test_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    extra = spark.createDataFrame([(k + 10**6, t) for k, t in odd_rows()], "doc_id long, text string")
    docs = docs.unionByName(extra, allowMissingColumns=True)
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{small}/labels.parquet").collect()}
    before = rows(docs)
    for name, step in corpus_pipeline.STAGES:
        out = stage(step(spark, docs, small), f"test-{name}")
        if name != "packing":
            assert out.columns == docs.columns
            after = rows(out)
        if name == "quality":
            known = [k for k in before if k in labels]
            assert sum((k in after) == bool(labels[k]) for k in known) >= 0.95 * len(known)
        elif name == "near_dedup":
            want = components(before, 5)
            assert set(after) == {k for k, (_, c) in want.items() if c == k}
        elif name == "substring_dedup":
            want = repeated_words(before, 35)
            assert set(after) == set(before)
            assert all(after[k] == (want[k][3] if want[k][1] else before[k]) for k in before)
            assert out.where(F.col("n_chars") != F.char_length("text")).count() == 0
        elif name == "decontaminate":
            items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
            want = contaminated(before, items)
            assert set(after) == {k for k in before if not want[k][4]}
        else:
            check_packing(out.collect(), before)
        docs, before = (out, after) if name != "packing" else (docs, before)


def test_odd_rows_and_empty_tables_pass(spark, small):
    schema = spark.read.parquet(f"{small}/documents.parquet").schema
    odd = spark.createDataFrame([(1, None, None, None, None), (1, None, None, None, None), (None, "a b", "en", None, 3), (None, "", "en", "s", 0), (7, "x y z", None, None, 5)], schema)
    for docs in (odd, spark.createDataFrame([], schema)):
        for _, step in corpus_pipeline.STAGES:
            out = step(spark, docs, small)
            out.collect()
            if out.columns == docs.columns:
                docs = out
