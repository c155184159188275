"""Sharding by longest processing time: groups that must stay together go, largest first, to the least
loaded shard through a heap.

The heap runs on the driver over a bounded number of items, whatever the corpus size: every group of at
least 1/(shards * FINENESS) of all bytes is an item of its own (there can't be more than shards *
FINENESS of these), and smaller groups are pooled by size class and content hash into pools of about
that size. Equal texts have equal size and hash, so a pool never splits a group."""

from __future__ import annotations

import heapq
import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stage

#: Items per shard, about, that the heap deals out.
FINENESS = 512
#: Rows that one task numbers, about.
SLOT_ROWS = 200_000


def longest_first(items: list[tuple[int, tuple]], shards: int) -> dict[tuple, int]:
    """items: (size, key). Larger items first (ties by key), each to the least loaded shard (ties to the
    smaller shard number)."""
    heap = [(0, s) for s in range(shards)]
    out: dict[tuple, int] = {}
    for size, key in sorted(items, key=lambda x: (-x[0], x[1])):
        load, shard = heapq.heappop(heap)
        out[key] = shard
        heapq.heappush(heap, (load + size, shard))
    return out


def shard_by_size(docs: DataFrame, shards: int = 16) -> DataFrame:
    """Puts all rows into shards 0..shards-1 of nearly equal bytes; rows of equal text stay together.

    docs: doc_id, text, any other columns (ignored). Size: UTF-8 bytes of the text (null: none) plus 1.
    Null and empty texts have the same bytes and so are one group. Returns doc_id, size, text_crc32
    (unsigned, of the UTF-8 bytes), law ('bytes'), shard, slot (gapless from 0 in each shard),
    grown_shard (null under this law). One row per input row; repeated rows stay repeated. Fewer groups
    than shards leave shards empty. Empty table: empty result. A single group larger than an even
    share makes its shard larger than the others: groups are never split."""
    text = F.coalesce("text", F.lit(""))
    rows = stage(docs.select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.unhex(F.md5(text.cast("binary"))).alias("group")), "digests")
    total, count = rows.agg(F.coalesce(F.sum("size"), F.lit(0)), F.count(F.lit(1))).first()
    share = max(1, math.ceil(total / (shards * FINENESS)))
    size_class = F.floor(F.log2("size") * 8).cast("int")
    rows = rows.withColumn("class", size_class)
    classes = {r["class"]: math.ceil(r["bytes"] / share) for r in rows.groupBy("class").agg(F.sum("size").alias("bytes")).collect()}
    large = rows.groupBy("group").agg(F.sum("size").alias("bytes")).where(F.col("bytes") >= share)
    own = [(r["bytes"], (0, bytes(r["group"]))) for r in large.collect()]
    spark = docs.sparkSession
    own_df = F.broadcast(spark.createDataFrame([(k[1], i) for i, (_, k) in enumerate(own)], "group binary, own int"))
    pools_df = F.broadcast(spark.createDataFrame(list(classes.items()), "class int, pools int"))
    pooled = rows.join(own_df, "group", "left").join(pools_df, "class", "left").withColumn("pool", F.when(F.col("own").isNull(), F.pmod(F.xxhash64("group"), F.greatest("pools", F.lit(1)))))
    pools = pooled.where("own is null").groupBy("class", "pool").agg(F.sum("size").alias("bytes")).collect()
    put = longest_first(own + [(r["bytes"], (1, r["class"], r["pool"])) for r in pools], shards)
    own_shard = F.broadcast(spark.createDataFrame([(i, put[k]) for i, (_, k) in enumerate(own)], "own int, own_shard int"))
    pool_shard = F.broadcast(spark.createDataFrame([(k[1], k[2], s) for k, s in put.items() if k[0]], "class int, pool long, pool_shard int"))
    placed = pooled.join(own_shard, "own", "left").join(pool_shard, ["class", "pool"], "left").select("doc_id", "size", "text_crc32", F.coalesce("own_shard", "pool_shard").alias("shard"))
    return number_slots(placed, count).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def number_slots(placed: DataFrame, count: int) -> DataFrame:
    """Gapless numbers within each shard: each shard's rows are cut into parts by a hash of the id, counted
    per part (a bounded table), numbered per part, and shifted by the counts of earlier parts."""
    parts = max(4, math.ceil(count / SLOT_ROWS))
    placed = placed.withColumn("part", F.pmod(F.xxhash64("doc_id", "size", "text_crc32"), F.lit(parts)).cast("int"))
    counts = placed.groupBy("shard", "part").agg(F.count(F.lit(1)).alias("n"))
    ahead = F.coalesce(F.sum("n").over(Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    # a row per part: grows with the corpus, so whether it is broadcast is left to its measured size
    offsets = counts.select("shard", "part", ahead.alias("ahead"))
    within = F.row_number().over(Window.partitionBy("shard", "part").orderBy("doc_id", "size", "text_crc32"))
    return placed.withColumn("nth", within).join(offsets, ["shard", "part"]).withColumn("slot", (F.col("ahead") + F.col("nth") - 1).cast("long"))
