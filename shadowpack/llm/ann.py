"""Approximate nearest neighbours by balanced posting lists.

Centroids are fitted on a bounded sample; their number grows with the table up to a bound, so they and
the graph between them are broadcast. Every distinct vector is listed under its nearest centroid, and
under further ones that are almost as near (boundary replicas). A query searches the centroid graph,
keeps the nearest lists, and further ones whose distance is within a ratio of the nearest one's, and is
compared exactly with their vectors. A query that finds too few is compared with all. The ratio is set
from the data: the true neighbours of a bounded number of vectors, found by brute force over the whole
table, must be in reach, so that recall doesn't fall as tables grow or clusters fade. Long lists are dealt
out in pieces, so that no task takes a whole popular list, and equal vectors are one entry, whatever their
number. Entries of equal cosine go by their smallest vec_id wherever some are left out."""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import release, ship_package, stage, stage_mark

#: Vectors to fit centroids on; centroids at most; vectors a list should hold; replicas at most.
SAMPLE, MOST_CENTROIDS, LIST_VECTORS, REPLICAS = 20_000, 8192, 128, 4
#: Relative excess of squared distance up to which a vector is replicated.
CLOSE = 0.25
#: Vectors whose true neighbours decide how far to search; share of those neighbours that must be in reach
#: by rank, and by distance ratio; lists searched at least.
CALIBRATION, REACH, LEAST_LISTS = 256, 0.985, 8
#: Edges per centroid in the graph; entries of its search for placing vectors.
EDGES, BEAM = 12, 48
#: Vectors of one list that one task compares at a time; queries compared with all vectors in one pass.
PIECE, PASS_QUERIES = 4096, 1024
#: Error bound of a cosine by matrix product; pairs whose cosine is computed at a time.
ROUNDING, PAIRS = 1e-12, 1 << 15


def fit_centroids(sample: np.ndarray, count: int, rounds: int = 8) -> np.ndarray:
    """Spherical k-means with a penalty on crowded clusters, from a fixed start; empty clusters restart
    from members of the largest."""
    rng = np.random.default_rng(11)
    count = max(1, min(count, sample.shape[0]))
    centroids = sample[np.sort(rng.choice(sample.shape[0], count, replace=False))].copy()
    target = sample.shape[0] / count
    load = np.full(count, target)
    for _ in range(rounds):
        near = np.concatenate([(b @ centroids.T - 0.02 * (load / target)).argmax(axis=1) for b in np.array_split(sample, max(1, sample.shape[0] // 2048))])
        load = np.bincount(near, minlength=count).astype(float)
        sums = np.zeros_like(centroids)
        np.add.at(sums, near, sample)
        empty = np.flatnonzero(load == 0)
        if empty.size:
            crowd = np.flatnonzero(near == load.argmax())
            sums[empty] = sample[rng.choice(crowd, empty.size)] + 0.01 * rng.standard_normal((empty.size, sample.shape[1]))
        centroids = (sums / np.maximum(np.linalg.norm(sums, axis=1, keepdims=True), 1e-12)).astype(np.float32)
    return centroids


def centroid_graph(centroids: np.ndarray, edges: int) -> np.ndarray:
    """Each centroid's nearest others, and a few far ones as shortcuts (rows x edges)."""
    n = centroids.shape[0]
    edges = min(edges, max(n - 1, 0))
    out = np.zeros((n, edges), dtype=np.int64)
    rng = np.random.default_rng(13)
    for a in range(0, n, 1024):
        s = centroids[a : a + 1024] @ centroids.T
        s[np.arange(s.shape[0]), a + np.arange(s.shape[0])] = -np.inf
        out[a : a + 1024] = np.argpartition(-s, max(edges - 1, 0), axis=1)[:, :edges] if edges else 0
    far = min(3, max(edges - 4, 0))
    if far:
        out[:, -far:] = rng.integers(0, n, (n, far))
    return out


def search_graph(queries: np.ndarray, centroids: np.ndarray, graph: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
    """Best-first walk over the centroid graph for all queries in step: the nearest centroids found (rows x
    beam, nearest first; -1 where fewer) and their cosines."""
    n, m = centroids.shape[0], queries.shape[0]
    beam = min(beam, n)
    seen = np.zeros((m, n), dtype=bool)
    start = np.unique(np.linspace(0, n - 1, min(n, 2 * beam)).astype(np.int64))
    score = queries @ centroids[start].T
    seen[:, start] = True
    best = np.argsort(-score, axis=1, kind="stable")[:, :beam]
    ids, cos = start[best], np.take_along_axis(score, best, axis=1)
    if ids.shape[1] < beam:
        pad = beam - ids.shape[1]
        ids, cos = np.pad(ids, ((0, 0), (0, pad)), constant_values=-1), np.pad(cos, ((0, 0), (0, pad)), constant_values=-np.inf)
    done = np.zeros((m, n + 1), dtype=bool)
    done[:, n] = True
    rows = np.arange(m)
    while graph.shape[1]:
        fresh = ~np.take_along_axis(done, np.where(ids < 0, n, ids), axis=1)
        active = np.flatnonzero(fresh.any(axis=1))
        if not active.size:
            break
        pick = ids[active, fresh[active].argmax(axis=1)]
        done[active, pick] = True
        near = graph[pick]
        sim = np.einsum("ijk,ik->ij", centroids[near], queries[active])
        sim[np.take_along_axis(seen[active], near, axis=1)] = -np.inf
        seen[rows[active][:, None], near] = True
        both_ids, both = np.concatenate([ids[active], near], axis=1), np.concatenate([cos[active], sim], axis=1)
        order = np.argsort(-both, axis=1, kind="stable")[:, :beam]
        cos[active] = np.take_along_axis(both, order, axis=1)
        ids[active] = np.where(np.isfinite(cos[active]), np.take_along_axis(both_ids, order, axis=1), -1)
    return ids, cos


def lists_within(ids: np.ndarray, cos: np.ndarray, ratio: float, most: int, least: int = 1) -> np.ndarray:
    """Which found centroids are within (1 + ratio) of the nearest one's squared distance, at most `most`; the
    nearest `least` in any case."""
    far, nth = 2 - 2 * cos, np.arange(ids.shape[1])[None, :]
    return (ids >= 0) & ((nth < least) | (far <= (1 + ratio) * np.maximum(far[:, :1], 1e-9)) & (nth < most))


def brute_kernel(shared, dim: int, k: int):
    """(key, vector) -> the k most similar rows of the batch for each calibration vector."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, unit = shared.value
        for batch in batches:
            for a in range(0, batch.num_rows, 4096):
                part = batch.slice(a, 4096)
                x = matrix(part.column(1), dim)
                own = part.column(0).to_numpy()
                s = unit @ (x / np.linalg.norm(x, axis=1, keepdims=True)).T
                s[keys[:, None] == own[None, :]] = -np.inf
                top = min(k, own.size)
                near = np.argpartition(-s, top - 1, axis=1)[:, :top]
                row = np.repeat(np.arange(keys.size), top)
                ok = np.isfinite(s[row, near.ravel()])
                yield pa.RecordBatch.from_arrays([pa.array(row[ok]), pa.array(s[row, near.ravel()][ok]), part.column(1).take(pa.array(near.ravel()[ok]))], ["query", "score", "vector"])

    return kernel


def reach(entries: DataFrame, centroids: np.ndarray, graph: np.ndarray, dim: int, k: int) -> tuple[float, int]:
    """(distance ratio, lists at most) that reach REACH of the true neighbours of CALIBRATION vectors each."""
    spark = entries.sparkSession
    rows = entries.orderBy(F.xxhash64(F.lit(5), "key")).limit(CALIBRATION).collect()
    unit = np.array([r["vector"] for r in rows])
    unit = unit / np.linalg.norm(unit, axis=1, keepdims=True)
    shared = spark.sparkContext.broadcast((np.array([r["key"] for r in rows]), unit))
    near = entries.select("key", "vector").mapInArrow(brute_kernel(shared, dim, k), "query long, score double, vector array<double>")
    nth = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score")))
    true = near.withColumn("nth", nth).where(F.col("nth") <= k).select("query", "vector").collect()
    if not true:
        return 0.2, LEAST_LISTS
    x = np.array([r["vector"] for r in true])
    x = (x / np.linalg.norm(x, axis=1, keepdims=True)).astype(np.float32)
    ids, cos = search_graph(x, centroids, graph, BEAM)
    held = lists_within(ids, cos, CLOSE, REPLICAS)
    far = 2 - 2 * (unit.astype(np.float32) @ centroids.T)
    query = np.array([r["query"] for r in true])
    distance = np.where(held, far[query[:, None], np.where(ids < 0, 0, ids)], np.inf).min(axis=1)
    rank = (far[query] < distance[:, None]).sum(axis=1) + 1
    ratio = distance / np.maximum(far.min(axis=1)[query], 1e-9)
    return max(0.2, float(np.quantile(ratio, REACH)) - 1), int(min(centroids.shape[0], max(LEAST_LISTS, math.ceil(np.quantile(rank, REACH)) + 2)))


def matrix(column: pa.Array, dim: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)


def place_kernel(shared, dim: int, ratio: float, most: int, least: int = 1):
    """(key, vec_id, vector) -> (key, vec_id, list, vector) for every list a vector belongs to, or a query looks into."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centroids, graph = shared.value
        for batch in batches:
            for a in range(0, batch.num_rows, 512):
                part = batch.slice(a, 512)
                x = matrix(part.column(2), dim)
                x = (x / np.linalg.norm(x, axis=1, keepdims=True)).astype(np.float32)
                ids, cos = search_graph(x, centroids, graph, max(BEAM, most))
                keep = lists_within(ids, cos, ratio, most, least)
                row, col = np.nonzero(keep)
                at = pa.array(row)
                yield pa.RecordBatch.from_arrays([part.column(0).take(at), part.column(1).take(at), pa.array(ids[row, col]), part.column(2).take(at)], ["key", "vec_id", "list", "vector"])

    return kernel


def first_of(row: np.ndarray, score: np.ndarray, vec_id: np.ndarray, n: int) -> np.ndarray:
    """Numbers of each row's n best entries: by score, ties to the smaller vec_id."""
    order = np.lexsort((vec_id, -score, row))
    sorted_ = row[order]
    return order[np.arange(order.size) - np.searchsorted(sorted_, sorted_) < n]


def best_entries(q: np.ndarray, v: np.ndarray, vec_id: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, row of v, cosine) of the n best of v for each of q. Cosines that count are summed pair by pair, in an
    order that depends on nothing else: equal ones are equal wherever they are computed."""
    q_norm, v_norm = np.sqrt((q * q).sum(axis=1)), np.sqrt((v * v).sum(axis=1))
    rough = (q @ v.T) / (q_norm[:, None] * v_norm[None, :])
    top = min(n, v.shape[0])
    floor = np.partition(rough, v.shape[0] - top, axis=1)[:, v.shape[0] - top]
    row, col = np.nonzero(rough >= floor[:, None] - ROUNDING)
    score = np.empty(row.size)
    for a in range(0, row.size, PAIRS):
        r, c = row[a : a + PAIRS], col[a : a + PAIRS]
        score[a : a + PAIRS] = (q[r] * v[c]).sum(axis=1) / (q_norm[r] * v_norm[c])
    keep = first_of(row, score, vec_id[col], n)
    return row[keep], col[keep], score[keep]


FOUND = "query long, key long, vec_id long, score double"


def compare_kernel(dim: int, k: int):
    """Pieces of lists arrive in order, each with its queries behind its vectors: (piece, is_query, key, smallest
    vec_id, vector). Yields each query's k + 1 nearest entries of the piece, in double precision."""

    def answers(vectors, queries):
        if not vectors or not queries:
            return
        v_keys, v_ids, v = (np.concatenate([x[i] for x in vectors]) for i in range(3))
        for q_keys, q in queries:
            for a in range(0, q_keys.size, 256):
                row, col, score = best_entries(q[a : a + 256], v, v_ids, k + 1)
                yield pa.RecordBatch.from_arrays([pa.array(q_keys[a + row]), pa.array(v_keys[col]), pa.array(v_ids[col]), pa.array(score)], ["query", "key", "vec_id", "score"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, vectors, queries = None, [], []
        for batch in batches:
            if not batch.num_rows:
                continue
            piece, is_query, keys, ids = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(4))
            x = matrix(batch.column(4), dim)
            cuts = np.concatenate([[0], np.flatnonzero((piece[1:] != piece[:-1]) | (is_query[1:] != is_query[:-1])) + 1, [piece.size]])
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                if piece[a] != now:
                    yield from answers(vectors, queries)
                    now, vectors, queries = piece[a], [], []
                if is_query[a]:
                    # queries come last and are answered as they come: none are held
                    yield from answers(vectors, [(keys[a:b], x[a:b])])
                else:
                    vectors.append((keys[a:b], ids[a:b], x[a:b]))

    return kernel


def exact_kernel(shared, dim: int, k: int):
    """(key, vec_id, vector) -> each asked query's k + 1 nearest entries of the task, in double precision."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked, q = shared.value
        held = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        for batch in batches:
            for a in range(0, batch.num_rows, PIECE):
                part = batch.slice(a, PIECE)
                keys, ids = (part.column(i).to_numpy(zero_copy_only=False) for i in range(2))
                row, col, score = best_entries(q, matrix(part.column(2), dim), ids, k + 1)
                both = [np.concatenate(x) for x in zip(held, (row, keys[col], ids[col], score), strict=True)]
                keep = first_of(both[0], both[3], both[2], k + 1)
                held = tuple(x[keep] for x in both)
        yield pa.RecordBatch.from_arrays([pa.array(asked[held[0]]), *map(pa.array, held[1:])], ["query", "key", "vec_id", "score"])

    return kernel


def nearest(vectors: DataFrame, every: int = 50, k: int = 5, list_vectors: int = LIST_VECTORS) -> DataFrame:
    """For each row whose vec_id is divisible by `every`, its k nearest other rows by cosine.

    vectors: vec_id, embedding (array of numbers), any other columns (ignored). Rows whose embedding is
    null, empty, zero or holds a null or non-finite component, whose vec_id is null, or whose length
    differs from the most frequent length, take no part; rows of a repeated vec_id count as separate
    candidates, and a query is asked once per vec_id. Returns query_id, rank (from 1, ties to
    the smaller vec_id), vec_id, score (cosine in double precision on the original vectors). A query
    with fewer candidates returns all of them. Empty table: empty result.

    Equal vectors are one entry of the index with their k + 1 smallest ids, which is all that ties need.
    A query whose lists hold fewer than k candidates is compared with every vector, PASS_QUERIES in a pass.
    Fit on at most SAMPLE distinct vectors (those of the smallest hashes); every vector is listed."""
    spark = vectors.sparkSession
    ship_package(spark)
    mark = stage_mark()
    doubles = F.transform("embedding", lambda x: x.cast("double"))
    usable = vectors.select("vec_id", doubles.alias("vector")).where("vec_id is not null and vector is not null")
    norm = F.aggregate("vector", F.lit(0.0), lambda s, x: s + x * x)
    usable = usable.where((F.size("vector") > 0) & ~F.exists("vector", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & (norm > 0))
    lengths = usable.groupBy(F.size("vector").alias("dim")).count().orderBy(F.desc("count"), "dim").first()
    if lengths is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    dim = lengths["dim"]
    rows = stage(usable.where(F.size("vector") == dim).select("vec_id", "vector", F.xxhash64("vector").alias("key")), "vectors")
    # equal vectors: one entry, with the k + 1 smallest ids
    nth = F.row_number().over(Window.partitionBy("key").orderBy("vec_id"))
    smallest = rows.select("key", "vec_id").withColumn("nth", nth).where(F.col("nth") <= k + 1).select("key", "vec_id")
    entries = stage(rows.groupBy("key").agg(F.min("vec_id").alias("vec_id"), F.first("vector").alias("vector")), "entries")
    count = entries.count()
    sample = np.array([r["vector"] for r in entries.orderBy(F.xxhash64(F.lit(3), "key")).limit(SAMPLE).select("vector").collect()])
    sample = (sample / np.linalg.norm(sample, axis=1, keepdims=True)).astype(np.float32)
    centroids = fit_centroids(sample, min(MOST_CENTROIDS, math.ceil(count / list_vectors)))
    graph = centroid_graph(centroids, EDGES)
    shared = spark.sparkContext.broadcast((centroids, graph))
    prune, most = reach(entries, centroids, graph, dim, k)
    array = "array<double>"
    placed = f"key long, vec_id long, list long, vector {array}"
    listed = entries.mapInArrow(place_kernel(shared, dim, CLOSE, REPLICAS), placed)
    asked = rows.where(F.col("vec_id") % every == 0).select("key").distinct().join(entries, "key").select("key", "vec_id", "vector")
    looked = asked.mapInArrow(place_kernel(shared, dim, prune, most, LEAST_LISTS), placed)
    listed = stage(listed, "lists")
    sizes = listed.groupBy("list").agg(F.ceil(F.count(F.lit(1)) / PIECE).cast("long").alias("pieces"))
    cut = listed.join(sizes, "list").select(F.xxhash64("list", F.pmod(F.xxhash64("key"), "pieces")).alias("piece"), F.lit(False).alias("is_query"), "key", "vec_id", "vector")
    # a query goes to every piece of its lists
    every_piece = F.explode(F.sequence(F.lit(0).cast("long"), F.col("pieces") - 1))
    spread = looked.join(sizes, "list").withColumn("p", every_piece).select(F.xxhash64("list", "p").alias("piece"), F.lit(True).alias("is_query"), "key", "vec_id", "vector")
    met = cut.unionByName(spread).repartition("piece").sortWithinPartitions("piece", "is_query")
    found = met.mapInArrow(compare_kernel(dim, k), FOUND).groupBy("query", "key").agg(F.max("score").alias("score"), F.min("vec_id").alias("least"))
    queries = rows.where(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query_id"), F.col("key").alias("query")).distinct()

    def ranked(found: DataFrame) -> DataFrame:
        # the best k + 1 entries of each query, then their rows: each has a row ahead of all rows left out, and
        # one of these rows at most is the query's own
        best = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "least"))
        top = found.withColumn("nth", best).where(F.col("nth") <= k + 1).select("query", "key", "score")
        candidates = top.join(smallest, "key").select("query", "vec_id", "score")
        pairs = queries.join(candidates, "query").where("query_id <> vec_id")
        rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
        return pairs.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

    first = stage(ranked(found), "nearest")
    have = first.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))
    short = stage(queries.join(have, "query_id", "left").where(F.coalesce("n", F.lit(0)) < k).select("query_id", "query"), "short")
    left = short.select(F.col("query").alias("key")).distinct().join(entries, "key").select("key", "vector").toLocalIterator()
    passes: list[DataFrame] = []
    while block := list(islice(left, PASS_QUERIES)):
        asked_now = spark.sparkContext.broadcast((np.array([r["key"] for r in block]), np.array([r["vector"] for r in block])))
        passes.append(stage(entries.mapInArrow(exact_kernel(asked_now, dim, k), FOUND).withColumnRenamed("vec_id", "least"), "exact"))
    if passes:
        again = ranked(reduce(DataFrame.unionByName, passes)).join(short.select("query_id"), "query_id", "left_semi")
        first = stage(first.join(short.select("query_id"), "query_id", "left_anti").unionByName(again), "all-nearest")
    release(mark, first)
    return first
