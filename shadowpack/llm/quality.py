"""Quality classifier by nearest-neighbour voting in a latent-semantic space."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship_package, unique_ids
from .kernels import column_bytes, lower_table, split_words, word_hashes
from .substring_dedup import with_doc_ids

#: Dimensions of the hashed terms, of the latent space; neighbours that vote; labelled rows at most.
TERMS, LATENT, NEIGHBOURS, LABELLED = 4096, 48, 15, 3000
THRESHOLD, FOLDS = 0.3, 5
#: Words back at which a repetition is a term.
LAGS = (1, 2, 3, 5, 8)
ROWS_AT_ONCE = 256


def character_classes() -> np.ndarray:
    """Letters of any script are one class, capitals another, digits a third; every other ASCII character
    is a class of its own. Style shows in these, whatever the language."""
    t = np.zeros(256, dtype=np.int64)
    t[0x61:0x7B] = t[0x80:] = 1
    t[0x41:0x5B] = 2
    t[0x30:0x3A] = 3
    other = [c for c in range(128) if t[c] == 0]
    t[other] = 4 + np.arange(len(other))
    return t


def term_counts(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows x TERMS counts of trigrams of character classes and of words that repeat one shortly before,
    and each row's number of places."""
    n = offsets.size - 1
    out = np.zeros((n, TERMS), dtype=np.float32)
    size = np.maximum(np.diff(offsets), 1)
    if data.size > 2:
        c = character_classes()[data]
        gram = ((c[:-2] * 128 + c[1:-1]) * 128 + c[2:]) * 0x9E3779B1
        bucket = len(LAGS) + (gram >> 7) % (TERMS - len(LAGS))
        row = np.repeat(np.arange(n), np.diff(offsets))[:-2]
        inside = np.arange(row.size) + 3 <= offsets[row + 1]
        out += np.bincount((row * TERMS + bucket)[inside], minlength=n * TERMS).reshape(n, TERMS)
    lowered = lower_table()[data]
    starts, ends, bounds = split_words(lowered, offsets, "space")
    if starts.size:
        words, row = word_hashes(lowered, starts, ends), np.repeat(np.arange(n), np.diff(bounds))
        for k, lag in enumerate(LAGS):
            if starts.size > lag:
                again = (words[lag:] == words[:-lag]) & (row[lag:] == row[:-lag])
                # a repetition weighs as much as the bytes of an average word
                out[:, k] = np.bincount(row[lag:][again], minlength=n) * 6
    return out, size.astype(np.float32)


def weighted(counts: np.ndarray, size: np.ndarray, idf: np.ndarray) -> np.ndarray:
    x = np.log1p(counts * (1000.0 / size[:, None]), dtype=np.float32) * idf
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)


def row_blocks(offsets: np.ndarray, limit: int = 1 << 20):
    a, n = 0, offsets.size - 1
    while a < n:
        b = min(max(int(np.searchsorted(offsets, offsets[a] + limit, side="right")) - 1, a + 1), a + ROWS_AT_ONCE, n)
        yield a, b
        a = b


def frequency_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Documents that hold each term, counted within the task."""
    df, rows = np.zeros(TERMS, dtype=np.int64), 0
    for batch in batches:
        data, offsets = column_bytes(batch.column(0))
        for a, b in row_blocks(offsets):
            counts, _ = term_counts(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
            df += (counts > 0).sum(axis=0)
            rows += b - a
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array(np.append(np.arange(TERMS), -1)), pa.array(np.append(df, rows))], ["term", "n"])


def count_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        data, offsets = column_bytes(batch.column(0))
        for a, b in row_blocks(offsets):
            counts, size = term_counts(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
            terms = [np.flatnonzero(x).astype(np.int32) for x in counts]
            yield pa.RecordBatch.from_arrays([batch.column(1).slice(a, b - a), pa.array(size.astype(np.float64)), pa.array(terms, pa.list_(pa.int32())), pa.array([x[t] for x, t in zip(counts, terms, strict=True)], pa.list_(pa.float32()))], ["quality", "size", "terms", "counts"])


def latent_axes(x: np.ndarray, rank: int, rounds: int = 6) -> np.ndarray:
    """The leading right singular vectors of x (terms x rank), by subspace iteration from a fixed start."""
    rank = min(rank, *x.shape)
    q = np.random.default_rng(7).standard_normal((x.shape[1], rank)).astype(np.float32)
    for _ in range(rounds):
        q, _ = np.linalg.qr(x.T @ (x @ q))
    return q.astype(np.float32)


def vote(latent: np.ndarray, references: np.ndarray, labels: np.ndarray, prior: float, neighbours: int) -> np.ndarray:
    """Share of label 1 among the nearest references, weighted by similarity; exact blocked products."""
    norm = np.linalg.norm(latent, axis=1, keepdims=True)
    similarity = (latent / np.maximum(norm, 1e-12)) @ references.T
    k = min(neighbours, references.shape[0])
    near = np.argpartition(-similarity, k - 1, axis=1)[:, :k]
    weight = np.maximum(np.take_along_axis(similarity, near, axis=1), 0).astype(np.float64) ** 8
    total = weight.sum(axis=1)
    score = (weight * labels[near]).sum(axis=1) / np.maximum(total, 1e-12)
    return np.where((total > 1e-9) & (norm[:, 0] > 1e-9), np.clip(score, 0, 1), prior)


def score_kernel(shared, neighbours: int):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        idf, axes, references, labels, prior = shared.value
        for batch in batches:
            data, offsets = column_bytes(batch.column(1))
            for a, b in row_blocks(offsets):
                if references.shape[0]:
                    counts, size = term_counts(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                    score = vote(weighted(counts, size, idf) @ axes, references, labels, prior, neighbours)
                else:
                    score = np.full(b - a, prior)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(score)], ["_uid", "score"])

    return kernel


def held_out(id_col: str = "doc_id"):
    """Rows kept out of training: crc32 of the id as text, modulo FOLDS, is 0 (a null id: not held out)."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % FOLDS == 0, F.lit(False))


def quality_scores(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, neighbours: int = NEIGHBOURS, labelled: int = LABELLED) -> DataFrame:
    """Scores every text: similarity-weighted share of label 1 among the nearest labelled texts.

    Terms are trigrams of character classes and short-range word repetitions, hashed; document frequencies
    are counted over all documents. At most `labelled` labelled rows (a documented bound: those with
    the smallest id hashes, outside the held-out fold) give the latent axes (singular vectors of their
    TF-IDF matrix) and are the voters; both are broadcast (bounded by labelled * LATENT and TERMS *
    LATENT numbers). The text is the only input of a score.

    docs: doc_id, text; labels: doc_id, quality; other columns are ignored. Returns doc_id, held_out, score
    (0..1), predicted (1 if score >= threshold). One row per row of docs. Null or empty texts get the
    share of label 1 among the voters; without any usable label every score is 0.5. Null labels are
    left out, several labels of one id are averaged. Null or repeated doc_ids: one row each. Empty
    table: empty result."""
    spark = docs.sparkSession
    ship_package(spark)
    ids = unique_ids(docs.select("doc_id", "text"))
    texts = ids.select("_uid", "text")
    counted = texts.select("text").mapInArrow(frequency_kernel, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()
    df, total = np.zeros(TERMS), 0
    for r in counted:
        if r["term"] >= 0:
            df[r["term"]] = r["n"]
        else:
            total = r["n"]
    idf = (np.log((total + 1) / (df + 1)) + 0.05).astype(np.float32)
    marked = labels.where("quality is not null and doc_id is not null").groupBy("doc_id").agg(F.avg("quality").alias("quality"))
    chosen = marked.where(~held_out()).orderBy(F.xxhash64("doc_id"), "doc_id").limit(labelled)
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("text", "quality").mapInArrow(count_kernel, "quality double, size double, terms array<int>, counts array<float>").collect()
    model = fit(sample, idf)
    shared = spark.sparkContext.broadcast(model)
    scored = texts.mapInArrow(score_kernel(shared, neighbours), "_uid long, score double")
    out = with_doc_ids(scored, ids)
    return out.select("doc_id", held_out().alias("held_out"), "score", F.when(F.col("score") >= threshold, 1).otherwise(0).cast("int").alias("predicted"))


def fit(sample: list, idf: np.ndarray) -> tuple:
    """(idf, axes, unit reference vectors, their labels, share of label 1) from the labelled sample."""
    labels = np.array([r["quality"] for r in sample], dtype=np.float64)
    counts = np.zeros((len(sample), TERMS), dtype=np.float32)
    for i, r in enumerate(sample):
        counts[i, r["terms"]] = r["counts"]
    if not len(sample):
        return idf, np.zeros((TERMS, 0), np.float32), np.zeros((0, 0), np.float32), labels, 0.5
    x = weighted(counts, np.array([r["size"] for r in sample], dtype=np.float32), idf)
    axes = latent_axes(x, LATENT)
    latent = x @ axes
    order = np.lexsort((*latent.T[:3], labels))  # a fixed order, whatever order the rows came in
    latent, labels = latent[order], labels[order]
    references = latent / np.maximum(np.linalg.norm(latent, axis=1, keepdims=True), 1e-12)
    return idf, axes, references.astype(np.float32), labels, float(labels.mean())
