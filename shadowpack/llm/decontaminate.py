"""Benchmark decontamination by winnowing.

Both sides keep the smallest gram hash of every `window - gram + 1` consecutive grams, so a shared span
of `window` words always shares a kept hash at the same place. Test fingerprints and windows are taken
in blocks of a checked size, each block broadcast to one pass over the texts; a corpus text is looked at
more closely only around fingerprints that occur in the block, where windows are compared in full."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship_package, stage, unique_ids
from .kernels import BYTE_BASE, POS_BITS, WORD_BASE, byte_values, chunks, column_bytes, lower_table, prefix_sums, range_hash, ranges, sliding_min, split_words, word_hashes
from .substring_dedup import with_doc_ids

WINDOW_WORDS, GRAM_WORDS = 13, 5
#: UTF-8 bytes of benchmark text that one broadcast block may hold.
BLOCK_BYTES = 16 << 20


def kept_grams(symbols: np.ndarray, bounds: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """Places (among all symbols) and hashes of the grams that winnowing keeps in each row."""
    n = np.diff(bounds)
    windows = np.maximum(n - window + 1, 0)
    if not windows.any():
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    sums = prefix_sums(symbols, WORD_BASE)
    at = np.arange(symbols.size - gram + 1)
    grams = range_hash(sums, at, at + gram, WORD_BASE)
    bits = np.uint64(max(POS_BITS, int(symbols.size).bit_length()))
    key = ((grams >> bits) << bits) | at.astype(np.uint64)
    pick = sliding_min(key, window - gram + 1)[ranges(bounds[:-1], windows)]
    pick = np.unique((pick & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64))
    return pick, grams[pick]


class Block:
    """Fingerprints and windows of some benchmark items.

    lengths: window length -> (sorted window hashes, each one's items as a slice of `items`)."""

    def __init__(self, item_ids: list[str], texts: list[str | None], window: int, gram: int):
        self.item_ids, self.window, self.gram = item_ids, window, gram
        data, offsets = column_bytes(pa.array(texts, pa.string()))
        lowered = lower_table()[data]
        starts, ends, bounds = split_words(lowered, offsets, "alnum")
        words = word_hashes(lowered, starts, ends)
        self.fingerprints = np.unique(kept_grams(words, bounds, window, gram)[1])
        n = np.diff(bounds)
        sums = prefix_sums(words, WORD_BASE)
        self.lengths: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for length in np.unique(np.minimum(n[n > 0], window)).tolist():
            rows = np.flatnonzero((n >= window) if length == window else (n == length))
            count = n[rows] - length + 1
            at, row = ranges(bounds[rows], count), np.repeat(rows, count)
            hashes = range_hash(sums, at, at + length, WORD_BASE)
            order = np.lexsort((row, hashes))
            hashes, row = hashes[order], row[order]
            first = np.ones(hashes.size, dtype=bool)
            first[1:] = (hashes[1:] != hashes[:-1]) | (row[1:] != row[:-1])
            hashes, row = hashes[first], row[first]
            keys, start = np.unique(hashes, return_index=True)
            self.lengths[length] = (keys, np.append(start, row.size), row)

    def hits(self, data: np.ndarray, offsets: np.ndarray):
        """Words' bounds, which words are hit, and (row, item) pairs of occurring windows."""
        lowered = lower_table()[data]
        starts, ends, bounds = split_words(lowered, offsets, "alnum")
        hit = np.zeros(starts.size + 1, dtype=np.int64)
        rows, items = [], []
        if starts.size:
            words = range_hash(prefix_sums(byte_values()[lowered], BYTE_BASE), starts, ends, BYTE_BASE)
            sums = prefix_sums(words, WORD_BASE)
            for length, (keys, item_start, item) in self.lengths.items():
                if length == self.window:
                    places, grams = kept_grams(words, bounds, self.window, self.gram)
                    places = places[member(grams, self.fingerprints)]
                    reach = self.window - self.gram
                    # every window that holds the matching gram is looked at
                    near = ranges(places - reach, np.full(places.size, reach + 1))
                    at = np.unique(near[near >= 0])
                else:
                    at = np.arange(starts.size)
                row = np.searchsorted(bounds, at, side="right") - 1
                inside = at + length <= bounds[np.minimum(row + 1, bounds.size - 1)]
                at, row = at[inside], row[inside]
                hashes = range_hash(sums, at, at + length, WORD_BASE)
                found = member(hashes, keys)
                at, row, hashes = at[found], row[found], hashes[found]
                np.add.at(hit, at, 1)
                np.add.at(hit, at + length, -1)
                k = np.searchsorted(keys, hashes)
                count = item_start[k + 1] - item_start[k]
                rows.append(np.repeat(row, count))
                items.append(item[ranges(item_start[k], count)])
        return bounds, np.cumsum(hit[:-1]) > 0, (np.concatenate(rows) if rows else np.zeros(0, np.int64)), (np.concatenate(items) if items else np.zeros(0, np.int64))


def member(values: np.ndarray, ordered: np.ndarray) -> np.ndarray:
    if not ordered.size:
        return np.zeros(values.size, dtype=bool)
    return ordered[np.minimum(np.searchsorted(ordered, values), ordered.size - 1)] == values


def item_lists(rows: np.ndarray, items: np.ndarray, names: list[str], n: int) -> list[list[str]]:
    out: list[list[str]] = [[] for _ in range(n)]
    if rows.size:
        pairs = np.unique(rows * np.int64(len(names)) + items)
        for p in pairs.tolist():
            out[p // len(names)].append(names[p % len(names)])
    return out


def _answer(uid, n_words, n_hit, found, share: int) -> list[pa.Array]:
    lists = [sorted(set(x)) for x in found]
    hit = pa.array(n_hit)
    return [uid, pa.array(n_words), hit, pa.array([len(x) for x in lists], pa.int64()), pa.array([hashlib.sha256(",".join(x).encode()).hexdigest() for x in lists]), pa.array((n_hit > 0) & (share * n_hit >= n_words)), pa.array(lists, pa.list_(pa.string()))]


NAMES = ["_uid", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "items"]
SCHEMA = "_uid long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, items array<string>"


def single_block_kernel(shared, share: int):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block: Block = shared.value
        for batch in batches:
            data, offsets = column_bytes(batch.column(1))
            for a, b in chunks(offsets):
                bounds, hit, rows, items = block.hits(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                total = np.concatenate([[0], np.cumsum(hit)])
                yield pa.RecordBatch.from_arrays(_answer(batch.column(0).slice(a, b - a), np.diff(bounds), np.diff(total[bounds]), item_lists(rows, items, block.item_ids, b - a), share), NAMES)

    return kernel


def partial_kernel(shared):
    """(uid, number of words, hit words as bytes 0/1 or null, items) of the rows of one block."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block: Block = shared.value
        for batch in batches:
            data, offsets = column_bytes(batch.column(1))
            for a, b in chunks(offsets):
                bounds, hit, rows, items = block.hits(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                lists = item_lists(rows, items, block.item_ids, b - a)
                raw = hit.astype(np.uint8)
                masks = [raw[s:e].tobytes() if x else None for s, e, x in zip(bounds[:-1].tolist(), bounds[1:].tolist(), lists, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(np.diff(bounds)), pa.array(masks, pa.binary()), pa.array(lists, pa.list_(pa.string()))], ["_uid", "n_words", "mask", "items"])

    return kernel


def merge_kernel(share: int):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n_words = batch.column(1).to_numpy()
            n_hit = np.zeros(n_words.size, dtype=np.int64)
            for i, masks in enumerate(batch.column(2).to_pylist()):
                if masks:
                    n_hit[i] = int(np.any([np.frombuffer(m, dtype=np.uint8) for m in masks], axis=0).sum())
            yield pa.RecordBatch.from_arrays(_answer(batch.column(0), n_words, n_hit, [[x for y in z for x in y] for z in batch.column(3).to_pylist()], share), NAMES)

    return kernel


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW_WORDS, gram: int = GRAM_WORDS, share: int = 20, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Words of documents inside any occurrence of a benchmark window. Words: maximal runs of digits,
    letters a-z (A-Z lower-cased) and non-ASCII characters. A window: `window` consecutive words of an
    item; an item of fewer words, but not none, is one window.

    docs: doc_id, text; benchmark: item_id, text; other columns are ignored. Returns doc_id, n_words,
    n_hit, n_items (items with occurring windows), items_sha256 (of the item_ids, sorted as strings and
    comma-joined), contaminated (n_hit > 0 and share * n_hit >= n_words), items (array). One row per row
    of docs. Null texts have no words; null item_ids are left out; items of one id count as one.
    Empty benchmark: nothing is hit. Rows with a null or repeated doc_id count as documents of their
    own. The benchmark is broadcast in blocks of at most block_bytes of text (or one item, if longer):
    one pass over docs for each block."""
    spark = docs.sparkSession
    ship_package(spark)
    ids = unique_ids(docs.select("doc_id", "text"))
    texts = ids.select("_uid", "text")
    items = benchmark.where(F.col("item_id").isNotNull()).select(F.col("item_id").cast("string").alias("item"), "text")
    size = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    if size <= block_bytes:
        rows = items.collect()
        shared = spark.sparkContext.broadcast(Block([r["item"] for r in rows], [r["text"] for r in rows], window, gram))
        return with_doc_ids(texts.mapInArrow(single_block_kernel(shared, share), SCHEMA), ids)
    parts = []
    for rows in item_blocks(items, block_bytes):
        shared = spark.sparkContext.broadcast(Block([r["item"] for r in rows], [r["text"] for r in rows], window, gram))
        parts.append(stage(texts.mapInArrow(partial_kernel(shared), "_uid long, n_words long, mask binary, items array<string>"), "hits"))
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    merged = whole.groupBy("_uid").agg(F.max("n_words").alias("n_words"), F.collect_list("mask").alias("masks"), F.collect_list("items").alias("items"))
    return with_doc_ids(merged.mapInArrow(merge_kernel(share), SCHEMA), ids)


def item_blocks(items: DataFrame, block_bytes: int):
    """Lists of items of at most block_bytes each, streamed to the driver one partition at a time."""
    held, size = [], 0
    for row in items.toLocalIterator():
        more = len((row["text"] or "").encode())
        if held and size + more > block_bytes:
            yield held
            held, size = [], 0
        held.append(row)
        size += more
    if held:
        yield held
