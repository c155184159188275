"""Substring dedup by relative Lempel-Ziv factoring of documents against indexed reference blocks."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  (pa.compute)
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship_package, unique_ids
from .kernels import WORD_BASE, chunks, column_bytes, prefix_sums, range_hash, ranges, split_words, word_hashes
from .repeats import Repeat, covered, repeated_windows, span_arrays

WINDOW_WORDS = 35
GRAM_WORDS = 8


def factor(symbols: np.ndarray, bounds: np.ndarray, cell: np.ndarray, copies: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Greedy factors of at least `length` symbols of each context against the reference: all contexts
    of its cell (and itself where it stands for several copies).

    The reference is indexed by the hash of every window. All contexts are parsed in step: where the
    window at the current place occurs elsewhere, the factor is extended symbol by symbol along that
    source; the next place is the first window that is not wholly inside the factor, so windows that
    reach over a factor's end are looked up one by one. Returns context, first window, windows."""
    n = np.diff(bounds)
    windows = np.maximum(n - length + 1, 0)
    start = ranges(bounds[:-1], windows)
    lane = np.repeat(np.arange(n.size), windows)
    sums = prefix_sums(symbols, WORD_BASE)
    keys = range_hash(sums, start, start + length, WORD_BASE) ^ (cell[lane].view(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    order = np.argsort(keys, kind="stable")
    same = keys[order][1:] == keys[order][:-1]
    # a source for each window: a neighbour of equal key in index order, or itself if copied
    source = np.full(start.size, -1, dtype=np.int64)
    source[order[1:][same]] = start[order[:-1][same]]
    lonely = np.zeros(start.size, dtype=bool)
    lonely[order[:-1][same]] = True
    back = lonely & (source < 0)
    follow = np.empty(start.size, dtype=np.int64)
    follow[order[:-1]] = order[1:]
    source[back] = start[follow[back]]
    own = (source < 0) & (copies[lane] > 1)
    source[own] = start[own]
    base = np.concatenate([[0], np.cumsum(windows)])[:-1]
    place = np.zeros(n.size, dtype=np.int64)
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    active = np.flatnonzero(windows > 0)
    padded = np.append(symbols, np.uint64(0))
    while active.size:
        src = source[base[active] + place[active]]
        hit = active[src >= 0]
        place[active[src < 0]] += 1
        if hit.size:
            src = src[src >= 0]
            at = bounds[hit] + place[hit]
            size = np.full(hit.size, length, dtype=np.int64)
            grow = np.arange(hit.size)
            while grow.size:
                end = at[grow] + size[grow]
                other = np.minimum(src[grow] + size[grow], symbols.size)
                ok = (end < bounds[hit[grow] + 1]) & (padded[other] == padded[np.minimum(end, symbols.size)])
                # a source must not run over its own context's end
                ok &= np.searchsorted(bounds, src[grow], side="right") == np.searchsorted(bounds, other, side="right")
                grow = grow[ok]
                size[grow] += 1
            out.append((hit, place[hit].copy(), size - length + 1))
            place[hit] += size - length + 1
        active = active[place[active] < windows[active]]
    if not out:
        z = np.zeros(0, np.int64)
        return z, z, z
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def word_resolver(length: int):
    def resolve(data, offsets, cell, side, copies):
        starts, ends, bounds = split_words(data, offsets, "space")
        return factor(word_hashes(data, starts, ends), bounds, cell, copies, length)

    return resolve


def cut_kernel(spec: Repeat, with_text: bool):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            uid, spans = batch.column(0), batch.column(2)
            data, offsets = column_bytes(batch.column(1))
            for a, b in chunks(offsets):
                text = data[offsets[a] : offsets[b]]
                starts, ends, bounds = split_words(text, offsets[a : b + 1] - offsets[a], "space")
                row, first, count = span_arrays(spans, a, b)
                gone = covered(bounds, row, first, count, spec.length)
                left = np.flatnonzero(~gone)
                kept_bounds = np.searchsorted(left, bounds)
                n_words = np.diff(bounds)
                n_kept = np.diff(kept_bounds)
                # each kept word with one byte behind it, a space, but for the last of a document
                joined = np.append(text, np.uint8(0x20))
                last = np.zeros(left.size, dtype=bool)
                last[kept_bounds[1:][n_kept > 0] - 1] = True
                joined[ends[left[~last]]] = 0x20
                width = ends[left] - starts[left] + ~last
                body = joined[ranges(starts[left], width)]
                size = np.concatenate([[0], np.cumsum(width)])[kept_bounds]
                raw = body.tobytes()
                bound = size.tolist()
                pieces = [raw[s:e] for s, e in zip(bound[:-1], bound[1:], strict=True)]
                columns = [uid.slice(a, b - a), pa.array(n_words), pa.array(n_words - n_kept), pa.array([hashlib.sha256(p).hexdigest() for p in pieces])]
                names = ["_uid", "n_words", "n_removed", "kept_sha256"]
                if with_text:
                    columns.append(pa.array([p.decode() for p in pieces], pa.string()))
                    names.append("kept_text")
                yield pa.RecordBatch.from_arrays(columns, names)

    return kernel


def substring_dedup(docs: DataFrame, window_words: int = WINDOW_WORDS, with_text: bool = True) -> DataFrame:
    """Removes every word covered by a window of `window_words` consecutive words of one document whose
    word sequence also starts anywhere else, the same document included. Words are maximal runs of
    characters other than ASCII white space. Windows are judged on the input.

    docs: doc_id, text, any other columns (ignored). Returns doc_id, n_words, n_removed, kept_sha256 and,
    if asked, kept_text (kept words joined by one space). One row per input row. Null text: no words.
    Rows with a null or repeated doc_id count as documents of their own. Empty table: empty result.
    A document whose words are all removed has the empty text."""
    ship_package(docs.sparkSession)
    ids = unique_ids(docs.select("doc_id", "text"))
    spec = Repeat("words", window_words, max(1, min(GRAM_WORDS, window_words // 2)))
    dealt, spans = repeated_windows(ids, spec, word_resolver(window_words))
    schema = "_uid long, n_words long, n_removed long, kept_sha256 string" + ", kept_text string" * with_text
    out = dealt.join(spans.hint("shuffle_hash"), "_uid", "left").select("_uid", "text", "spans").mapInArrow(cut_kernel(spec, with_text), schema)
    return with_doc_ids(out, ids)


def with_doc_ids(out: DataFrame, ids: DataFrame) -> DataFrame:
    """out with doc_id in place of _uid: a cast where ids were unique, a join with the numbered rows else."""
    from .common import is_numbered

    if not is_numbered(ids):
        return out.withColumnRenamed("_uid", "doc_id")
    return out.join(ids.select("_uid", "doc_id"), "_uid").select("doc_id", *[c for c in out.columns if c != "_uid"])
