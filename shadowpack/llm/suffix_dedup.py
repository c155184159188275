"""Suffix-array dedup: bytes covered by long strings that start more than once."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  (pa.compute)
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship_package, unique_ids
from .kernels import chunks, column_bytes, kasai, ranges, suffix_order
from .repeats import Repeat, covered, repeated_windows, span_arrays
from .substring_dedup import with_doc_ids

LENGTH_BYTES = 400
GRAM_BYTES = 24


class Shard:
    """Suffix array of contexts, each closed by an end mark; windows are its first places."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, length: int):
        size = np.diff(offsets)
        self.start = offsets[:-1] + np.arange(size.size)
        self.windows = np.maximum(size - length + 1, 0)
        self.length = length
        self.symbols = np.zeros(int(offsets[-1]) + size.size, dtype=np.int16)
        self.symbols[ranges(self.start, size)] = data.astype(np.int16) + 1
        self.live = ranges(self.start, self.windows)
        self.order, self.rank = suffix_order(self.symbols)

    def repeated_inside(self) -> np.ndarray:
        """Per live place: whether its window also starts at a neighbour in suffix order."""
        common = kasai(self.symbols, self.order, self.rank, self.start, self.windows, self.length)
        before = common >= self.length
        # places that hold a shorter suffix than a window can't stand between two equal windows,
        # but an end mark is no symbol of a window: both places must be live
        alive = np.zeros(self.symbols.size, dtype=bool)
        alive[self.live] = True
        linked = before[self.order] & alive[self.order]
        linked[1:] &= alive[self.order[:-1]]
        linked[:1] = False
        flags = np.zeros(self.symbols.size, dtype=bool)
        flags[self.order[linked]] = True
        flags[self.order[:-1][linked[1:]]] = True
        return flags[self.live]

    def found_in(self, other: Shard) -> np.ndarray:
        """Per live place: whether its window starts in the other shard, by binary search in its order."""
        a, b, n = self.symbols, other.symbols, other.symbols.size
        low = np.zeros(self.live.size, dtype=np.int64)
        high = np.full(self.live.size, n, dtype=np.int64)
        found = np.zeros(self.live.size, dtype=bool)
        while True:
            open_ = np.flatnonzero(low < high)
            if not open_.size:
                break
            middle = (low[open_] + high[open_]) // 2
            common, less = compare(b, other.order[middle], a, self.live[open_], self.length)
            found[open_] |= common >= self.length
            low[open_[less]] = middle[less] + 1
            high[open_[~less]] = middle[~less]
        return found


def compare(b: np.ndarray, q: np.ndarray, a: np.ndarray, p: np.ndarray, cap: int) -> tuple[np.ndarray, np.ndarray]:
    """Common prefix (up to cap) of b[q:] and a[p:], and whether b[q:] sorts before a[p:]."""
    common = np.zeros(p.size, dtype=np.int64)
    less = np.zeros(p.size, dtype=bool)
    go = np.arange(p.size)
    end_b = b.size - 1
    while go.size:
        x, y = b[np.minimum(q[go] + common[go], end_b)], a[p[go] + common[go]]
        same = x == y
        stop = go[~same]
        less[stop] = x[~same] < y[~same]
        go = go[same]
        common[go] += 1
        go = go[common[go] < cap]
    return common, less


def suffix_resolver(length: int):
    def resolve(data, offsets, cell, side, copies):
        size = np.diff(offsets)
        windows = np.maximum(size - length + 1, 0)
        lane = np.repeat(np.arange(size.size), windows)
        place = ranges(np.zeros(size.size, np.int64), windows)
        two_sided = np.isin(cell, cell[side != 0])
        flags = np.zeros(lane.size, dtype=bool)
        parts = [np.flatnonzero(~two_sided)]
        for c in np.unique(cell[two_sided]):
            parts += [np.flatnonzero((cell == c) & (side == s)) for s in (1, -1)]
        shards = []
        first_window = np.concatenate([[0], np.cumsum(windows)])
        for part in parts:
            if not part.size:
                shards.append(None)
                continue
            bytes_ = data[ranges(offsets[part], size[part])]
            shard = Shard(bytes_, np.concatenate([[0], np.cumsum(size[part])]), length)
            mine = ranges(first_window[part], windows[part])
            if not shards:
                flags[mine] |= shard.repeated_inside()
            shards.append((shard, mine))
        for k in range(1, len(shards), 2):
            one, two = shards[k], shards[k + 1]
            if one and two:
                flags[one[1]] |= one[0].found_in(two[0])
                flags[two[1]] |= two[0].found_in(one[0])
        flags |= copies[lane] > 1
        hit = np.flatnonzero(flags)
        if not hit.size:
            z = np.zeros(0, np.int64)
            return z, z, z
        new = np.ones(hit.size, dtype=bool)
        new[1:] = (hit[1:] != hit[:-1] + 1) | (lane[hit[1:]] != lane[hit[:-1]])
        head = np.flatnonzero(new)
        return lane[hit[head]], place[hit[head]], np.diff(np.append(head, hit.size))

    return resolve


def cut_kernel(spec: Repeat, with_text: bool):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            uid, spans = batch.column(0), batch.column(2)
            data, offsets = column_bytes(batch.column(1))
            for a, b in chunks(offsets):
                text = data[offsets[a] : offsets[b]]
                bounds = offsets[a : b + 1] - offsets[a]
                row, first, count = span_arrays(spans, a, b)
                gone = covered(bounds, row, first, count, spec.length)
                removed = np.concatenate([[0], np.cumsum(gone)])
                opens = gone.copy()
                opens[1:] &= ~gone[:-1] | np.isin(np.arange(1, gone.size), bounds)
                spans_before = np.concatenate([[0], np.cumsum(opens)])
                kept = text[~gone].tobytes()
                at = (bounds - removed[bounds]).tolist()
                pieces = [kept[s:e] for s, e in zip(at[:-1], at[1:], strict=True)]
                columns = [uid.slice(a, b - a), pa.array(np.diff(bounds)), pa.array(np.diff(removed[bounds])), pa.array(np.diff(spans_before[bounds])), pa.array([hashlib.sha256(p).hexdigest() for p in pieces])]
                names = ["_uid", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
                if with_text:
                    columns.append(pa.array(pieces, pa.binary()))
                    names.append("kept_bytes")
                yield pa.RecordBatch.from_arrays(columns, names)

    return kernel


def suffix_dedup(docs: DataFrame, length_bytes: int = LENGTH_BYTES, with_text: bool = True) -> DataFrame:
    """Removes every UTF-8 byte covered by a string of `length_bytes` bytes that also starts anywhere else
    in the corpus, the same document included; matches never cross documents, strings are judged on
    the input.

    docs: doc_id, text, any other columns (ignored). Returns doc_id, n_bytes, n_removed, n_spans (maximal
    removed runs), kept_sha256 and, if asked, kept_bytes (binary: a cut may fall inside a character).
    One row per input row. Null or empty text: no bytes. Rows with a null or repeated doc_id count as
    documents of their own. Empty table: empty result."""
    ship_package(docs.sparkSession)
    ids = unique_ids(docs.select("doc_id", "text"))
    spec = Repeat("bytes", length_bytes, max(1, min(GRAM_BYTES, length_bytes // 2)))
    dealt, spans = repeated_windows(ids, spec, suffix_resolver(length_bytes))
    schema = "_uid long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept_bytes binary" * with_text
    out = dealt.join(spans.hint("shuffle_hash"), "_uid", "left").select("_uid", "text", "spans").mapInArrow(cut_kernel(spec, with_text), schema)
    return with_doc_ids(out, ids)
