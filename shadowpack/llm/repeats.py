"""Windows of a fixed number of symbols that start more than once in a corpus, exactly and whole.

Plan, in terms of rows that move:

1. Every document's windows are grouped into runs by winnowing (`kernels.winnowed_runs`): the gram
   that stands for a window depends on its content alone, so equal windows always share it. One row
   (gram hash, digest of the run's content) per run: about two rows per (length - gram) symbols.
2. Gram hashes that occur once are dropped by a counted semi join: no window there can repeat.
3. Runs of equal content are counted and represented by one of them (pre-aggregation: thousands of
   copies become one context). Two contexts of a gram can only share a window if they share the half window
   to the left or to the right of the gram: a context that shares neither half with another is
   answered by its own copies. Texts of the others are cut out of their documents.
4. Contexts of one gram hash meet in one cell. A resolver (suffix arrays, or factoring against a
   reference) says which of their windows occur again. Grams with many different contexts are split
   over a grid of cells, so that a cell stays bounded and every two contexts still meet.
5. Answers are joined back to all runs and gathered per document.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  (pa.compute)
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship_package, stage, unstage
from .kernels import (
    BYTE_BASE,
    WORD_BASE,
    byte_values,
    chunks,
    column_bytes,
    split_words,
    winnowed_runs,
    word_hashes,
)

#: Different contexts of one gram hash that a cell may hold from one side.
CELL_CONTEXTS = 1500
#: Bytes of context text that a resolver takes at a time (whole cells, so a cell may exceed it).
BLOCK_BYTES = 1 << 20


@dataclass(frozen=True)
class Repeat:
    """unit: 'words' (runs of anything but ASCII white space) or 'bytes'; windows of `length` units;
    `gram` units represent a window."""

    unit: str
    length: int
    gram: int

    def symbols(self, data: np.ndarray, offsets: np.ndarray):
        """Symbol hashes, row bounds among them, and the byte place of each symbol's start and end."""
        if self.unit == "bytes":
            at = np.arange(data.size)
            return byte_values()[data], offsets, at, at + 1
        starts, ends, bounds = split_words(data, offsets, "space")
        return word_hashes(data, starts, ends), bounds, starts, ends

    def runs(self, data: np.ndarray, offsets: np.ndarray):
        symbols, bounds, starts, ends = self.symbols(data, offsets)
        return winnowed_runs(symbols, bounds, self.length, self.gram, BYTE_BASE if self.unit == "bytes" else WORD_BASE), bounds, starts, ends


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64))


def occurrence_kernel(spec: Repeat) -> Callable:
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            uid = batch.column(0).to_numpy(zero_copy_only=False)
            data, offsets = column_bytes(batch.column(1))
            for a, b in chunks(offsets):
                runs, *_ = spec.runs(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                if runs.row.size:
                    # a document's runs of equal content are one row, however often they come back
                    order = np.lexsort((runs.first, runs.anchor, runs.digest, runs.row))
                    row, digest, anchor = runs.row[order], runs.digest[order], runs.anchor[order]
                    new = np.ones(order.size, dtype=bool)
                    new[1:] = (row[1:] != row[:-1]) | (digest[1:] != digest[:-1]) | (anchor[1:] != anchor[:-1])
                    head = np.flatnonzero(new)
                    firsts = pa.ListArray.from_arrays(pa.array(np.append(head, order.size).astype(np.int32)), pa.array(runs.first[order]))
                    yield pa.RecordBatch.from_arrays([pa.array(uid[a + row[head]]), firsts, _signed(anchor[head]), _signed(digest[head]), pa.array(runs.count[order][head]), pa.array(runs.left[order][head]), pa.array(runs.right[order][head])], ["_uid", "firsts", "anchor", "digest", "n", "left", "right"])

    return kernel


def context_kernel(spec: Repeat) -> Callable:
    """Cuts the wanted contexts out of the documents that hold them."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = column_bytes(batch.column(0))
            wanted = batch.column(1)
            w_off = wanted.offsets.to_numpy()
            values = wanted.values
            w_anchor = values.field(0).to_numpy().view(np.uint64)
            w_digest = values.field(1).to_numpy().view(np.uint64)
            w_copies = values.field(2).to_numpy()
            w_cells = values.field(3).to_numpy()
            for a, b in chunks(offsets):
                base = int(offsets[a])
                runs, bounds, starts, ends = spec.runs(data[base : offsets[b]], offsets[a : b + 1] - base)
                if not runs.row.size:
                    continue
                row = np.repeat(np.arange(b - a), np.diff(w_off[a : b + 1]))
                lo, hi = int(w_off[a]), int(w_off[b])
                # one run of each kind of context: any run of that digest in that row will do
                key = _pair_keys(runs.row, runs.digest)
                order = np.argsort(key, kind="stable")
                at = order[np.minimum(np.searchsorted(key[order], _pair_keys(row, w_digest[lo:hi])), order.size - 1)]
                good = (runs.row[at] == row) & (runs.digest[at] == w_digest[lo:hi]) & (runs.anchor[at] == w_anchor[lo:hi])
                at, pick = at[good], lo + np.flatnonzero(good)
                first = bounds[runs.row[at]] + runs.first[at]
                last = first + runs.count[at] + spec.length - 2
                text = data[base : offsets[b]]
                cut = [text[s:e].tobytes() for s, e in zip(starts[first].tolist(), ends[last].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([_signed(w_anchor[pick]), _signed(w_digest[pick]), pa.array(w_copies[pick]), pa.array(w_cells[pick]), pa.array(cut, pa.binary())], ["anchor", "digest", "copies", "cells", "context"])

    return kernel


def _pair_keys(row: np.ndarray, digest: np.ndarray) -> np.ndarray:
    return digest ^ (row.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def resolver_kernel(resolve: Callable) -> Callable:
    """Feeds whole cells, several at a time, to `resolve(data, offsets, cell, side, copies)`, which returns
    (context number, first window, number of windows) of all repeated stretches."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def answer(table: pa.Table):
            data, offsets = column_bytes(table.column("context"))
            cell = table.column("cell").to_numpy()
            k, first, count = resolve(data, offsets, cell, table.column("side").to_numpy(), table.column("copies").to_numpy())
            if k.size:
                yield pa.RecordBatch.from_arrays([table.column("anchor").combine_chunks().take(pa.array(k)), table.column("digest").combine_chunks().take(pa.array(k)), pa.array(first.astype(np.int64)), pa.array(count.astype(np.int64))], ["anchor", "digest", "rel", "n"])

        held: list[pa.RecordBatch] = []
        size = 0
        for batch in batches:
            offsets = column_bytes(batch.column(5))[1]
            for a, b in chunks(offsets, BLOCK_BYTES // 4):
                held.append(batch.slice(a, b - a))
                size += int(offsets[b] - offsets[a])
                if size < BLOCK_BYTES:
                    continue
                table = pa.Table.from_batches(held)
                cells = table.column("cell").to_numpy()
                last = int(np.searchsorted(cells, cells[-1]))  # the cell that may go on stays
                if last:
                    yield from answer(table.slice(0, last))
                    held = table.slice(last).to_batches()
                    size = sum(int(column_bytes(h.column(5))[1][-1]) for h in held)
        if held:
            yield from answer(pa.Table.from_batches(held))

    return kernel


def repeated_windows(docs: DataFrame, spec: Repeat, resolve: Callable) -> tuple[DataFrame, DataFrame]:
    """docs: (_uid long, unique; text). Returns docs dealt out by _uid, to join with, and
    (_uid, spans: array of (first window, number of windows)) of the documents with repeated windows.

    Empty tables give empty results; null texts have no windows."""
    ship_package(docs.sparkSession)
    texts = docs.select("_uid", "text").where(F.col("_uid").isNotNull())
    dealt = texts.repartition("_uid")
    found = stage(texts.mapInArrow(occurrence_kernel(spec), "_uid long, firsts array<long>, anchor long, digest long, n long, left int, right int"), "runs")
    # written, so that the join deals out both sides afresh and a very common gram can be split
    often = stage(found.groupBy("anchor").agg(F.sum(F.size("firsts")).alias("times")).where("times > 1").select("anchor"), "grams")
    kept = stage(found.join(often, "anchor", "left_semi"), "repeated-grams")
    unstage(found, often)
    kinds = stage(kept.groupBy("anchor", "digest").agg(F.sum(F.size("firsts").cast("long")).alias("copies"), F.min("_uid").alias("_uid"), F.max("n").alias("n"), F.max("left").alias("left"), F.max("right").alias("right")), "contexts")
    halves = kinds.select("anchor", "digest", F.explode(F.array(F.struct(F.lit(0).alias("at"), F.col("left").alias("half")), F.struct(F.lit(1).alias("at"), F.col("right").alias("half")))).alias("h")).select("anchor", "digest", "h.at", "h.half").where("half <> 0")
    shared = halves.groupBy("anchor", "at", "half").agg(F.count(F.lit(1)).alias("kinds")).where("kinds > 1").select("anchor", "at", "half")
    met = halves.join(shared, ["anchor", "at", "half"], "left_semi").select("anchor", "digest").distinct()
    meeting = stage(kinds.join(met, ["anchor", "digest"], "left_semi").select("anchor", "digest", "copies", "_uid"), "meeting-contexts")
    several = meeting.groupBy("anchor").agg(F.ceil(F.count(F.lit(1)) / CELL_CONTEXTS).cast("long").alias("cells"))
    # no other context to be compared with, and within one context no window comes twice: its place
    # around the gram tells windows apart. Copies repeat all its windows
    alone = kinds.where("copies > 1").join(meeting, ["anchor", "digest"], "left_anti").select("anchor", "digest", F.lit(0).cast("long").alias("rel"), "n")
    wanted = (
        meeting.join(several, "anchor")
        .groupBy("_uid")
        .agg(F.collect_list(F.struct("anchor", "digest", "copies", "cells")).alias("wanted"))
    )
    contexts = dealt.join(wanted.hint("shuffle_hash"), "_uid").select("text", "wanted").mapInArrow(context_kernel(spec), "anchor long, digest long, copies long, cells long, context binary")
    mine = F.pmod("digest", "cells")
    grid = F.transform(F.sequence(F.lit(0).cast("long"), F.col("cells") - 1), lambda j: F.xxhash64("anchor", F.least(mine, j), F.greatest(mine, j)))
    # in a cell of two different parts, side tells the parts apart; it is 0 in a cell of one part
    side = F.transform(F.sequence(F.lit(0).cast("long"), F.col("cells") - 1), lambda j: F.signum(mine - j).cast("int"))
    celled = contexts.select("anchor", "digest", F.explode(F.arrays_zip(grid.alias("cell"), side.alias("side"))).alias("at"), "copies", "context")
    celled = celled.select("anchor", "digest", F.col("at.cell").alias("cell"), F.col("at.side").alias("side"), "copies", "context")
    answers = celled.repartition("cell").sortWithinPartitions("cell").mapInArrow(resolver_kernel(resolve), "anchor long, digest long, rel long, n long")
    spans = kept.select("_uid", "firsts", "anchor", "digest").join(answers.unionByName(alone), ["anchor", "digest"]).select("_uid", F.transform("firsts", lambda f: F.struct((f + F.col("rel")).alias("first"), F.col("n").alias("n"))).alias("part")).groupBy("_uid").agg(F.flatten(F.collect_list("part")).alias("spans"))
    return dealt, spans


def covered(bounds: np.ndarray, row: np.ndarray, first: np.ndarray, count: np.ndarray, length: int) -> np.ndarray:
    """Which symbols are covered by the given windows (several rows of symbols, one after the other)."""
    delta = np.zeros(int(bounds[-1]) + 1, dtype=np.int64)
    start = bounds[row] + first
    np.add.at(delta, start, 1)
    np.add.at(delta, start + count + length - 1, -1)
    return np.cumsum(delta[:-1]) > 0


def span_arrays(column: pa.Array, a: int, b: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row (from a), first window and number of windows of the spans of rows a to b; null is none."""
    column = column.slice(a, b - a)
    sizes = np.nan_to_num(pa.compute.list_value_length(column).to_numpy(zero_copy_only=False), nan=0).astype(np.int64)
    flat = column.flatten()
    return np.repeat(np.arange(b - a), sizes), flat.field(0).to_numpy(), flat.field(1).to_numpy()
