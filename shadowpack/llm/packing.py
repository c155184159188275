"""Packing token sequences by cutting-stock column generation.

Documents are tokenised once. All but a hashed share of them keep whole pieces: full sequences, and one
rest of less than a sequence. Rests are counted by length class (a bounded histogram); a linear
program over patterns of classes is solved on the driver by column generation (knapsack dynamic
programming prices the columns) and rounded. Rests, ranked within their class, take the patterns'
places. The hashed share of documents, as one long stream, is cut to fill what the patterns leave open,
and then whole sequences; the stream's end goes into sequences of a power of two."""

from __future__ import annotations

import math
import os
import zlib
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ship_package, stage, unique_ids
from .kernels import chunks, column_bytes, lower_table, ranges, split_words, word_hashes
from .substring_dedup import with_doc_ids

SEQUENCE, END_ID = 4096, 2
#: Tokens by which length classes differ.
CLASS_TOKENS = 32
#: One document in so many is cut freely to fill gaps.
FILLER_ONE_IN = 8
#: Tokens of the filler stream that one task joins with gaps.
CELL_TOKENS = 1 << 16
PART_ROWS = 200_000
#: Words whose ids a worker remembers.
CACHE_WORDS = 1_000_000


class WordCache:
    """Token ids of words, remembered in an open-addressed table of 64-bit word hashes.

    The tokenizer drops white space and never joins across it, so a text's ids are its words' ids, one after
    the other. A letter and the punctuation behind it are never one token either, so a word's final
    punctuation is split off and fewer words differ."""

    def __init__(self, tokenizer_json: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(tokenizer_json)
        vocab = self.tokenizer.get_vocab()
        self.ends_word = np.zeros(max(vocab.values()) + 1, dtype=bool)
        self.ends_word[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        self.clear()

    def clear(self) -> None:
        size = 1 << (2 * CACHE_WORDS - 1).bit_length()
        self.mask = np.uint64(size - 1)
        self.keys = np.zeros(size, dtype=np.uint64)  # 0: free
        self.slots = np.zeros(size, dtype=np.int32)
        self.words = 0
        self.ids = np.zeros(1 << 16, dtype=np.uint32)
        self.used = 0
        self.start = np.zeros(CACHE_WORDS + 1, dtype=np.int64)
        self.size = np.zeros(CACHE_WORDS + 1, dtype=np.int64)

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """Each hash's slot, or -1."""
        out = np.full(hashes.size, -1, dtype=np.int64)
        left = np.arange(hashes.size)
        at = hashes & self.mask
        while left.size:
            there = self.keys[at]
            same = there == hashes[left]
            out[left[same]] = self.slots[at[same]]
            go = ~same & (there != 0)
            left, at = left[go], (at[go] + np.uint64(1)) & self.mask
        return out

    def insert(self, hashes: np.ndarray, slots: np.ndarray) -> None:
        """Distinct hashes that aren't there yet."""
        left = np.arange(hashes.size)
        at = hashes & self.mask
        while left.size:
            free = np.flatnonzero(self.keys[at] == 0)
            _, first = np.unique(at[free], return_index=True)
            won = free[first]
            self.keys[at[won]] = hashes[left[won]]
            self.slots[at[won]] = slots[left[won]]
            go = np.ones(left.size, dtype=bool)
            go[won] = False
            left, at = left[go], at[go]
            taken = self.keys[at] != 0
            at = np.where(taken, (at + np.uint64(1)) & self.mask, at)

    def tokens(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words, one after the other, and their numbers. Words of letters alone are one token run
        each, so many of them are tokenised as one text and told apart by end-of-word ids."""
        encode = getattr(self.tokenizer, "encode_batch_fast", self.tokenizer.encode_batch)
        ids: list[np.ndarray] = [np.zeros(0, np.uint32)] * len(words)
        plain = [i for i, w in enumerate(words) if w.isalpha()]
        rest = [i for i, w in enumerate(words) if not w.isalpha()]
        groups = [plain[a : a + 256] for a in range(0, len(plain), 256)]
        for group, found in zip(groups, encode([" ".join([words[i] for i in g]) for g in groups], add_special_tokens=False), strict=True):
            flat = np.array(found.ids, dtype=np.uint32)
            ends = np.flatnonzero(self.ends_word[flat]) + 1
            if ends.size == len(group) and (not ends.size or ends[-1] == flat.size):
                for i, part in zip(group, np.split(flat, ends[:-1]), strict=True):
                    ids[i] = part
            else:
                rest += group
        for a in range(0, len(rest), 4096):
            for i, found in zip(rest[a : a + 4096], encode([words[i] for i in rest[a : a + 4096]], add_special_tokens=False), strict=True):
                ids[i] = np.array(found.ids, dtype=np.uint32)
        return np.concatenate(ids), np.array([x.size for x in ids], dtype=np.int64)

    def add(self, hashes: np.ndarray, words: list[str]) -> None:
        flat, sizes = self.tokens(words)
        while self.used + flat.size > self.ids.size:
            self.ids = np.append(self.ids, np.zeros_like(self.ids))
        self.ids[self.used : self.used + flat.size] = flat
        slots = self.words + np.arange(hashes.size)
        self.size[slots] = sizes
        self.start[slots] = self.used + np.cumsum(sizes) - sizes
        self.insert(hashes, slots)
        self.used += flat.size
        self.words += hashes.size

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all rows, one row after the other, and the rows' bounds."""
        # lower-casing here must not make a special token's string of another
        text = data if b"<|" in data.tobytes() else lower_table()[data]
        starts, ends, bounds = split_words(text, offsets, "space")
        if not starts.size:
            return np.zeros(0, np.uint32), np.zeros(offsets.size, np.int64)
        s, e, first = split_punctuation(text, starts, ends)
        bounds = first[bounds]
        hashes = np.maximum(word_hashes(text, s, e), np.uint64(1))
        raw = text.tobytes()
        # a slice of so many words never holds more different ones than the cache
        parts = [self.encode_words(raw, s[a : a + CACHE_WORDS], e[a : a + CACHE_WORDS], hashes[a : a + CACHE_WORDS]) for a in range(0, hashes.size, CACHE_WORDS)]
        size = np.concatenate([x[1] for x in parts])
        return np.concatenate([x[0] for x in parts]), np.concatenate([[0], np.cumsum(size)])[bounds]

    def encode_words(self, raw: bytes, s: np.ndarray, e: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of at most CACHE_WORDS words, one after the other, and their numbers."""
        slots = self.find(hashes)
        missing = np.flatnonzero(slots < 0)
        if missing.size:
            new, at = np.unique(hashes[missing], return_index=True)
            if self.words + new.size > CACHE_WORDS:
                self.clear()
                new, at = np.unique(hashes, return_index=True)
                missing = np.arange(hashes.size)
            at = missing[at]
            self.add(new, [raw[a:b].decode() for a, b in zip(s[at].tolist(), e[at].tolist(), strict=True)])
            slots[missing] = self.find(hashes[missing])
        size = self.size[slots]
        return self.ids[ranges(self.start[slots], size)], size


# Punctuation that ends a word, split off where a letter stands before it.
FINAL = b".,;:!?#$%&*)"


def split_punctuation(text: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the parts, and for each word its first part's number (length words+1)."""
    final = np.zeros(256, dtype=bool)
    final[list(FINAL)] = True
    stem = ends.copy()
    for _ in range(4):
        stem -= final[text[stem - 1]] & (stem - starts > 1)
    before = text[stem - 1]
    cut = (stem < ends) & (before >= 0x61) & (before <= 0x7A)
    n = 1 + cut
    first = np.concatenate([[0], np.cumsum(n)])
    s, e = np.repeat(starts, n), np.repeat(ends, n)
    e[first[:-1][cut]] = stem[cut]
    s[first[:-1][cut] + 1] = stem[cut]
    return s, e, first


_CACHES: dict[int, WordCache] = {}


def word_cache(tokenizer_json: str) -> WordCache:
    """One cache for each worker process, kept from task to task."""
    key = zlib.crc32(tokenizer_json.encode())
    if key not in _CACHES:
        _CACHES.clear()
        _CACHES[key] = WordCache(tokenizer_json)
    return _CACHES[key]


def token_kernel(shared):
    """Per document: number of ids with the end mark, whether it is filler, checksums of its whole
    sequences and its rest, and the ids themselves if it is filler."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = word_cache(shared.value)
        for batch in batches:
            data, offsets = column_bytes(batch.column(1))
            filler = batch.column(2).to_pylist()
            for a, b in chunks(offsets):
                ids, bounds = cache.encode(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                bounds = bounds.tolist()
                total, sums, kept = [], [], []
                for i in range(b - a):
                    own = np.append(ids[bounds[i] : bounds[i + 1]], np.uint32(END_ID)).astype("<u4").tobytes()
                    total.append(len(own) // 4)
                    fill = filler[a + i]
                    kept.append(own if fill else None)
                    sums.append([] if fill else [zlib.crc32(own[k : k + 4 * SEQUENCE]) for k in range(0, len(own), 4 * SEQUENCE)])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(total, pa.int64()), pa.array(sums, pa.list_(pa.int64())), pa.array(kept, pa.binary())], ["_uid", "n", "sums", "ids"])

    return kernel


def best_column(prices: np.ndarray, sizes: np.ndarray, capacity: int) -> tuple[float, np.ndarray]:
    """The most valuable pattern: unbounded knapsack by dynamic programming over the capacity."""
    value = np.zeros(capacity + 1)
    choice = np.full(capacity + 1, -1)
    for c in range(1, capacity + 1):
        fit = np.flatnonzero(sizes <= c)
        value[c], choice[c] = value[c - 1], -1
        if fit.size:
            v = value[c - sizes[fit]] + prices[fit]
            k = int(np.argmax(v))
            if v[k] > value[c] + 1e-12:
                value[c], choice[c] = v[k], fit[k]
    pattern, c = np.zeros(sizes.size, dtype=np.int64), capacity
    while c > 0:
        if choice[c] < 0:
            c -= 1
        else:
            pattern[choice[c]] += 1
            c -= int(sizes[choice[c]])
    return float(value[capacity]), pattern


def cutting_stock(sizes: np.ndarray, demand: np.ndarray, capacity: int, most_rounds: int = 4000) -> tuple[list[tuple[np.ndarray, int]], float]:
    """Patterns with multiplicities that hold at least the demand of each size, and the linear program's
    bound on their number. Revised simplex over generated columns; the optimum is rounded down and
    what is missing is packed first-fit, largest first."""
    m = sizes.size
    if not m:
        return [], 0.0
    basis = np.diag(capacity // sizes).astype(float)
    need = demand.astype(float)
    for _ in range(most_rounds):
        prices = np.linalg.solve(basis.T, np.ones(m))
        value, column = best_column(prices, sizes, capacity)
        if value <= 1 + 1e-7:
            break
        x, way = np.linalg.solve(basis, need), np.linalg.solve(basis, column.astype(float))
        ratio = np.where(way > 1e-9, np.maximum(x, 0) / np.where(way > 1e-9, way, 1), np.inf)
        basis[:, int(np.argmin(ratio))] = column
    x = np.maximum(np.linalg.solve(basis, need), 0)
    out = [(np.rint(basis[:, i]).astype(np.int64), int(math.floor(x[i] + 1e-9))) for i in range(m)]
    out = [(p, k) for p, k in out if k > 0]
    missing = demand - sum((p * k for p, k in out), np.zeros(m, np.int64))
    bins: list[tuple[np.ndarray, int]] = []
    for i in sorted(range(m), key=lambda i: -sizes[i]):
        for _ in range(int(max(missing[i], 0))):
            for k, (pattern, room) in enumerate(bins):
                if room >= sizes[i]:
                    pattern[i] += 1
                    bins[k] = (pattern, room - int(sizes[i]))
                    break
            else:
                pattern = np.zeros(m, dtype=np.int64)
                pattern[i] = 1
                bins.append((pattern, capacity - int(sizes[i])))
    return out + [(p, 1) for p, _ in bins], float(x.sum())


def prefix_sums_of(df: DataFrame, weight: str, parts: int, order: str, within: list[str] | None = None) -> DataFrame:
    """df with `before`: the sum of weight over earlier rows (of the same `within`), in an order that is
    fixed by hashed parts and then by `order`. Only per-part sums, a bounded table, meet in one place."""
    within = within or []
    df = df.withColumn("_part", F.pmod(F.xxhash64(order), F.lit(parts)))
    sums = df.groupBy(*within, "_part").agg(F.sum(weight).alias("_w"))
    window = (Window.partitionBy(*within) if within else Window.partitionBy(F.lit(0))).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    # a row per part: grows with the corpus, so whether it is broadcast is left to its measured size
    ahead = sums.select(*within, "_part", F.coalesce(F.sum("_w").over(window), F.lit(0)).alias("_ahead"))
    own = F.coalesce(F.sum(weight).over(Window.partitionBy(*within, "_part").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return df.withColumn("_own", own).join(ahead, [*within, "_part"]).withColumn("before", (F.col("_own") + F.col("_ahead")).cast("long")).drop("_part", "_own", "_ahead")


def pack(docs: DataFrame, tokenizer_path: str) -> DataFrame:
    """Packs the tokens of all documents into sequences of SEQUENCE tokens. A document's ids: those of the
    tokenizer, without special tokens, then END_ID; each lies in exactly one piece.

    docs: doc_id, text, any other columns (ignored). Returns doc_id, start, length, ids_crc32 (unsigned, of
    the ids as little-endian 32-bit numbers), doc_tokens, sequence_id, offset (gapless from 0 in each
    sequence); one row per piece. Null text: empty, so the end id alone. Rows with a null or repeated
    doc_id count as documents of their own. Empty table: empty result. Sequences that end short are to
    be padded, unless their length is a power of two."""
    spark = docs.sparkSession
    ship_package(spark)
    ids = unique_ids(docs.select("doc_id", "text"))
    shared = spark.sparkContext.broadcast(Path(tokenizer_path).read_text())
    fill = F.pmod(F.xxhash64(F.col("_uid"), F.lit(7)), F.lit(FILLER_ONE_IN)) == 0
    tokens = stage(ids.select("_uid", "text", fill.alias("fill")).mapInArrow(token_kernel(shared), "_uid long, n long, sums array<long>, ids binary"), "tokens")
    normal = tokens.where("ids is null").select("_uid", "n", "sums", F.floor(F.col("n") / SEQUENCE).alias("full"), (F.col("n") % SEQUENCE).alias("rest"))
    # running sums carry a few numbers for each document; ids and checksums come back by join, so a part of so
    # many rows is bounded in bytes too
    rows = tokens.count()
    parts = max(4, math.ceil(rows / PART_ROWS))
    # whole sequences of one document
    ahead_of = prefix_sums_of(normal.where("full > 0").select("_uid", "full"), "full", parts, "_uid").select("_uid", "before")
    whole = ahead_of.join(normal.where("full > 0"), "_uid").select("_uid", "n", "before", F.explode(F.sequence(F.lit(0).cast("long"), F.col("full") - 1)).alias("k"), "sums")
    whole = whole.select("_uid", (F.col("k") * SEQUENCE).alias("start"), F.lit(SEQUENCE).cast("long").alias("length"), F.element_at("sums", (F.col("k") + 1).cast("int")).alias("ids_crc32"), F.col("n").alias("doc_tokens"), (F.col("before") + F.col("k")).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    n_whole = normal.agg(F.coalesce(F.sum("full"), F.lit(0))).first()[0]
    # rests by class and pattern
    rest = normal.where("rest > 0").select("_uid", "n", "full", "rest", F.element_at("sums", -1).alias("ids_crc32"), F.ceil(F.col("rest") / CLASS_TOKENS).cast("int").alias("class"))
    histogram = {r["class"]: r["count"] for r in rest.groupBy("class").count().collect()}
    classes = np.array(sorted(histogram), dtype=np.int64)
    patterns, _ = cutting_stock(classes, np.array([histogram[c] for c in classes.tolist()], dtype=np.int64), SEQUENCE // CLASS_TOKENS)
    places, sequence, taken = [], int(n_whole), {c: 0 for c in classes.tolist()}
    for pattern, times in patterns:
        for k in np.flatnonzero(pattern).tolist():
            c, per = int(classes[k]), int(pattern[k])
            places.append((c, taken[c], taken[c] + per * times, per, sequence))
            taken[c] += per * times
        sequence += times
    places_df = F.broadcast(spark.createDataFrame(places, "class int, lo long, hi long, per long, first_sequence long"))
    ranked = prefix_sums_of(rest.withColumn("one", F.lit(1)), "one", parts, "_uid", ["class"]).withColumnRenamed("before", "rank")
    put = ranked.join(places_df, "class").where("rank >= lo and rank < hi").withColumn("sequence_id", F.col("first_sequence") + F.floor((F.col("rank") - F.col("lo")) / F.col("per")))
    ahead = F.sum("rest").over(Window.partitionBy("sequence_id").orderBy(F.desc("rest"), "_uid").rowsBetween(Window.unboundedPreceding, -1))
    put = stage(put.select("_uid", (F.col("full") * SEQUENCE).alias("start"), F.col("rest").alias("length"), "ids_crc32", F.col("n").alias("doc_tokens"), "sequence_id", F.coalesce(ahead, F.lit(0)).cast("long").alias("offset")), "rests")
    # the filler stream and the gaps it fills
    used = put.groupBy("sequence_id").agg(F.sum("length").alias("used"))
    gaps = used.where(F.col("used") < SEQUENCE).select("sequence_id", "used", (F.lit(SEQUENCE) - F.col("used")).alias("gap"))
    gaps = stage(prefix_sums_of(gaps, "gap", parts, "sequence_id").select("sequence_id", "used", F.col("before").alias("lo"), (F.col("before") + F.col("gap")).alias("hi")), "gaps")
    open_ = gaps.agg(F.coalesce(F.max("hi"), F.lit(0))).first()[0]
    stream_places = prefix_sums_of(tokens.where("ids is not null").select("_uid", "n"), "n", parts, "_uid")
    stream = stream_places.join(tokens.where("ids is not null").select("_uid", "ids"), "_uid").select("_uid", "n", "ids", F.col("before").alias("lo"), (F.col("before") + F.col("n")).alias("hi"))
    total = tokens.where("ids is not null").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    more = max(0, total - open_)
    full_more = more // SEQUENCE
    own = spark.range(full_more).select((F.lit(sequence) + F.col("id")).alias("sequence_id"), F.lit(0).cast("long").alias("used"), (F.lit(open_) + F.col("id") * SEQUENCE).alias("lo"), (F.lit(open_) + (F.col("id") + 1) * SEQUENCE).alias("hi"))
    at, tail = open_ + full_more * SEQUENCE, []
    for bit in reversed(range(SEQUENCE.bit_length())):
        if (more % SEQUENCE) >> bit & 1:
            tail.append((sequence + full_more + len(tail), 0, at, at + (1 << bit)))
            at += 1 << bit
    gaps = gaps.unionByName(own).unionByName(spark.createDataFrame(tail, "sequence_id long, used long, lo long, hi long"))

    def by_cell(df: DataFrame) -> DataFrame:
        cells = F.sequence(F.floor(F.col("lo") / CELL_TOKENS), F.floor((F.col("hi") - 1) / CELL_TOKENS))
        return df.withColumn("cell", F.explode(cells)).withColumn("from", F.greatest("lo", F.col("cell") * CELL_TOKENS)).withColumn("to", F.least("hi", (F.col("cell") + 1) * CELL_TOKENS))

    pieces = by_cell(stream).select("_uid", "n", "cell", F.col("lo").alias("doc_lo"), F.col("from").alias("a"), F.col("to").alias("b"), F.substring("ids", (4 * (F.col("from") - F.col("lo")) + 1).cast("int"), (4 * (F.col("to") - F.col("from"))).cast("int")).alias("part"))
    holes = by_cell(gaps).select("sequence_id", "used", "cell", F.col("lo").alias("gap_lo"), F.col("from").alias("c"), F.col("to").alias("d"))
    cut = pieces.join(holes, "cell").where("a < d and c < b").withColumn("x", F.greatest("a", "c")).withColumn("y", F.least("b", "d"))
    cut = cut.select("_uid", (F.col("x") - F.col("doc_lo")).alias("start"), (F.col("y") - F.col("x")).alias("length"), F.crc32(F.substring("part", (4 * (F.col("x") - F.col("a")) + 1).cast("int"), (4 * (F.col("y") - F.col("x"))).cast("int"))).alias("ids_crc32"), F.col("n").alias("doc_tokens"), "sequence_id", (F.col("used") + F.col("x") - F.col("gap_lo")).alias("offset"))
    return with_doc_ids(whole.unionByName(put).unionByName(cut), ids)
