"""MinHash near-dedup with b-bit signatures.

1. Every text becomes a set of shingle hashes; texts of equal sets, told by a 128-bit digest of the full
   set, form a class, whose smallest doc_id stands for it. A class is one row from here on, however many
   copies it has.
2. Each class gets MINIMA minima. Minima of a band make its bucket key; the low BITS bits of all
   minima are packed into the signature.
3. First round: in each bucket every class is paired with the bucket's smallest, never with all.
   Pairs whose collision-corrected similarity, estimated from bit counts, may reach the threshold are
   candidates; confirmed ones, on full sets, are joined to components.
   Only the likeliest pair of each class is confirmed here.
4. Further rounds: buckets that still hold several components are taken up again. Members of different
   components are compared by set sizes and bit counts in blocks (buckets of many members over a grid
   of blocks): for some rounds each member's likeliest partner is confirmed, which joins up large groups
   in few pairs, and at last, by longer signatures, every pair that may reach the threshold. Pairs within one component need
   no look: their link would change nothing. So every candidate pair is connected already or examined."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  (pa.compute)
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import release, ship_package, stage, stage_mark, unique_ids, unstage
from .components import connected_components
from .kernels import WORD_BASE, chunks, column_bytes, lower_table, mix, prefix_sums, range_hash, ranges, split_words, word_hashes
from .substring_dedup import with_doc_ids

#: Bands of a bucket key each, minima in a band, minima in a signature (those of the bands first), bits kept.
BANDS, ROWS, MINIMA, BITS = 52, 6, 320, 4
#: Minima of the longer signatures by which the last round tells apart what is near the threshold.
WIDE_MINIMA = 2048
#: Standard deviations of the estimate below the threshold at which a pair is still confirmed.
SLACK = 4.5
#: Members of a bucket that one block holds from one side; rounds that look for one partner each.
BLOCK_MEMBERS, PARTNER_ROUNDS = 4000, 3


@lru_cache(maxsize=4)
def multipliers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n of a fixed series: a longer signature begins with the minima of a shorter one."""
    seeds = mix(np.arange(1, 2 * n + 1, dtype=np.uint64) * np.uint64(0xA0761D6478BD642F))
    return seeds[0::2].astype(np.uint32) | np.uint32(1), seeds[1::2].astype(np.uint32)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each row, one row after the other, and their bounds."""
    lowered = lower_table()[data]
    starts, ends, bounds = split_words(lowered, offsets, "space")
    n = np.diff(bounds)
    if not starts.size:
        return np.zeros(0, np.uint64), np.zeros(offsets.size, np.int64)
    words = word_hashes(lowered, starts, ends)
    sums = prefix_sums(words, WORD_BASE)
    count = np.where(n == 0, 0, np.maximum(n - width + 1, 1))
    at = ranges(bounds[:-1], count)
    row = np.repeat(np.arange(n.size), count)
    hashes = range_hash(sums, at, np.minimum(at + width, bounds[row + 1]), WORD_BASE)
    order = np.lexsort((hashes, row))
    hashes, row = hashes[order], row[order]
    first = np.ones(hashes.size, dtype=bool)
    first[1:] = (hashes[1:] != hashes[:-1]) | (row[1:] != row[:-1])
    hashes, row = hashes[first], row[first]
    return hashes, np.searchsorted(row, np.arange(n.size + 1))


def minima(hashes: np.ndarray, bounds: np.ndarray, n: int) -> np.ndarray:
    """n minima for each row that has shingles; rows x n, 32 bits."""
    a, b = multipliers(n)
    low, high = hashes.astype(np.uint32), (hashes >> np.uint64(32)).astype(np.uint32)
    full = np.flatnonzero(np.diff(bounds) > 0)
    out = np.zeros((bounds.size - 1, n), dtype=np.uint32)
    for j in range(n):
        x = (low ^ b[j]) * a[j]
        x ^= x >> np.uint32(15)
        x += high
        x *= np.uint32(0x2C1B3C6D)
        x ^= x >> np.uint32(12)
        out[full, j] = np.minimum.reduceat(x, bounds[full]) if full.size else 0
    return out


def pack_bits(minima_: np.ndarray, bits: int) -> np.ndarray:
    """The low bits of each minimum, packed; rows x bytes."""
    planes = [(minima_ >> np.uint32(k)) & np.uint32(1) for k in range(bits)]
    return np.packbits(np.concatenate(planes, axis=1).astype(np.uint8), axis=1)


def agreeing(a: np.ndarray, b: np.ndarray, bits: int) -> np.ndarray:
    """How many minima agree in all their low bits, from packed signatures as 64-bit words (rows x words)."""
    width = b.shape[-1] // bits
    differ = a[..., :width] ^ b[..., :width]
    for k in range(1, bits):
        differ = differ | (a[..., k * width : (k + 1) * width] ^ b[..., k * width : (k + 1) * width])
    return width * 64 - np.bitwise_count(differ).sum(axis=-1, dtype=np.int64)


def words_of(column: pa.Array) -> np.ndarray:
    return column_bytes(column)[0].reshape(len(column), -1).view(np.uint64)


def sizes_fit(a: np.ndarray, b: np.ndarray, threshold: float) -> np.ndarray:
    """Sets of that similarity can't differ more in size."""
    return np.minimum(a, b) >= threshold * np.maximum(a, b) - 1e-9


def estimated(agree: np.ndarray, n: int, bits: int) -> np.ndarray:
    """Similarity corrected for collisions of low bits: unequal minima agree with chance 2**-bits."""
    chance = 2.0**-bits
    return (agree / n - chance) / (1 - chance)


def least_agreement(threshold: float, n: int, bits: int) -> int:
    """Agreements below which a pair of that similarity falls with negligible chance."""
    p = threshold + (1 - threshold) * 2.0**-bits
    return int(np.floor(n * p - SLACK * np.sqrt(n * p * (1 - p))))


def band_keys(low: np.ndarray) -> np.ndarray:
    """rows x BANDS bucket keys; keys of different bands differ."""
    bands = np.zeros((low.shape[0], BANDS), dtype=np.uint64)
    for r in range(ROWS):
        bands = mix(bands * np.uint64(31) + low[:, r : BANDS * ROWS : ROWS].astype(np.uint64) + np.uint64(r + 1))
    return mix(bands + np.arange(BANDS, dtype=np.uint64)[None, :])


def signature_kernel(width: int):

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            uid = batch.column(0)
            data, offsets = column_bytes(batch.column(1))
            for a, b in chunks(offsets):
                hashes, bounds = shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], width)
                sets, at = hashes.tobytes(), (8 * bounds).tolist()
                keys = [hashlib.blake2b(sets[s:e], digest_size=16).digest() for s, e in zip(at[:-1], at[1:], strict=True)]
                size = np.diff(bounds)
                low = minima(hashes, bounds, MINIMA)
                bands = band_keys(low)
                packed = pack_bits(low, BITS)
                raw = packed.tobytes()
                step = packed.shape[1]
                yield pa.RecordBatch.from_arrays(
                    [
                        uid.slice(a, b - a),
                        pa.array(size),
                        pa.array(keys, pa.binary()),
                        pa.array([raw[i * step : (i + 1) * step] for i in range(b - a)], pa.binary()),
                        pa.ListArray.from_arrays(pa.array(np.arange(b - a + 1, dtype=np.int32) * BANDS), pa.array(bands.view(np.int64).ravel())),
                    ],
                    ["_uid", "n_shingles", "set_key", "signature", "bands"],
                )

    return kernel


def wide_kernel(width: int):
    """(id, set size, signature of WIDE_MINIMA minima followed by all bucket keys) of the texts that are still to
    be compared."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = column_bytes(batch.column(1))
            for a, b in chunks(offsets, 1 << 18):
                hashes, bounds = shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], width)
                low = minima(hashes, bounds, WIDE_MINIMA)
                packed = np.concatenate([pack_bits(low, BITS), band_keys(low).view(np.uint8).reshape(b - a, -1)], axis=1)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(np.diff(bounds)), pa.array([x.tobytes() for x in packed], pa.binary())], ["id", "size", "signature"])

    return kernel


def bits_filter_kernel(threshold: float):
    """Keeps the candidate pairs (a, b, signatures, set sizes) that may belong to sets of the threshold's
    similarity, with their number of agreements."""
    least = least_agreement(threshold, MINIMA, BITS)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            agree = agreeing(words_of(batch.column(2)), words_of(batch.column(3)), BITS)
            keep = pa.array((agree >= least) & sizes_fit(batch.column(4).to_numpy(), batch.column(5).to_numpy(), threshold))
            yield pa.RecordBatch.from_arrays([x.filter(keep) for x in (batch.column(0), batch.column(1), pa.array(agree))], ["a", "b", "agree"])

    return kernel


def bucket_kernel(threshold: float, every: bool):
    """Cells arrive whole and in order: (cell, side, component, id, set size, bucket, signature). Compares members of
    different components by bit counts and yields pairs (a, b, agree) that may reach the threshold: all
    of them (`every`), each in the first bucket that its members share and in no other, or for each member
    a, those of the cell's largest component aside, its likeliest partner b alone."""
    least = least_agreement(threshold, WIDE_MINIMA if every else MINIMA, BITS)

    def pairs(cell):
        side, part, ids, size, bucket, sig = (np.concatenate([c[k] for c in cell]) for k in range(1, 7))
        order = np.lexsort((ids, part))
        side, part, ids, size, sig = side[order], part[order], ids[order], size[order], sig[order]
        if every:
            words = WIDE_MINIMA * BITS // 64
            sig, keys = sig[:, :words], sig[:, words:]
            here = bucket[0].view(np.uint64)
        if part[0] == part[-1]:
            return
        two_sided = bool((side != 0).any())
        _, heads, members = np.unique(part, return_index=True, return_counts=True)
        starts, ends = np.repeat(heads, members), np.repeat(heads + members, members)
        largest = np.repeat(np.arange(heads.size) == members.argmax(), members)
        out: list[tuple] = []
        for i in range(ids.size) if every else np.flatnonzero(~largest).tolist():
            near = np.arange(ends[i], ids.size) if every else np.concatenate([np.arange(starts[i]), np.arange(ends[i], ids.size)])
            near = near[sizes_fit(size[near], size[i], threshold)]
            if two_sided:
                near = near[side[near] != side[i]]
            if not near.size:
                continue
            agree = agreeing(sig[i], sig[near], BITS)
            hit = np.flatnonzero(agree >= least)
            if hit.size and every:
                first = (keys[near[hit]] == keys[i]).argmax(axis=1)
                hit = hit[keys[i][first] == here]
            elif hit.size:
                hit = agree.argmax()[None]
            if hit.size:
                out.append((np.full(hit.size, ids[i]), ids[near[hit]], agree[hit]))
        if out:
            one, two, agree = (np.concatenate(x) for x in zip(*out, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(one), pa.array(two), pa.array(agree)], ["a", "b", "agree"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = []
        for batch in batches:
            if not batch.num_rows:
                continue
            cell, *rest = (batch.column(k).to_numpy() for k in range(6))
            rest.append(words_of(batch.column(6)))
            cuts = np.concatenate([[0], np.flatnonzero(np.diff(cell)) + 1, [cell.size]])
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                if held and held[0][0] != cell[a]:
                    yield from pairs(held)
                    held = []
                held.append((cell[a], *(x[a:b] for x in rest)))
        if held:
            yield from pairs(held)

    return kernel


def confirm_kernel(width: int, numerator: int, denominator: int):
    """(a, b, text of a, text of b): keeps pairs with denominator * shared >= numerator * union."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            one, two = column_bytes(batch.column(2)), column_bytes(batch.column(3))
            for a, b in chunks(one[1] + two[1]):
                sets = [shingle_sets(d[o[a] : o[b]], o[a : b + 1] - o[a], width) for d, o in (one, two)]
                row = [np.repeat(np.arange(b - a), np.diff(s[1])) for s in sets]
                both_row, both = np.concatenate(row), np.concatenate([s[0] for s in sets])
                order = np.lexsort((both, both_row))
                same = (both[order][1:] == both[order][:-1]) & (both_row[order][1:] == both_row[order][:-1])
                shared = np.bincount(both_row[order][1:][same], minlength=b - a)
                union = np.diff(sets[0][1]) + np.diff(sets[1][1]) - shared
                keep = pa.array((denominator * shared >= numerator * union) & (union > 0))
                yield pa.RecordBatch.from_arrays([batch.column(k).slice(a, b - a).filter(keep) for k in (0, 1)], ["a", "b"])

    return kernel


def near_duplicates(docs: DataFrame, width: int = 5, numerator: int = 80, denominator: int = 100) -> DataFrame:
    """Components of documents linked by Jaccard similarity of their word shingle sets, at least
    numerator / denominator. Words: maximal runs of anything but ASCII white space, A-Z lower-cased. A
    document's set: its distinct shingles of `width` words; with fewer words, the whole sequence as
    one; without words, empty and linked with nothing.

    docs: doc_id, text, any other columns (ignored). Returns doc_id, n_shingles, component_id (smallest
    doc_id reachable, itself included), kept (doc_id = component_id); one row per input row. Null text:
    no words. Rows with a null or repeated doc_id count as documents of their own; component_id is then
    an internal number for those rows (negative). Empty table: empty result."""
    ship_package(docs.sparkSession)
    ids = unique_ids(docs.select("doc_id", "text"))
    threshold = numerator / denominator
    mark = stage_mark()
    texts = ids.select("_uid", "text")
    rows = stage(texts.mapInArrow(signature_kernel(width), "_uid long, n_shingles long, set_key binary, signature binary, bands array<long>"), "signatures")
    classes = stage(rows.where("n_shingles > 0").groupBy("set_key", "n_shingles").agg(F.min("_uid").alias("id")), "classes")
    lead = stage(rows.join(classes.select(F.col("id").alias("_uid")), "_uid", "left_semi").select(F.col("_uid").alias("id"), "n_shingles", "signature", "bands"), "class-signatures")
    buckets = lead.select("id", F.explode("bands").alias("bucket"))
    shared = buckets.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("first")).where("n > 1")
    members = stage(buckets.join(shared, "bucket"), "buckets")
    signatures = lead.select("id", F.col("n_shingles").alias("size"), "signature")
    star = members.where("id <> first").select(F.col("first").alias("a"), F.col("id").alias("b")).distinct()
    # one pair for each class, its likeliest; what is left out here comes up again below
    likely = filtered(star, signatures, threshold).groupBy("b").agg(F.max_by("a", F.struct("agree", "a")).alias("a")).select("a", "b")
    confirm = (texts, width, numerator, denominator)
    tested, links = confirmed(likely, *confirm, "links")
    parts = stage(connected_components(links), "components")
    k, every = 0, False
    while not every:
        every = k >= PARTNER_ROUNDS
        cells = open_cells(members, parts, wide_signatures(members, parts, texts, width) if every else signatures)
        found = cells.mapInArrow(bucket_kernel(threshold, every), "a long, b long, agree long")
        if not every:
            found = found.groupBy("a").agg(F.max_by("b", F.struct("agree", "b")).alias("b"))
        pairs = found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct().join(tested, ["a", "b"], "left_anti")
        more, late = confirmed(pairs, *confirm, f"links-{k}")
        tested = tested.unionByName(more)
        if late.limit(1).count():
            links = links.unionByName(late)
            parts = stage(connected_components(links), "components")
            k += 1
        else:
            k = PARTNER_ROUNDS  # no partner is left to be found one by one
    release(mark, rows, classes, parts)
    of_class = classes.join(parts, classes["id"] == parts["node"], "left").select("set_key", "n_shingles", F.coalesce("component", "id").alias("component_id"))
    whole = rows.select("_uid", "n_shingles", "set_key").join(of_class, ["set_key", "n_shingles"], "left")
    out = whole.select("_uid", "n_shingles", F.coalesce("component_id", "_uid").alias("component_id"))
    return with_doc_ids(out.withColumn("kept", F.col("_uid") == F.col("component_id")), ids).select("doc_id", "n_shingles", "component_id", "kept")


def open_members(members: DataFrame, parts: DataFrame) -> DataFrame:
    """Members (bucket, id, n, part) of the buckets that hold several components."""
    tagged = members.select("bucket", "id", "n").join(parts, members["id"] == parts["node"], "left").select("bucket", "id", "n", F.coalesce("component", "id").alias("part"))
    mixed = tagged.groupBy("bucket").agg(F.min("part").alias("p"), F.max("part").alias("q")).where("p <> q").select("bucket")
    return tagged.join(mixed, "bucket", "left_semi")


def wide_signatures(members: DataFrame, parts: DataFrame, texts: DataFrame, width: int) -> DataFrame:
    still = open_members(members, parts).select(F.col("id").alias("_uid")).distinct()
    return stage(texts.join(still, "_uid", "left_semi").select("_uid", "text").mapInArrow(wide_kernel(width), "id long, size long, signature binary"), "wide-signatures")


def open_cells(members: DataFrame, parts: DataFrame, signatures: DataFrame) -> DataFrame:
    """Members of the buckets that hold several components, dealt out by bucket; buckets of more than
    BLOCK_MEMBERS over a grid of cells in which every two members still meet."""
    open_ = open_members(members, parts).join(signatures, "id")
    cells = F.greatest(F.lit(1), F.ceil(F.col("n") / BLOCK_MEMBERS)).cast("long")
    mine = F.pmod(F.xxhash64("id"), "cells")
    span = F.sequence(F.lit(0).cast("long"), F.col("cells") - 1)
    at = F.transform(span, lambda j: F.struct(F.xxhash64("bucket", F.least(mine, j), F.greatest(mine, j)).alias("cell"), F.signum(mine - j).cast("int").alias("side")))
    celled = open_.withColumn("cells", cells).select(F.explode(at).alias("at"), "part", "id", "size", "bucket", "signature").select("at.cell", "at.side", "part", "id", "size", "bucket", "signature")
    return celled.repartition("cell").sortWithinPartitions("cell")


def filtered(pairs: DataFrame, signatures: DataFrame, threshold: float) -> DataFrame:
    one = signatures.select(F.col("id").alias("a"), F.col("signature").alias("sig_a"), F.col("size").alias("size_a"))
    two = signatures.select(F.col("id").alias("b"), F.col("signature").alias("sig_b"), F.col("size").alias("size_b"))
    return pairs.join(one, "a").join(two, "b").select("a", "b", "sig_a", "sig_b", "size_a", "size_b").mapInArrow(bits_filter_kernel(threshold), "a long, b long, agree long")


def confirmed(pairs: DataFrame, texts: DataFrame, width: int, numerator: int, denominator: int, name: str) -> tuple[DataFrame, DataFrame]:
    """The candidate pairs, and those of them that hold on full sets. Only texts of candidate pairs move."""
    pairs = stage(pairs, f"{name}-candidates")
    needed = pairs.select(F.col("a").alias("_uid")).union(pairs.select(F.col("b").alias("_uid"))).distinct()
    own = stage(texts.join(needed, "_uid", "left_semi"), f"{name}-texts")
    both = pairs.join(own.select(F.col("_uid").alias("a"), F.col("text").alias("text_a")), "a").join(own.select(F.col("_uid").alias("b"), F.col("text").alias("text_b")), "b")
    links = stage(both.select("a", "b", "text_a", "text_b").mapInArrow(confirm_kernel(width, numerator, denominator), "a long, b long"), name)
    unstage(own)
    return pairs, links
