"""Vectorised byte, word, hash and winnowing kernels on numpy arrays over Arrow buffers."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa

U = np.uint64
CHUNK_BYTES = 1 << 20
SPACES = (0x20, *range(0x09, 0x0E))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64 bits (xor-shift and multiply)."""
    x = x ^ (x >> U(31))
    x = x * U(0x7FB5D329728EA185)
    x = x ^ (x >> U(27))
    x = x * U(0x81DADEF4BC2DD44D)
    return x ^ (x >> U(33))


@lru_cache(maxsize=1)
def byte_values() -> np.ndarray:
    return mix(np.arange(1, 257, dtype=U) * U(0x9E3779B97F4A7C15))


_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i up to n; base is odd."""
    have = _POWERS.get(base)
    if have is None or have[0].size <= n:
        size = 1 << max(16, int(n + 1).bit_length())
        both = []
        for b in (base, pow(base, -1, 1 << 64)):
            x = np.full(size, b, dtype=U)
            x[0] = 1
            both.append(np.cumprod(x, dtype=U))
        if len(_POWERS) > 4:
            _POWERS.clear()
        _POWERS[base] = have = (both[0], both[1])
    return have


def prefix_sums(values: np.ndarray, base: int) -> np.ndarray:
    out = np.zeros(values.size + 1, dtype=U)
    np.cumsum(values * powers(base, values.size)[0][: values.size], out=out[1:])
    return out


BYTE_BASE, WORD_BASE = 0x5851F42D4C957F2D, 0xD1342543DE82EF95


def range_hash(sums: np.ndarray, start: np.ndarray, end: np.ndarray, base: int) -> np.ndarray:
    """The hash of each range [start, end) of the values below `sums`."""
    return mix((sums[end] - sums[start]) * powers(base, sums.size)[1][start] + (end - start).astype(U))


def column_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all rows, one after the other, and each row's place: offsets of length rows+1.
    Null counts as no bytes."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null(b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    buffers = column.buffers()
    n = len(column)
    if not n:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(buffers[1], dtype=np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    data = np.frombuffer(buffers[2], dtype=np.uint8)[offsets[0] : offsets[-1]] if buffers[2] is not None else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def chunks(offsets: np.ndarray, limit: int = CHUNK_BYTES):
    """Row ranges (a, b) of at most `limit` bytes, or one row if it alone is longer."""
    a, n = 0, offsets.size - 1
    while a < n:
        b = int(np.searchsorted(offsets, offsets[a] + limit, side="right")) - 1
        b = min(max(b, a + 1), n)
        yield a, b
        a = b


@lru_cache(maxsize=4)
def word_table(kind: str) -> np.ndarray:
    """Which bytes belong to words: 'space' splits at ASCII white space; 'alnum' keeps digits, a-z and
    all bytes of non-ASCII characters."""
    t = np.ones(256, dtype=bool)
    if kind == "space":
        t[list(SPACES)] = False
    else:
        t[:128] = False
        t[0x30:0x3A] = True
        t[0x61:0x7B] = True
    return t


@lru_cache(maxsize=1)
def lower_table() -> np.ndarray:
    t = np.arange(256, dtype=np.uint8)
    t[0x41:0x5B] += 32
    return t


def split_words(data: np.ndarray, offsets: np.ndarray, kind: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and for each row the first word's number (length rows+1)."""
    if not data.size:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(offsets.size, np.int64)
    inside = word_table(kind)[data]
    edge = np.zeros(data.size + 1, dtype=bool)
    edge[offsets] = True
    before = np.empty_like(inside)
    before[0], before[1:] = False, inside[:-1]
    starts = np.flatnonzero(inside & (~before | edge[:-1]))
    after = np.empty_like(inside)
    after[-1], after[:-1] = False, inside[1:]
    ends = np.flatnonzero(inside & (~after | edge[1:])) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    return range_hash(prefix_sums(byte_values()[data], BYTE_BASE), starts, ends, BYTE_BASE)


def sliding_min(key: np.ndarray, w: int) -> np.ndarray:
    """Minimum over each w consecutive entries, by doubling; length key.size - w + 1."""
    out, have = key, 1
    while have < w:
        step = min(have, w - have)
        out = np.minimum(out[: out.size - step], out[step:])
        have += step
    return out


POS_BITS = 26


def ranges(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """All integers start[i] .. start[i]+count[i]-1, one range after the other."""
    total = int(count.sum())
    if not total:
        return np.zeros(0, np.int64)
    ends = np.cumsum(count)
    return np.repeat(start - (ends - count), count) + np.arange(total)


class Runs:
    """Windows of `length` symbols grouped by the winnowed gram that represents them."""

    __slots__ = ("anchor", "count", "digest", "first", "left", "right", "row", "width")

    def __init__(self, row, first, count, anchor, digest, left, right, width):
        self.row, self.first, self.count, self.anchor, self.digest, self.left, self.right, self.width = row, first, count, anchor, digest, left, right, width


def winnowed_runs(symbols: np.ndarray, bounds: np.ndarray, length: int, gram: int, base: int) -> Runs:
    """For each row (symbols[bounds[r]:bounds[r+1]]) every window of `length` symbols picks the smallest
    hash among its grams (ties: the leftmost), which depends on the window's content alone. Consecutive
    windows with the same pick form a run: row, first window (within the row), number of windows, the
    picked gram's hash, a digest of all symbols the run's windows cover, and hashes (32 bits, 0 for none) of the
    picked gram with half of a window's other symbols to its left, and to its right. Every window
    has one of these two halves inside, so runs that share neither share no window."""
    n = np.diff(bounds)
    windows = np.maximum(n - length + 1, 0)
    empty = np.zeros(0, np.int64)
    if not windows.any():
        return Runs(empty, empty, empty, empty.astype(U), empty.astype(U), empty.astype(np.int32), empty.astype(np.int32), length)
    sums = prefix_sums(symbols, base)
    at = np.arange(symbols.size - gram + 1)
    grams = range_hash(sums, at, at + gram, base)
    if symbols.size >= 1 << POS_BITS:  # one row beyond the position bits: hashes keep fewer bits, order is the same
        bits = U(int(symbols.size).bit_length())
    else:
        bits = U(POS_BITS)
    key = ((grams >> bits) << bits) | at.astype(U)
    lowest = sliding_min(key, length - gram + 1)
    start = ranges(bounds[:-1], windows)
    row = np.repeat(np.arange(windows.size), windows)
    pick = (lowest[start] & ((U(1) << bits) - U(1))).astype(np.int64)
    new = np.empty(start.size, dtype=bool)
    new[0] = True
    new[1:] = (pick[1:] != pick[:-1]) | (row[1:] != row[:-1])
    head = np.flatnonzero(new)
    count = np.diff(np.append(head, start.size))
    first, pick, row = start[head], pick[head], row[head]
    digest = mix(range_hash(sums, first, first + count + length - 1, base) ^ mix((pick - first).astype(U) << U(20) | count.astype(U)))
    half = (length - gram + 1) // 2
    end = first + count + length - 1
    left = np.where(pick - half >= first, half_key(range_hash(sums, np.maximum(pick - half, 0), pick + gram, base)), 0)
    right = np.where(pick + gram + half <= end, half_key(range_hash(sums, pick, np.minimum(pick + gram + half, symbols.size), base)), 0)
    return Runs(row, first - bounds[row], count, grams[pick], digest, left.astype(np.int32), right.astype(np.int32), length)


def half_key(hashes: np.ndarray) -> np.ndarray:
    """The high 31 bits, never 0."""
    return np.maximum((hashes >> U(33)).astype(np.int64), 1)


def seven_symbols(symbols: np.ndarray) -> np.ndarray:
    """The seven symbols from each place on, nine bits each, first symbol highest; 0 past the end."""
    n = symbols.size
    padded = np.zeros(n + 7, dtype=U)
    padded[:n] = symbols
    key = np.zeros(n, dtype=U)
    for j in range(7):
        key = (key << U(9)) | padded[j : j + n]
    return key


def suffix_order(symbols: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Suffix array of byte symbols 0..256 (0 marks the end of a piece) and its inverse.

    Starts from the order by seven symbols and refines only groups of equal rank, doubling the depth
    at each round, until every suffix has a rank of its own."""
    n = symbols.size
    key = seven_symbols(symbols)
    order = np.argsort(key)
    rank = np.empty(n + 1, dtype=np.int64)
    rank[n] = -1
    slots = np.arange(n)
    keys, depth = key[order], 7
    while True:
        edge = np.empty(slots.size, dtype=bool)
        edge[0] = True
        edge[1:] = keys[1:] != keys[:-1]
        heads = np.maximum.accumulate(np.where(edge, slots, 0))
        rank[order[slots]] = heads
        tail = np.append(edge[1:], True)
        keep = ~(edge & tail)
        slots = slots[keep]
        if not slots.size:
            return order, rank[:n]
        place = order[slots]
        keys = rank[place] * (n + 1) + rank[np.minimum(place + depth, n)] + 1
        by = np.argsort(keys)
        order[slots] = place[by]
        keys = keys[by]
        depth *= 2


def kasai(symbols: np.ndarray, order: np.ndarray, rank: np.ndarray, lane_start: np.ndarray, lane_count: np.ndarray, cap: int) -> np.ndarray:
    """Common prefix (up to cap) of each suffix with its predecessor in suffix order, for the first
    lane_count[i] positions from lane_start[i]; other positions hold 0. Lanes advance together: each
    carries its match length minus one from position to position, as in the linear-time method."""
    n = symbols.size
    text = np.zeros(n + cap + 7, dtype=U)
    text[:n] = seven_symbols(symbols)
    text[n:] = np.arange(1, cap + 8, dtype=U) << U(62)
    steps = U(1) << (np.arange(1, 7, dtype=U) * U(9))
    out = np.zeros(n, dtype=np.int64)
    by = np.argsort(-lane_count, kind="stable")
    start, count = lane_start[by], lane_count[by]
    have = np.zeros(start.size, dtype=np.int64)
    alive = start.size
    for step in range(int(count[0]) if count.size else 0):
        alive = int(np.searchsorted(-count[:alive], -step, side="left"))
        here = start[:alive] + step
        slot = rank[here]
        before = order[np.maximum(slot - 1, 0)]
        h = np.maximum(have[:alive] - 1, 0)
        h[slot == 0] = 0
        grow = np.flatnonzero((slot > 0) & (h < cap))
        while grow.size:
            # seven symbols at a time; where they differ, the highest bit tells how many agree
            differ = text[here[grow] + h[grow]] ^ text[before[grow] + h[grow]]
            h[grow] += np.where(differ == 0, 7, 6 - np.searchsorted(steps, differ, side="right"))
            grow = grow[(differ == 0) & (h[grow] < cap)]
        np.minimum(h, cap, out=h)
        have[:alive] = h
        out[here] = h
    return out
