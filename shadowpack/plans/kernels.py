"""Numpy kernels over Arrow batches of packed groups (rectangular blocks of groups x items)."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa

from .hierarchy import Hierarchy

#: Bytes that one block of groups x candidates x items may take.
BLOCK_BYTES = 48 << 20
#: Widest groups whose items are compared pair by pair.
MOST_PAIRED = 32
#: Groups and bytes of Arrow batches that a kernel takes together.
GATHERED_ROWS, GATHERED_BYTES = 40_000, 32 << 20
#: Groups of a stored block, of a block in work, and groups of one width from which on they aren't padded.
STORED_GROUPS, WORKING_GROUPS, OWN_WIDTH = 8_192, 16_384, 256


@dataclass
class Caps:
    """What a kernel needs of the local caps: named item sets, or levels by attribute."""

    hierarchy: Hierarchy
    levels: list[tuple[str | None, int]]

    def nodes(self, block: Block) -> list[tuple[np.ndarray, np.ndarray]]:
        """Bottom-up levels as (node of each item or -1, cap of each node)."""
        out: list[tuple[np.ndarray, np.ndarray]] = []
        if self.levels:
            named = 0
            for column, cap in self.levels:
                if column is None:
                    out.append(Level((np.broadcast_to(np.int8(0), block.ids.shape), np.array([cap]))))
                else:
                    node = block.nodes[named]
                    out.append(Level((node, np.full(max(int(node.max(initial=0)) + 1, 1), cap))))
                    named += 1
        for level in self.hierarchy.levels():
            node = np.full(block.ids.shape, -1, dtype=np.int64)
            for n, s in enumerate(level):
                node[np.ones(block.ids.shape, bool) if s.items is None else np.isin(block.ids, sorted(s.items))] = n
            out.append(Level((node, np.array([s.cap for s in level]))))
        return out

    def single(self) -> int | None:
        """Q if a cap over the whole group is the only one."""
        if self.levels:
            return self.levels[0][1] if len(self.levels) == 1 and self.levels[0][0] is None and not self.hierarchy.sets else None
        return self.hierarchy.single_cap()


@dataclass
class Block:
    """Groups x items, padded: item ids (-1 where there is none), profits, needs, units, node codes. Sparse problems
    have each item's one knapsack (from 1, 0 where there is none) and its need in place of needs."""

    group: np.ndarray
    ids: np.ndarray
    profit: np.ndarray
    needs: np.ndarray | None
    units: np.ndarray
    valid: np.ndarray
    nodes: list[np.ndarray]
    knapsack: np.ndarray | None = None
    need: np.ndarray | None = None
    #: Whether no place is empty, and whether all units are 1.
    full: bool = False
    single: bool = False

    def part(self, rows: np.ndarray) -> Block:
        """Some of the groups, laid out as all are."""

        def of(x: np.ndarray | None) -> np.ndarray | None:
            return None if x is None else picked(x, rows)

        return Block(self.group[rows], of(self.ids), of(self.profit), of(self.needs), of(self.units), of(self.valid), [of(x) for x in self.nodes], of(self.knapsack), of(self.need), self.full, self.single)

    def priced(self, net: np.ndarray) -> np.ndarray:
        """Nets, -1 where there is no item."""
        return net if self.full else np.where(self.valid, net, -1.0)

    @property
    def amounts(self) -> np.ndarray | None:
        """Units, None where all are 1."""
        return None if self.single else self.units

    def dense(self, k: int) -> np.ndarray:
        """Needs as groups x items x knapsacks."""
        if self.needs is not None:
            return self.needs
        out = np.zeros((*self.ids.shape, k + 1))
        np.put_along_axis(out, self.knapsack[:, :, None].astype(np.int64), self.need[:, :, None], axis=2)
        return out[:, :, 1:]

    def net(self, prices: np.ndarray) -> np.ndarray:
        """Profit less priced needs; the same bits in either form, as needs of 0 change nothing."""
        if self.needs is not None:
            return net_of(self.profit, self.needs, prices)
        return self.profit - np.append(0.0, prices)[self.knapsack] * self.need

    def used(self, take: np.ndarray, k: int) -> np.ndarray:
        """Use of each knapsack by each group."""
        if self.needs is not None:
            return np.stack([used_of(take, self.needs[:, :, x]) for x in range(k)], axis=1)
        out = np.zeros((self.ids.shape[0], k + 1))
        np.add.at(out, (np.arange(self.ids.shape[0])[:, None], self.knapsack), take * self.need)
        return out[:, 1:]

    def total_used(self, take: np.ndarray, k: int) -> np.ndarray:
        if self.needs is not None:
            amount = take.astype(float)
            return np.array([total_of(amount, self.needs[:, :, x]) for x in range(k)])
        return np.bincount(self.knapsack.ravel(), weights=(take * self.need).ravel(), minlength=k + 1)[1:]


def picked(x: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """x[rows], laid out item by item."""
    return np.take(x.T, rows, axis=-1).T


def of_rows(level: tuple[np.ndarray, np.ndarray], rows: np.ndarray) -> Level:
    node, caps = level
    return Level((np.broadcast_to(node[:1, :1], (rows.size, node.shape[1])) if node.strides == (0, 0) else picked(node, rows), caps))


def used_of(take: np.ndarray, slope: np.ndarray) -> np.ndarray:
    """Use by each group."""
    return np.where(take, slope, 0.0).sum(axis=1) if take.dtype == bool else (take * slope).sum(axis=1)


def total_of(amount: np.ndarray, values: np.ndarray) -> float:
    """Sum of products, over arrays laid out item by item."""
    return float(np.einsum("mg,mg->", amount.T, values.T))


def gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The same rows in larger batches: short ones spend their time on calls."""
    part: list[pa.RecordBatch] = []
    for batch in batches:
        part.append(batch)
        if "width" in batch.schema.names:  # stored blocks are long already
            yield part.pop()
            continue
        if sum(b.num_rows for b in part) >= GATHERED_ROWS or sum(b.nbytes for b in part) >= GATHERED_BYTES:
            yield from pa.Table.from_batches(part).combine_chunks().to_batches()
            part = []
    if part:
        yield from pa.Table.from_batches(part).combine_chunks().to_batches()


def blocks(batch: pa.RecordBatch, k: int, bytes_per_item: int | Callable[[int], int] = 64, most: int | None = None) -> Iterator[Block]:
    """Rectangular blocks of a packed batch; groups of like size lie together, so little is padding. Arrays are
    groups x items, but lie in memory item by item: kernels then work on long runs of groups. A batch may hold
    needs of more than k knapsacks; the first k count. bytes_per_item: a number, or one for each width. most: the
    largest number of groups of a block; groups of a width that many have are then not padded."""
    if not batch.num_rows:
        return
    if "width" in batch.schema.names:
        yield from _restored(batch, k, bytes_per_item)
        return
    offsets = batch.column("item_ids").offsets.to_numpy()
    size = np.diff(offsets)
    flat = {c: batch.column(c).values.to_numpy(zero_copy_only=False) for c in ("item_ids", "profits", "units")}
    dense = "needs" in batch.schema.names
    needs = batch.column("needs").values.to_numpy(zero_copy_only=False) if dense else None
    needs_offset = batch.column("needs").offsets.to_numpy() if dense else None
    stride = (int(needs_offset[-1]) - int(needs_offset[0])) // max(1, int(offsets[-1]) - int(offsets[0])) if dense else 0
    wide = bytes_per_item if callable(bytes_per_item) else lambda m: bytes_per_item
    names = [c for c in batch.schema.names if c.startswith("node")]
    codes = [batch.column(c).values.to_numpy(zero_copy_only=False) for c in names]
    one = [batch.column(c).values.to_numpy(zero_copy_only=False) for c in ("one_knapsack", "one_need") if c in batch.schema.names]
    group = batch.column("group_id").to_numpy()
    order = np.argsort(size, kind="stable")
    a = 0
    while a < order.size:
        width = max(int(size[order[a]]), 1)
        # widths up to a quarter above share a block
        b = a + int(np.searchsorted(size[order[a:]], width + max(width // 4, 1), side="right"))
        if most:
            alone = a + int(np.searchsorted(size[order[a:]], width, side="right"))
            b = min(alone if alone - a >= OWN_WIDTH else b, a + most)
        b = min(max(b, a + 1), a + max(1, BLOCK_BYTES // ((wide(width) + 8 * k * dense) * width)))
        rows = order[a:b]
        m = int(size[rows].max(initial=0))
        at = offsets[rows][None, :] + np.arange(m)[:, None]
        valid = np.arange(m)[:, None] < size[rows][None, :]
        full = bool(valid.all())
        at = at if full else np.where(valid, at, 0)

        def placed(values: np.ndarray, empty, at=at, valid=valid, full=full) -> np.ndarray:
            return values[at].T if full else np.where(valid, values[at], empty).T

        table = None
        if dense and m:
            need_at = (needs_offset[rows] - stride * offsets[rows])[None, :] + at * stride
            need_at = need_at if full else np.where(valid, need_at, 0)
            table = np.empty((k, m, b - a))
            for x in range(k):
                table[x] = needs[need_at + x] if full else np.where(valid, needs[need_at + x], 0.0)
            table = table.transpose(2, 1, 0)
        if m:
            # codes count the nodes of one group: they are fewer than its items
            tight = np.int8 if m <= MOST_PAIRED else np.int64
            units = placed(flat["units"], 0).astype(np.int64)
            yield Block(group[rows], placed(flat["item_ids"], -1), placed(flat["profits"], 0.0), table, units, valid.T, [placed(c.astype(tight), -1) for c in codes], *(placed(c, 0) for c in one), full=full, single=bool((units == valid.T).all()))
        a = b


def packed_bytes(values: np.ndarray) -> bytes:
    """An array as bytes, in the narrowest type that holds its numbers exactly: its type's name in eight bytes, then
    the numbers, filled up to a multiple of eight bytes."""
    for kind in ("i1", "i2", "i4"):
        limits = np.iinfo(kind)
        if values.size and (values.min() < limits.min or values.max() > limits.max):
            continue
        small = values.astype(kind)
        if np.array_equal(small, values):
            break
    else:
        kind, small = values.dtype.str[1:], values
    data = small.tobytes()
    return kind.encode().ljust(8) + data + bytes(-len(data) % 8)


def unpacked(data: pa.Buffer | None, n: int) -> np.ndarray:
    return np.frombuffer(data, dtype=np.dtype(bytes(data[:8]).decode().strip()), count=n, offset=8)


def stored_columns(k: int, nodes: int) -> list[str]:
    return ["group_id", "sizes", "item_ids", "profits", *(f"need{x}" for x in range(k)), "units", *(f"node{i}" for i in range(nodes))]


def stored(block: Block, k: int) -> list[bytes]:
    """The stored_columns of a block of a dense problem: arrays item by item. Sizes are left out where no place is empty, units
    where all are 1."""
    sizes = b"" if block.full else packed_bytes(block.valid.sum(axis=1))
    units = b"" if block.single else packed_bytes(block.units.T)
    return [packed_bytes(block.group), sizes, packed_bytes(block.ids.T), packed_bytes(block.profit.T), *(packed_bytes(block.needs[:, :, x].T) for x in range(k)), units, *(packed_bytes(c.T) for c in block.nodes)]


def _restored(batch: pa.RecordBatch, k: int, bytes_per_item: int | Callable[[int], int]) -> Iterator[Block]:
    """The blocks of a batch of stored ones: those of one width are put together or cut to a size that suits the caches."""
    count, width = batch.column("groups").to_numpy(), batch.column("width").to_numpy()
    columns = {c: batch.column(c) for c in batch.schema.names if c not in ("groups", "width")}
    names = [c for c in columns if c.startswith("node")]
    wide = bytes_per_item if callable(bytes_per_item) else lambda m: bytes_per_item
    for m in np.unique(width).tolist():
        most = max(1, min(WORKING_GROUPS, BLOCK_BYTES // ((wide(m) + 8 * k) * m)))
        part: list[tuple[int, int, int]] = []
        held = 0
        rows = np.flatnonzero(width == m).tolist()
        for r in rows:
            for a in range(0, int(count[r]), most):
                b = min(a + most, int(count[r]))
                if held + b - a > most:
                    yield _put_together(columns, names, count, part, m, k)
                    part, held = [], 0
                part.append((r, a, b))
                held += b - a
        if part:
            yield _put_together(columns, names, count, part, m, k)


def _put_together(columns: dict[str, pa.Array], names: list[str], count: np.ndarray, part: list[tuple[int, int, int]], m: int, k: int) -> Block:
    n = sum(b - a for _, a, b in part)

    def filled(out: np.ndarray, column: str, empty: int | np.ndarray = 0) -> np.ndarray:
        at, high = 0, out.shape[0] if out.ndim > 1 else 1
        for r, a, b in part:
            data = columns[column][r].as_buffer()
            out[..., at : at + b - a] = unpacked(data, high * int(count[r])).reshape(*out.shape[:-1], int(count[r]))[..., a:b] if data.size else empty
            at += b - a
        return out

    whole = all(columns["sizes"][r].as_buffer().size == 0 for r, _, _ in part)
    single = all(columns["units"][r].as_buffer().size == 0 for r, _, _ in part)
    sizes = None if whole else filled(np.empty(n, dtype=np.int64), "sizes", m)
    valid = np.broadcast_to(True, (m, n)) if whole else np.arange(m)[:, None] < sizes[None, :]
    units = np.broadcast_to(np.int64(1), (m, n)) if single and whole else valid.astype(np.int64) if single else filled(np.empty((m, n), dtype=np.int64), "units", valid)
    needs = np.empty((k, m, n))
    for x in range(k):
        filled(needs[x], f"need{x}")
    tight = np.int8 if m <= MOST_PAIRED else np.int64
    nodes = [filled(np.empty((m, n), dtype=tight), c).T for c in names]
    return Block(filled(np.empty(n, dtype=np.int64), "group_id"), filled(np.empty((m, n), dtype=np.int32), "item_ids").T, filled(np.empty((m, n)), "profits").T, needs.transpose(2, 1, 0), units.T, valid.T, nodes, full=whole, single=single)


def net_of(profit: np.ndarray, needs: np.ndarray, prices: np.ndarray, skip: int | None = None) -> np.ndarray:
    """profit minus priced needs, left to right (without knapsack `skip`)."""
    out = profit.copy(order="K")
    for k in range(needs.shape[-1]):
        if k != skip:
            out -= prices[k] * needs[..., k]
    return out


def greedy(net: np.ndarray, units: np.ndarray | None, levels: list[tuple[np.ndarray, np.ndarray]], least: np.ndarray | float = 0.0) -> np.ndarray:
    """Units taken of each item: items by net descending (ties by place), each as far as every cap set that
    holds it has room. Optimal for nested or disjoint sets. net, units and nodes: rows x items; units None: all are 1,
    and nets where there is no item aren't positive."""
    rows, m = net.shape
    good = net > least
    if units is None:
        if not levels:
            return good
        if m <= MOST_PAIRED:
            return paired(net, good, levels)
        units = np.ones(net.shape, dtype=np.int64)
    if not levels:
        return np.where(good, units, 0)
    if m <= MOST_PAIRED and int(units.max(initial=0)) <= 1:
        return paired(net, good & (units > 0), levels)
    order = np.argsort(-net, axis=1, kind="stable")
    take = np.zeros((rows, m), dtype=np.int64)
    if len(levels) == 1 and levels[0][1].size == 1 and not (levels[0][0] < 0).any() and int(units.max(initial=0)) <= 1:
        cap = int(levels[0][1][0])
        top = order[:, :cap]
        np.put_along_axis(take, top, np.take_along_axis(np.where(good, units, 0), top, axis=1), axis=1)
        return take
    room = [np.broadcast_to(np.append(caps, np.iinfo(np.int64).max), (rows, caps.size + 1)).copy() for _, caps in levels]
    whole = [left for (node, caps), left in zip(levels, room, strict=True) if caps.size == 1 and not (node < 0).any()]
    r = np.arange(rows)
    for place in range(m):
        # nets fall: a row ends at its first that isn't positive, or once a cap over all items is used up
        j = order[r, place]
        open_ = net[r, j] > 0
        for left in whole:
            open_ &= left[r, 0] > 0
        r, j = r[open_], j[open_]
        if not r.size:
            break
        amount = np.where(good[r, j], units[r, j], 0)
        at = [np.where(node[r, j] < 0, left.shape[1] - 1, node[r, j]) for (node, _), left in zip(levels, room, strict=True)]
        for n, left in zip(at, room, strict=True):
            amount = np.minimum(amount, left[r, n])
        for n, left in zip(at, room, strict=True):
            left[r, n] -= np.where(n == left.shape[1] - 1, 0, amount)
        take[r, j] = amount
    return take


def whole_group(node: np.ndarray, caps: np.ndarray) -> bool:
    """Whether a level is one set of all items."""
    return caps.size == 1 and (node.size > 0 and node[0, 0] >= 0 if node.strides == (0, 0) else not (node < 0).any())


def paired(net: np.ndarray, good: np.ndarray, levels: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """The same for single units and nested sets: level by level, bottom-up, an item stays if fewer than cap of the
    items left in its set come before it. Items are compared with all others, all groups at once, one bit a group."""
    n, m, groups = net.T, net.shape[1], net.shape[0]
    good = good.T
    kept: np.ndarray | None = None
    before: np.ndarray | None = None
    for level in levels:
        node, caps = level
        if caps.min() >= m:
            continue
        if kept is None and whole_group(node, caps) and caps[0] == 1:
            good = _best(n, good)
            continue
        kept = np.packbits(good, axis=1) if kept is None else kept
        before = _before(n, kept.shape[1]) if before is None else before
        out = np.zeros(kept.shape, dtype=np.uint8)
        for c, same in (level.same if isinstance(level, Level) else Level(level).same).items():
            # planes[q, j]: whether more than q of the items left in its set come before item j
            planes = np.zeros((c, *kept.shape), dtype=np.uint8)
            for i in range(m):
                ahead = before[i] & kept[i]
                if same is not None:
                    ahead &= same[i]
                for q in range(c - 1, 0, -1):
                    planes[q] |= planes[q - 1] & ahead
                planes[0] |= ahead
            out |= planes[c - 1]
        kept &= ~out
    return good.T if kept is None else np.unpackbits(kept, axis=1, count=groups).view(bool).T


def _before(n: np.ndarray, size: int) -> np.ndarray:
    """[i, j]: whether item i comes before item j, one bit a group."""
    m = n.shape[0]
    out = np.zeros((m, m, size), dtype=np.uint8)
    for i in range(m - 1):
        out[i, i + 1 :] = np.packbits(n[i] >= n[i + 1 :], axis=1)
        np.invert(out[i, i + 1 :], out=out[i + 1 :, i])
    return out


class Level(tuple):
    """(node of each item or -1, cap of each node), and which items share a node, by the node's cap."""

    @cached_property
    def same(self) -> dict[int, np.ndarray | None]:
        """By cap: [i, j], whether items i and j share a node of that cap, one bit a group; None: everywhere. Caps that no
        node can reach are left out."""
        node, caps = self
        m = node.shape[1]
        if whole_group(node, caps):
            return {int(caps[0]): None} if caps[0] < m else {}
        out: dict[int, np.ndarray | None] = {}
        for c in np.unique(caps[caps < m]).tolist():
            inside = node.T if (caps == c).all() else np.where((np.append(caps, -1) == c)[node.T], node.T, -1)
            some = inside >= 0
            out[c] = np.stack([np.packbits((inside[i] == inside) & some, axis=1) for i in range(m)])
        return out


def _best(n: np.ndarray, good: np.ndarray) -> np.ndarray:
    """Of the good items, the first of largest positive net."""
    best, place = np.zeros(n.shape[1]), np.full(n.shape[1], -1, dtype=np.int8)
    for j in range(n.shape[0]):
        better = (n[j] > best) & good[j]
        np.copyto(best, n[j], where=better)
        np.copyto(place, j, where=better)
    return place[None, :] == np.arange(n.shape[0], dtype=np.int8)[:, None]


def margins(net: np.ndarray, take: np.ndarray, valid: np.ndarray, levels: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """How far each group's nets (of single units, under nested sets) and differences of its nets may move before what it
    takes can change. An item that is left out stays out as long as its net isn't positive, or all items taken in the
    smallest full set around it are worth more; one that is taken stays as long as its net is positive."""
    n, t = net.T, take.T
    m = n.shape[0]
    worth = np.where(t, n, np.inf)
    rival, bound = np.zeros(n.shape), np.zeros(n.shape, dtype=bool)
    for node, caps in levels:
        if caps.min() >= m:
            continue
        if whole_group(node, caps):
            tight = ~bound & (t.sum(axis=0, dtype=np.int16) >= caps[0])
            np.copyto(rival, worth.min(axis=0), where=tight)
            bound |= tight
            continue
        place = node.T
        for j in range(m):
            some = np.flatnonzero(~t[j] & ~bound[j] & (place[j] >= 0))
            if not some.size:
                continue
            same = place[:, some] == place[j, some]
            tight = (same & t[:, some]).sum(axis=0, dtype=np.int16) >= np.append(caps, 0)[place[j, some]]
            some, same = some[tight], same[:, tight]
            rival[j, some] = np.where(same, worth[:, some], np.inf).min(axis=0)
            bound[j, some] = True
    slack = np.where(t, n, rival - n)
    return slack.min(axis=0) if valid.all() else np.where(valid.T, slack, np.inf).min(axis=0)


def candidates(intercept: np.ndarray, slope: np.ndarray) -> np.ndarray:
    """Critical prices of one knapsack (rows x C), descending, 0 where there is none: zero crossings of the
    items' lines and crossings of every two lines, those that are finite and positive."""
    m = intercept.shape[1]
    a, b = np.triu_indices(m, 1)
    with np.errstate(divide="ignore", invalid="ignore"):
        zero = np.where(slope > 0, intercept / slope, 0.0)
        rise = slope[:, a] - slope[:, b]
        cross = np.where(rise != 0, (intercept[:, a] - intercept[:, b]) / rise, 0.0)
    c = np.concatenate([zero, cross], axis=1)
    c[~np.isfinite(c) | (c <= 0)] = 0.0
    return -np.sort(-c, axis=1)


def emissions(block: Block, prices: np.ndarray, k: int, levels: list[tuple[np.ndarray, np.ndarray]], eval_at: str = "segment", window: tuple[float, float] | None = None, needs: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(v1, v2) of all groups of the block: lowering the price of knapsack k below v1 raises its use by v2.

    The solution is constant between two neighbouring candidates and is evaluated at the middle ('segment'),
    or, as an ablation, at the candidate itself ('point'). With a window (low, high], only candidates in it
    are evaluated one by one; all use that comes above it counts at the lowest candidate above it."""
    needs = block.dense(prices.size) if needs is None else needs
    slope = needs[:, :, k]
    intercept = block.priced(net_of(block.profit, needs, prices, skip=k))
    if window is not None:
        return _window_emissions(intercept, slope, block, levels, window)
    return _emissions(intercept, slope, block.valid, block.amounts, levels, eval_at)


class Settled:
    """What a block takes at some prices, and by how much of one price each group would have to be moved to take anything
    else: a window around the price then needs a look at few groups."""

    def __init__(self, block: Block, prices: np.ndarray, levels: list[tuple[np.ndarray, np.ndarray]], net: np.ndarray, take: np.ndarray, needs: np.ndarray):
        self.block, self.prices, self.levels, self.take, self.needs = block, prices, levels, take, needs
        self.margin = margins(net, take, block.valid, levels) - 1e-9 * float(block.profit.max(initial=1.0))

    @staticmethod
    def fits(block: Block) -> bool:
        return block.single and block.ids.shape[1] <= MOST_PAIRED

    def emissions(self, x: int, window: tuple[float, float]) -> tuple[np.ndarray, np.ndarray]:
        """emissions() of knapsack x with a window that holds its price."""
        low, high = window
        slope = self.needs[:, :, x]
        above = max(high * (1 + 1e-12), np.nextafter(high, np.inf))
        far = max(above - self.prices[x], self.prices[x] - low) * (1 + 1e-9)
        moves = ~(self.margin > far * slope.max(axis=1))
        used = np.where(moves, 0.0, used_of(self.take, slope))
        still = used[used > 0]
        rows = np.flatnonzero(moves)
        levels = [of_rows(level, rows) for level in self.levels]
        v1, v2 = emissions(self.block.part(rows), self.prices, x, levels, "segment", window)
        return np.concatenate([np.full(still.size, above), v1]), np.concatenate([still, v2])


def _window_emissions(intercept: np.ndarray, slope: np.ndarray, block: Block, levels: list[tuple[np.ndarray, np.ndarray]], window: tuple[float, float]) -> tuple[np.ndarray, np.ndarray]:
    """Use never falls as the price does: groups that use the same just above the window and at its lower end have
    no emission in it. The critical prices of all others are looked at."""
    low, high = window
    at_low = used_of(greedy(block.priced(intercept - low * slope), block.amounts, levels), slope)
    if high < np.inf:
        above = max(high * (1 + 1e-12), np.nextafter(high, np.inf))
        over = used_of(greedy(block.priced(intercept - above * slope), block.amounts, levels), slope)
    else:
        above, over = np.inf, np.zeros(at_low.size)
    moved = np.flatnonzero(at_low != over)
    still = over[(at_low == over) & (over > 0)]
    units, parts = block.amounts, [(np.full(still.size, above), still)]
    step = max(1, BLOCK_BYTES // (24 * slope.shape[1] * (slope.shape[1] + 1)))
    for s in range(0, max(1, moved.size), step):
        some = moved[s : s + step]
        parts.append(_emissions(picked(intercept, some), picked(slope, some), picked(block.valid, some), None if units is None else picked(units, some), [of_rows(level, some) for level in levels], "segment", window))
    v1, v2 = (np.concatenate(x) for x in zip(*parts, strict=True))
    return v1, v2


def _emissions(intercept: np.ndarray, slope: np.ndarray, valid: np.ndarray, units: np.ndarray | None, levels: list[tuple[np.ndarray, np.ndarray]], eval_at: str, window: tuple[float, float] | None = None) -> tuple[np.ndarray, np.ndarray]:
    c = candidates(intercept, np.where(valid, slope, 0.0))
    if window is not None:
        # few columns hold all that is left: candidates above the window but the lowest, and below it, go
        low, high = window
        first = np.maximum((c > high).sum(axis=1) - 1, 0)
        # one column for the lowest above, and one below the window, where the last segment ends
        at = first[:, None] + np.arange(int(((c > low) & (c <= high)).sum(axis=1).max(initial=0)) + 2)[None, :]
        c = np.where(at < c.shape[1], np.take_along_axis(c, np.minimum(at, c.shape[1] - 1), axis=1), 0.0)
    rows, width = c.shape
    lower = np.concatenate([c[:, 1:], np.zeros((rows, 1))], axis=1)
    last = (c > lower) & (c > 0)  # the last of equal candidates
    if window is not None:
        last &= c > low
    probe = (c + lower) / 2 if eval_at == "segment" else c
    r, i = np.nonzero(last)
    if not r.size:
        return np.zeros(0), np.zeros(0)
    out_use = np.zeros((rows, width))
    step = max(1, BLOCK_BYTES // (32 * max(1, valid.shape[1])))
    for s in range(0, r.size, step):
        rr, ii = r[s : s + step], i[s : s + step]
        own = picked(slope, rr)
        net = picked(intercept, rr) - probe[rr, ii][:, None] * own
        net[~picked(valid, rr)] = -1.0
        take = greedy(net, None if units is None else picked(units, rr), [of_rows(level, rr) for level in levels])
        out_use[rr, ii] = used_of(take, own)
    before = np.maximum.accumulate(np.concatenate([np.zeros((rows, 1)), out_use[:, :-1]], axis=1), axis=1)
    grown = out_use - before
    keep = last & (grown > 0)
    return c[keep], grown[keep]


def use_at(block: Block, prices: np.ndarray, k: int, levels: list[tuple[np.ndarray, np.ndarray]], grid: list[float], needs: np.ndarray) -> np.ndarray:
    """Use of knapsack k by all groups of the block at each of its prices of the grid."""
    slope = needs[:, :, k]
    intercept = net_of(block.profit, needs, prices, skip=k)
    return np.array([total_of(greedy(block.priced(intercept - x * slope), block.amounts, levels).astype(float), slope) for x in grid])


def linear_emissions(profit: np.ndarray, need: np.ndarray, adjusted: np.ndarray, q: int) -> tuple[np.ndarray, np.ndarray]:
    """Sparse one-to-one case with one cap q: (mask, v1) by selection of the q-th and (q+1)-th value."""
    m = adjusted.shape[1]
    padded = np.concatenate([adjusted, np.zeros((adjusted.shape[0], max(0, q + 1 - m)))], axis=1)
    part = -np.partition(-padded, (q - 1, q), axis=1)
    qth, next_ = part[:, q - 1 : q], part[:, q : q + 1]
    rival = np.where(adjusted >= qth, next_, qth)
    ok = (profit > rival) & (need > 0)
    with np.errstate(divide="ignore", invalid="ignore"):
        return ok, np.where(ok, (profit - rival) / need, 0.0)


def linear_block(block: Block, prices: np.ndarray, q: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(knapsack from 1, v1, v2) of a block of a sparse problem by the linear-time map."""
    price = np.append(0.0, prices)[block.knapsack]
    adjusted = np.where(block.valid, np.maximum(block.profit - price * block.need, 0.0), 0.0)
    ok, v1 = linear_emissions(block.profit, block.need, adjusted, q)
    return block.knapsack[ok], v1[ok], block.need[ok]


@dataclass(frozen=True)
class Buckets:
    """How critical prices of one knapsack are counted. 'uneven': smallest next to `price` and growing
    exponentially with the distance, in units of `delta`; 'even': of `width` from `low` on; 'value': each
    price by itself. Only prices within [low, high] count; all those above `top` share one bucket."""

    kind: str
    price: float = 0.0
    delta: float = 1.0
    base: float | None = None
    shifted: bool = False
    width: float = 1.0
    low: float = 0.0
    high: float = float("inf")
    top: float = float("inf")

    def of(self, v: np.ndarray) -> np.ndarray:
        return np.where(v > self.top, np.iinfo(np.int64).max, self._of(v))  # which is no price's bits

    def _of(self, v: np.ndarray) -> np.ndarray:
        if self.kind == "value":
            return np.ascontiguousarray(v).view(np.int64)  # positive doubles order as their bits do
        if self.kind == "even":
            return np.floor((v - self.low) / self.width).astype(np.int64)
        d = v - self.price
        ratio = np.abs(d) / self.delta
        steps = np.log(np.maximum(ratio, 1.0))
        steps = np.floor(steps if self.base is None else steps / np.log(self.base))
        if self.shifted:
            steps = np.where(ratio < 1.0, 0, steps + 1)
        return (np.sign(d) * steps).astype(np.int64)


class Histogram:
    """mass, smallest and largest price, and number of the emissions of each bucket."""

    MOST_PENDING = 1 << 16

    def __init__(self, buckets: Buckets):
        self.buckets = buckets
        self.rows = [np.zeros(0, np.int64), np.zeros(0), np.zeros(0), np.zeros(0), np.zeros(0, np.int64)]
        self.pending: list[list[np.ndarray]] = []
        self.size = 0

    def add(self, v1: np.ndarray, v2: np.ndarray) -> None:
        keep = (v1 >= self.buckets.low) & (v1 <= self.buckets.high)
        v1, v2 = v1[keep], v2[keep]
        top = v1 > self.buckets.top
        if top.any():
            self.pending.append([self.buckets.of(v1[top][:1]), v2[top].sum()[None], v1[top].min()[None], v1[top].max()[None], np.array([top.sum()], dtype=np.int64)])
            v1, v2 = v1[~top], v2[~top]
            self.size += 1
        if v1.size:
            self.pending.append([self.buckets.of(v1), v2, v1, v1, np.ones(v1.size, dtype=np.int64)])
            self.size += v1.size
            if self.size > self.MOST_PENDING:
                self.merge()

    def merge(self) -> list[np.ndarray]:
        if self.pending:
            bucket, mass, lo, hi, n = (np.concatenate(x) for x in zip(self.rows, *self.pending, strict=True))
            order = np.argsort(bucket, kind="stable")
            head = np.flatnonzero(np.diff(bucket[order], prepend=bucket[order][0] - 1))
            self.rows = [bucket[order][head], np.add.reduceat(mass[order], head), np.minimum.reduceat(lo[order], head), np.maximum.reduceat(hi[order], head), np.add.reduceat(n[order], head)]
            self.pending, self.size = [], 0
        return self.rows
