"""Local caps on item sets within a group, and their nesting."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class CapSet:
    """At most `cap` units of the items in `items` per group; items None means every item."""

    cap: int
    items: frozenset[int] | None = None


class Hierarchy:
    """Cap sets in bottom-up order. Equal sets are merged to the smaller cap, caps are floored."""

    def __init__(self, sets: list[CapSet]):
        best: dict[frozenset[int] | None, int] = {}
        for s in sets:
            cap = int(np.floor(s.cap))
            if cap <= 0:
                raise ValueError(f"caps must be positive, got {s.cap}")
            if s.items is not None and not s.items:
                raise ValueError("a cap set must hold items")
            best[s.items] = min(cap, best.get(s.items, cap))
        self.sets = sorted((CapSet(c, i) for i, c in best.items()), key=lambda s: (s.items is None, len(s.items or ()), sorted(s.items or ())))

    @classmethod
    def build(cls, caps: list[tuple[int, list[int] | None]]) -> Hierarchy:
        return cls([CapSet(c, None if i is None else frozenset(i)) for c, i in caps])

    @classmethod
    def root(cls, cap: int) -> Hierarchy:
        return cls([CapSet(cap)])

    @classmethod
    def none(cls) -> Hierarchy:
        return cls([])

    def is_laminar(self) -> bool:
        """Whether every two sets are nested or disjoint."""
        named = [s.items for s in self.sets if s.items is not None]
        return all(not (a & b) or a <= b or b <= a for i, a in enumerate(named) for b in named[i + 1 :])

    def is_disjoint(self) -> bool:
        named = [s.items for s in self.sets if s.items is not None]
        return all(not (a & b) for i, a in enumerate(named) for b in named[i + 1 :])

    def require_laminar(self) -> None:
        if not self.is_laminar():
            raise ValueError("cap sets cross: use the exact per-group solver")

    def heights(self) -> list[int]:
        """1 + the largest height of a strict subset; sets of one height are disjoint if laminar."""
        out: list[int] = []
        for k, s in enumerate(self.sets):
            below = [out[j] for j in range(k) if s.items is None or self.sets[j].items < s.items]
            out.append(1 + max(below, default=0))
        return out

    def topo(self) -> list[CapSet]:
        return list(self.sets)

    def levels(self) -> list[list[CapSet]]:
        heights = self.heights()
        return [[s for s, h in zip(self.sets, heights, strict=True) if h == level] for level in range(1, max(heights, default=0) + 1)]

    def masks(self, item_ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(sets x items membership, caps) for an array of item ids."""
        if not self.sets:
            return np.zeros((0, *item_ids.shape), dtype=bool), np.zeros(0, dtype=np.int64)
        member = [np.ones(item_ids.shape, dtype=bool) if s.items is None else np.isin(item_ids, sorted(s.items)) for s in self.sets]
        return np.stack(member), np.array([s.cap for s in self.sets], dtype=np.int64)

    def single_cap(self) -> int | None:
        """Q if the only cap is one over every item."""
        return self.sets[0].cap if len(self.sets) == 1 and self.sets[0].items is None else None

    def covers_all(self) -> bool:
        return any(s.items is None for s in self.sets)
