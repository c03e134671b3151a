"""State of one chain: maximal sets, pair counts, and components under joints, kept up to date by moves.

Only joints with two or more components are stored, at most items - 1 of them.  A move touches the
components under its own joint, under the joint with either item, and, by one item, under stored
joints inside; pair counts change in the sets the move adds and removes.  `rebuild=True` computes
everything from the maximal sets after each move; both give the same chain for the same numbers.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from itertools import combinations

from .family import bits
from .moves import joints, occurrence, pair_count, reduced_family


def _least(part: int) -> int:
    return part & -part


class ChainState:
    __slots__ = ("k", "maxs", "occ", "once", "parts", "weights", "md", "rebuild", "order", "merges")

    def __init__(self, k: int, maxs: list[int] | None = None, rebuild: bool = False):
        self.k, self.rebuild = k, rebuild
        self.maxs = set(maxs if maxs is not None else (1 << i for i in range(k)))
        self._all()

    def _all(self) -> None:
        listed = sorted(self.maxs)
        self.occ = occurrence(listed)
        self.once = sorted(p for p, n in self.occ.items() if n == 1)
        self.parts = joints(listed)
        self.weights = {s: pair_count(parts) for s, parts in self.parts.items()}
        self.md = sum(self.weights.values())
        self.order: list[int] | None = None  # joints in order, and the merges of those drawn from, until they change
        self.merges: dict[int, list[tuple[bool, int, int, int]]] = {}

    @property
    def degree(self) -> int:
        return len(self.once) + self.md

    # -- drawing -------------------------------------------------------------------------------

    def move(self, n: int) -> tuple[bool, int, int, int]:
        """Legal move number n in a fixed order: (is a merge, s, x, y); s lacks x and y."""
        if n < len(self.once):
            pair = self.once[n]
            whole = next(m for m in self.maxs if m & pair == pair)
            x = pair & -pair
            return False, whole & ~pair, x, pair ^ x
        n -= len(self.once)
        if self.order is None:
            self.order = sorted(self.parts)
        for s in self.order:
            count = self.weights[s]
            if n >= count:
                n -= count
                continue
            made = self.merges.get(s)
            if made is None:
                items = [list(bits(p)) for p in self.parts[s]]
                made = [(True, s, x, y) if x < y else (True, s, y, x) for v, w in combinations(items, 2) for x in v for y in w]
                self.merges[s] = made
            return made[n]
        raise IndexError("no such move")

    # -- moves ---------------------------------------------------------------------------------

    def merge(self, s: int, x: int, y: int) -> None:
        self._swap([m for m in (s | x, s | y) if m in self.maxs], [s | x | y])
        if self.rebuild:
            return
        self._join(s, x, y)
        self._extend(s, x, y)
        self._extend(s, y, x)

    def split(self, s: int, x: int, y: int) -> None:
        whole = s | x | y
        left = [m for m in (s | x, s | y) if m and not any(o != whole and o & m == m for o in self.maxs)]
        self._swap([whole], left)
        if self.rebuild:
            return
        self._put(s, reduced_family(list(self.maxs), s))
        self._shrink(s, x, y)
        self._shrink(s, y, x)

    def _swap(self, gone: list[int], new: list[int]) -> None:
        self.maxs.difference_update(gone)
        self.maxs.update(new)
        if self.rebuild:
            self._all()
            return
        for sets, by in ((gone, -1), (new, 1)):
            for m in sets:
                for a, b in combinations(bits(m), 2):
                    pair, old = a | b, self.occ.get(a | b, 0)
                    now = old + by
                    if now:
                        self.occ[pair] = now
                    else:
                        del self.occ[pair]
                    if old == 1:
                        del self.once[bisect_left(self.once, pair)]
                    if now == 1:
                        insort(self.once, pair)

    def _put(self, s: int, parts: list[int]) -> None:
        self.order = None
        self.merges.pop(s, None)
        if s in self.parts:
            del self.parts[s]
            self.md -= self.weights.pop(s)
        if len(parts) > 1:
            self.parts[s] = sorted(parts, key=_least)
            self.weights[s] = count = pair_count(parts)
            self.md += count

    def _join(self, s: int, x: int, y: int) -> None:
        """x's and y's components under s become one."""
        parts = self.parts[s]
        both = [p for p in parts if p & (x | y)]
        self._put(s, [p for p in parts if not p & (x | y)] + [both[0] | both[-1]])

    def _extend(self, s: int, x: int, y: int) -> None:
        """After a merge: x is new next to y."""
        own = s | y
        if own in self.parts:
            self._put(own, [*self.parts[own], x])
        else:  # not stored: it had one component or none
            self._put(own, reduced_family(list(self.maxs), own))
        for u in [u for u in self.parts if u & y and u != own and u & ~y & ~s == 0]:
            rest = s & ~u
            self._put(u, [p | x if p & rest else p for p in self.parts[u]])

    def _shrink(self, s: int, x: int, y: int) -> None:
        """After a split: x is no longer next to y."""
        own = s | y
        if own in self.parts:
            self._put(own, [p for p in self.parts[own] if p != x])
        for u in [u for u in self.parts if u & y and u != own and u & ~y & ~s == 0]:
            self._put(u, [p & ~x if p & x else p for p in self.parts[u]])
