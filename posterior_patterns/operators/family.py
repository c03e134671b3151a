"""Families of itemsets as models: closure, maximal sets, junction trees, chordality.

An itemset is an int whose bit i-1 is item i.  A family is named by its maximal sets.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable, Iterator


def bits(mask: int) -> Iterator[int]:
    """Single-bit masks of a set, ascending."""
    while mask:
        low = mask & -mask
        yield low
        mask ^= low


def items_of(mask: int) -> list[int]:
    return [b.bit_length() for b in bits(mask)]


def mask_of(items: Iterable[int]) -> int:
    made = 0
    for i in items:
        made |= 1 << (i - 1)
    return made


def canonical(mask: int) -> str:
    """Item ids, ascending, joined by '-'."""
    return "-".join(map(str, items_of(mask)))


def subsets(mask: int) -> Iterator[int]:
    """All subsets of a set, the empty one last."""
    sub = mask
    while sub:
        yield sub
        sub = (sub - 1) & mask
    yield 0


def closure(sets: Iterable[int]) -> set[int]:
    """The downward-closed family the sets generate; the empty set belongs to it."""
    made = {0}
    for m in sets:
        made.update(subsets(m))
    return made


def is_downward_closed(family: Iterable[int]) -> bool:
    held = set(family) | {0}
    return all(m ^ b in held for m in held for b in bits(m))


def maximal(family: Iterable[int]) -> list[int]:
    kept: list[int] = []
    for m in sorted(set(family), key=lambda m: -m.bit_count()):
        if m and not any(m & k == m for k in kept):
            kept.append(m)
    return sorted(kept)


def singletons(k: int) -> list[int]:
    return [1 << i for i in range(k)]


def saturated(k: int) -> list[int]:
    return [(1 << k) - 1]


def tree(k: int, edges: Iterable[tuple[int, int]]) -> list[int]:
    """A forest of item pairs (1-based); items without an edge stay alone."""
    pairs = [mask_of(e) for e in edges]
    return maximal(pairs + singletons(k))


def all_pairs(k: int) -> list[int]:
    return maximal([1 << i | 1 << j for i in range(k) for j in range(i)] + singletons(k))


def best_tree(weights: dict[tuple[int, int], float], k: int) -> list[tuple[int, int]]:
    """Edges of a spanning tree of greatest weight; ties go to the smaller pair."""
    home, made = list(range(k + 1)), []

    def find(x: int) -> int:
        while home[x] != x:
            home[x] = home[home[x]]
            x = home[x]
        return x

    for (a, b), _ in sorted(weights.items(), key=lambda e: (-e[1], e[0])):
        ra, rb = find(a), find(b)
        if ra != rb:
            home[ra] = rb
            made.append((min(a, b), max(a, b)))
    return sorted(made)


def junction_tree(maxs: list[int]) -> list[tuple[int, int, int]]:
    """Edges (i, j, intersection) of a spanning tree of greatest total intersection over the maximal sets."""
    if not maxs:
        return []
    best = {j: ((maxs[0] & maxs[j]).bit_count(), 0) for j in range(1, len(maxs))}
    edges = []
    while best:
        j = max(best, key=lambda x: (best[x][0], -x))
        _, i = best.pop(j)
        edges.append((i, j, maxs[i] & maxs[j]))
        for other in best:
            w = (maxs[j] & maxs[other]).bit_count()
            if w > best[other][0]:
                best[other] = (w, j)
    return edges


def is_decomposable(maxs: list[int]) -> bool:
    """A junction tree exists iff the best spanning tree's intersections add up to all repeated memberships."""
    union = 0
    for m in maxs:
        union |= m
    return sum(s.bit_count() for *_, s in junction_tree(maxs)) == sum(m.bit_count() for m in maxs) - union.bit_count()


def neighbours(maxs: Iterable[int]) -> dict[int, int]:
    """Item bit -> mask of the items it shares a set with."""
    made: dict[int, int] = {}
    for m in maxs:
        for b in bits(m):
            made[b] = made.get(b, 0) | m
    return {b: m & ~b for b, m in made.items()}


def is_chordal(adjacent: dict[int, int]) -> bool:
    """Repeatedly remove an item whose neighbours are all linked."""
    left = dict(adjacent)
    while left:
        for b, near in left.items():
            if all(near & ~left[c] & ~c == 0 for c in bits(near)):
                break
        else:
            return False
        del left[b]
        for c in bits(near):
            left[c] &= ~b
    return True


def cliques(adjacent: dict[int, int]) -> list[int]:
    """Maximal cliques of a chordal graph, by the same elimination."""
    left, found = dict(adjacent), []
    while left:
        b, near = next((b, near) for b, near in left.items() if all(near & ~left[c] & ~c == 0 for c in bits(near)))
        found.append(near | b)
        del left[b]
        for c in bits(near):
            left[c] &= ~b
    return maximal(found)


def is_decomposable_by_elimination(maxs: list[int]) -> bool:
    """Second test: the pair graph is chordal and the maximal sets are its cliques."""
    graph = neighbours(maxs)
    return is_chordal(graph) and cliques(graph) == maximal(maxs)


def separators(maxs: list[int]) -> Counter:
    """Multiset of junction-tree intersections; the same for every junction tree."""
    return Counter(s for *_, s in junction_tree(maxs))


def cycle_witness(maxs: list[int]) -> list[int] | None:
    """A ring of items without a chord, or three linked items outside every set; None if decomposable."""
    graph = neighbours(maxs)
    if not is_chordal(graph):
        for start in graph:
            for near in bits(graph[start]):
                # shortest way back from near to start that avoids start's other neighbours next to near
                for last in bits(graph[start] & ~near & ~graph[near]):
                    allowed = ~(graph[start] | start) | near | last
                    paths, seen = [[near]], near
                    while paths:
                        longer = []
                        for path in paths:
                            for step in bits(graph[path[-1]] & allowed & ~seen):
                                if step == last:
                                    return [start, *path, last]
                                seen |= step
                                longer.append([*path, step])
                        paths = longer
    for c in cliques(graph) if is_chordal(graph) else []:
        if not any(c & m == c for m in maxs):
            return list(bits(c))
    return None


def family_size(maxs: list[int]) -> int:
    """Members of a decomposable family, the empty set included."""
    return sum(1 << m.bit_count() for m in maxs) - sum(1 << s.bit_count() for *_, s in junction_tree(maxs))


def n_params(maxs: list[int]) -> int:
    return family_size(maxs) - 1
