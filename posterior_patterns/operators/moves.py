"""Merges and splits between decomposable families, computed afresh from the maximal sets."""

from __future__ import annotations

from itertools import combinations

from .family import bits, is_decomposable, junction_tree, maximal


def merge(maxs: list[int], s: int, x: int, y: int) -> list[int]:
    """Add s with x and y, and all subsets."""
    return maximal([*maxs, s | x | y])


def split(maxs: list[int], whole: int, x: int, y: int) -> list[int]:
    """Drop the sets of `whole` that hold both x and y."""
    return maximal([m for m in maxs if m != whole] + [whole & ~x, whole & ~y])


def occurrence(maxs: list[int]) -> dict[int, int]:
    """Pair mask -> number of maximal sets that hold it."""
    made: dict[int, int] = {}
    for m in maxs:
        for a, b in combinations(bits(m), 2):
            made[a | b] = made.get(a | b, 0) + 1
    return made


def legal_splits(maxs: list[int]) -> list[tuple[int, int, int]]:
    """(set, x, y) with x and y together in that maximal set only."""
    once = {p for p, n in occurrence(maxs).items() if n == 1}
    return sorted((m, a, b) for m in maxs for a, b in combinations(bits(m), 2) if a | b in once)


def reduced_family(maxs: list[int], s: int) -> list[int]:
    """Components of the strict supersets of s after s is taken away."""
    parts: list[int] = []
    for m in maxs:
        if m & s == s and m != s:
            piece, apart = m & ~s, []
            for p in parts:
                if p & piece:
                    piece |= p
                else:
                    apart.append(p)
            parts = [*apart, piece]
    return sorted(parts, key=lambda p: p & -p)


def pair_count(parts: list[int]) -> int:
    """Pairs of items in different components."""
    made = total = 0
    for p in parts:
        n = p.bit_count()
        made += total * n
        total += n
    return made


def joints(maxs: list[int]) -> dict[int, list[int]]:
    """Sets under which a merge exists, with their components: all are junction-tree intersections."""
    found = {s for *_, s in junction_tree(maxs)}
    made = {s: reduced_family(maxs, s) for s in sorted(found)}
    return {s: parts for s, parts in made.items() if len(parts) > 1}


def legal_merges(maxs: list[int]) -> list[tuple[int, int, int]]:
    """(s, x, y) with x < y in different components under s."""
    made = []
    for s, parts in joints(maxs).items():
        for v, w in combinations(parts, 2):
            made += [(s, min(x, y), max(x, y)) for x in bits(v) for y in bits(w)]
    return sorted(made)


def degrees(maxs: list[int]) -> tuple[int, int, int]:
    """(number of legal splits, of legal merges, of both)."""
    sd = sum(n == 1 for n in occurrence(maxs).values())
    md = sum(pair_count(parts) for parts in joints(maxs).values())
    return sd, md, sd + md


def path_to_independence(maxs: list[int]) -> list[tuple[int, int, int]]:
    """Splits that lead to the family of single items, every family on the way decomposable."""
    made, now = [], maxs
    while options := legal_splits(now):
        step = max(options, key=lambda o: (o[0].bit_count(), o))
        made.append(step)
        now = split(now, *step)
    return made


def neighbours_by_flip(maxs: list[int], k: int) -> list[list[int]]:
    """Decomposable families one pair away, found by trying every pair of the graph."""
    from .family import cliques, is_chordal, neighbours

    graph = {1 << i: 0 for i in range(k)} | neighbours(maxs)
    made = []
    for i, j in combinations(range(k), 2):
        flipped = dict(graph)
        flipped[1 << i] ^= 1 << j
        flipped[1 << j] ^= 1 << i
        if is_chordal(flipped):
            made.append(cliques(flipped))
    assert all(map(is_decomposable, made))
    return made
