"""All models of a few items: decomposable families (K <= 6) and general ones (K <= 4)."""

from __future__ import annotations

from functools import cache
from itertools import combinations, permutations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .family import closure, cliques, is_chordal


def pair_list(k: int) -> list[tuple[int, int]]:
    """Pairs of items (from 0) in the order of their bits in a graph number."""
    return list(combinations(range(k), 2))


def pair_bits(k: int) -> dict[frozenset, int]:
    return {frozenset(p): 1 << i for i, p in enumerate(pair_list(k))}


def edge_mask(itemset: int, k: int) -> int:
    """Graph number of all pairs inside an itemset."""
    at = pair_bits(k)
    inside = [i for i in range(k) if itemset >> i & 1]
    return sum(at[frozenset(p)] for p in combinations(inside, 2))


def chordless_cycles(k: int) -> list[tuple[int, int]]:
    """(pairs among the cycle's items, pairs of the cycle) for every cycle of four or more items."""
    at, made = pair_bits(k), set()
    for n in range(4, k + 1):
        for items in combinations(range(k), n):
            for rest in permutations(items[1:]):
                if rest[0] < rest[-1]:
                    ring = (items[0], *rest)
                    cycle = sum(at[frozenset((ring[i], ring[(i + 1) % n]))] for i in range(n))
                    made.add((sum(at[frozenset(p)] for p in combinations(items, 2)), cycle))
    return sorted(made)


@cache
def decomposable(k: int) -> list[list[int]]:
    """Maximal sets of every decomposable family of k items, by graph number."""
    found = []
    pairs = pair_list(k)
    for g in range(1 << len(pairs)):
        graph = {1 << i: 0 for i in range(k)}
        for n, (i, j) in enumerate(pairs):
            if g >> n & 1:
                graph[1 << i] |= 1 << j
                graph[1 << j] |= 1 << i
        if is_chordal(graph):
            found.append(cliques(graph))
    return found


@cache
def general(k: int) -> list[frozenset]:
    """Every downward-closed family of k <= 4 items that holds all single items, as sets of members."""
    if k > 4:
        raise ValueError("general families are enumerated for up to 4 items")
    single = closure(1 << i for i in range(k))
    found = {frozenset(single)}
    edge = [frozenset(single)]
    while edge:
        new = []
        for f in edge:
            for m in range(1, 1 << k):
                if m not in f and all(m ^ (1 << i) in f for i in range(k) if m >> i & 1):
                    g = f | {m}
                    if g not in found:
                        found.add(g)
                        new.append(g)
        edge = new
    return sorted(found, key=lambda f: (len(f), sorted(f)))


def graphs(spark: SparkSession, k: int) -> DataFrame:
    """Graph numbers (g) of all decomposable families: all graphs but those with a chordless cycle."""
    every = spark.range(1 << len(pair_list(k))).select(F.col("id").alias("g"))
    rings = chordless_cycles(k)
    if not rings:
        return every
    cycles = spark.createDataFrame(rings, "pairs bigint, cycle bigint")
    return every.join(F.broadcast(cycles), F.col("g").bitwiseAND(F.col("pairs")) == F.col("cycle"), "left_anti")


def itemset_edges(spark: SparkSession, k: int) -> DataFrame:
    """(mask, size, edges): an itemset belongs to graph g iff g holds all its edges."""
    return spark.createDataFrame([(m, m.bit_count(), edge_mask(m, k)) for m in range(1, 1 << k)], "mask bigint, size int, edges bigint")
