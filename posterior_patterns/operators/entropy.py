"""Entropies of item projections, in nats, by four methods with one result.

hash_agg   one aggregation per itemset
batch      all itemsets in one pass over the patterns (the default elsewhere)
sort_scan  rows in the order of the projection, runs found by comparing with the row before; kept for
           comparison: it sorts whole patterns for every itemset
from_support   cells from subset supports by inclusion-exclusion, without a pass over the data
"""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .family import bits
from .patterns import BROADCAST_ITEMSETS, WORD_BITS, cells, cells_from_frequencies, submasks, support


def n_log_n(n: Column) -> Column:
    return F.when(n > 0, n * F.log(n)).otherwise(F.lit(0.0))


def _of_cells(found: DataFrame, key: str = "x") -> DataFrame:
    """H = log N - sum(n log n) / N; integers are summed before any division."""
    summed = found.groupBy(key).agg(F.sum("n").alias("rows"), F.sum(n_log_n(F.col("n"))).alias("s"))
    return summed.select(F.col(key).alias("mask"), F.bit_count(key).alias("size"), F.abs(F.log("rows") - F.col("s") / F.col("rows")).alias("h"))


def entropy(patterns: DataFrame, itemsets: DataFrame, method: str = "batch", k: int = 20) -> DataFrame:
    """(mask, size, h)."""
    if method == "batch":
        return _of_cells(cells(patterns, itemsets))
    if method == "hash_agg":
        made = None
        for row in itemsets.select("mask").toLocalIterator():
            one = patterns.groupBy(F.col("mask").bitwiseAND(F.lit(row.mask)).alias("cell")).agg(F.sum("n").alias("n")).withColumn("x", F.lit(row.mask).cast("bigint"))
            made = one if made is None else made.unionByName(one)
        return _of_cells(made)
    if method == "sort_scan":
        x = itemsets.select(F.col("mask").alias("x"))
        rows = patterns.crossJoin(F.broadcast(x)).select("x", F.col("mask").bitwiseAND(F.col("x")).alias("cell"), "n")
        order = Window.partitionBy("x").orderBy("cell")
        started = rows.withColumn("new", F.when(F.lag("cell").over(order) == F.col("cell"), 0).otherwise(1))
        runs = started.withColumn("run", F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, 0)))
        return _of_cells(runs.groupBy("x", "run").agg(F.sum("n").alias("n")))
    if method == "from_support":
        wanted = itemsets.select(F.explode(submasks(F.col("mask"), k)).alias("mask")).distinct().withColumn("size", F.bit_count("mask"))
        known = support(patterns, wanted)
        full = cells_from_frequencies(known, k)
        return _of_cells(full.join(itemsets.select(F.col("mask").alias("x")), "x", "left_semi"))
    raise ValueError(f"no such method: {method}")


def wide_entropy(patterns: DataFrame, wanted: DataFrame, words: int) -> DataFrame:
    """patterns(words, n) and wanted(m), masks as decimal strings -> (m, h), all in one pass."""

    @F.pandas_udf("array<bigint>")
    def cut(masks: pd.Series) -> pd.Series:
        low = (1 << WORD_BITS) - 1
        return masks.map(lambda m: [int(m) >> (WORD_BITS * i) & low for i in range(words)])

    sets = wanted.select("m", cut("m").alias("x"))
    sets = F.broadcast(sets) if wanted.count() <= BROADCAST_ITEMSETS else sets
    cell = F.zip_with("words", "x", lambda a, b: a.bitwiseAND(b))
    found = patterns.crossJoin(sets).select("m", cell.alias("cell"), "n").groupBy("m", "cell").agg(F.sum("n").alias("n"))
    summed = found.groupBy("m").agg(F.sum("n").alias("rows"), F.sum(n_log_n(F.col("n"))).alias("s"))
    return summed.select("m", F.abs(F.log("rows") - F.col("s") / F.col("rows")).alias("h"))


def projections(patterns: DataFrame, itemsets: DataFrame) -> DataFrame:
    """patterns(mask, n), small enough to be shipped, and distinct itemsets(mask) -> (mask, support, h), for itemsets by the million.

    A task sorts its itemsets and halves them again and again.  Each half is counted on the patterns cut down to the
    items that occur in it, made from those of the half above: neighbours in order share items, so few are left.
    """
    spark, wanted = patterns.sparkSession, itemsets.select("mask")
    got = patterns.select("mask", "n").toArrow()  # callers have checked the size
    shared = spark.sparkContext.broadcast((got.column("mask").to_numpy(), got.column("n").to_numpy().astype(float)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [batch.column(0).to_numpy() for batch in batches]
        if not parts or not sum(map(len, parts)):
            return
        masks = np.sort(np.concatenate(parts))
        support, h = np.zeros(len(masks), dtype=np.int64), np.zeros(len(masks))
        todo = [(0, len(masks), *shared.value)]
        while todo:
            low, high, cell, n = todo.pop()
            union = np.bitwise_or.reduce(masks[low:high])
            cell, at = np.unique(cell & union, return_inverse=True)
            n = np.bincount(at, n, len(cell))
            if high - low > 1:
                middle = (low + high) // 2
                todo += [(low, middle, cell, n), (middle, high, cell, n)]
            elif total := n.sum():
                some = n[n > 0]
                support[low] = round(n[cell == union].sum())
                h[low] = abs(np.log(total) - (some * np.log(some)).sum() / total)
        yield pa.RecordBatch.from_arrays([pa.array(masks), pa.array(support), pa.array(h)], names=["mask", "support", "h"])

    spread = wanted.repartitionByRange(max(spark.sparkContext.defaultParallelism * 4, 1), "mask")
    return spread.mapInArrow(run, "mask bigint, support bigint, h double")


def mobius_weights(entropies: DataFrame, n: int, k: int) -> DataFrame:
    """(mask, size, w): a model's BIC weight is the sum of w over the members of its family.

    w = -N * sum over subsets B of (-1)^(|C| - |B|) H(B), less half a log N for the member's parameter.
    """
    full = entropies.select("mask", "h")
    grid = full.select(F.col("mask").alias("c"), F.explode(submasks(F.col("mask"), k)).alias("mask"))
    signed = grid.join(full, "mask").select("c", F.when((F.bit_count("c") - F.bit_count("mask")) % 2 == 0, F.col("h")).otherwise(-F.col("h")).alias("h"))
    half = 0.5 * float(np.log(n)) if n > 0 else 0.0
    return signed.groupBy("c").agg(F.sum("h").alias("d")).select(F.col("c").alias("mask"), F.bit_count("c").alias("size"), (F.col("d") * F.lit(-float(n)) - F.lit(half)).alias("w"))


#: Patterns from which on columns are bits and counting by place costs more than a few passes over bits.
MANY = 1 << 15
#: Items of an itemset whose cells are found from supports of its subsets, mostly known from smaller itemsets.
BY_SUPPORT = 5


def _packed(flags: np.ndarray) -> np.ndarray:
    """Flags as bits of 64-bit words."""
    made = np.zeros(-(-len(flags) // 64) * 8, dtype=np.uint8)
    made[: -(-len(flags) // 8)] = np.packbits(flags.astype(bool), bitorder="little")
    return made.view(np.uint64)


class EntropyCache:
    """Entropies of projections of a pattern table that a task holds; least recently used ones go."""

    def __init__(self, masks, counts, capacity: int = 500_000):
        self.counts = np.asarray(counts, dtype=np.int64)
        self.n = float(self.counts.sum())
        self.wide = None
        if isinstance(masks, np.ndarray):
            if masks.ndim == 2:
                self.wide = masks
            else:
                self.masks = masks
        elif (masks := list(masks)) and max(masks) >> 62:
            words = (max(m.bit_length() for m in masks) + 61) // 62
            self.wide = np.array([[m >> (62 * i) & ((1 << 62) - 1) for i in range(words)] for m in masks], dtype=np.int64)
        else:
            self.masks = np.array(masks, dtype=np.int64)
        self.capacity, self.held, self.misses = capacity, OrderedDict(), 0
        # large counts first, so that the high bits of counts are those of a few leading patterns
        order = np.argsort(-self.counts, kind="stable")
        self.counts = self.counts[order]
        if self.wide is None:
            self.masks = self.masks[order]
        else:
            self.wide = self.wide[order]
        self.columns: dict[int, np.ndarray] = {}
        self.many = len(self.counts) > MANY
        self.supports: dict[int, int] = {0: int(self.counts.sum())}
        self.planes = [_packed(self.counts[: np.count_nonzero(self.counts >= 1 << b)] >> b & 1) for b in range(int(self.counts.max(initial=0)).bit_length())]

    def __call__(self, mask: int) -> float:
        found = self.held.get(mask)
        if found is not None:
            return found
        self.misses += 1
        value = self._compute(mask)
        self.held[mask] = value
        if len(self.held) > self.capacity:
            self.held.popitem(last=False)
        return value

    def _column(self, item: int) -> np.ndarray:
        """Whether each pattern holds an item: 0 or 1, or a bit where there are more than MANY patterns."""
        made = self.columns.get(item)
        if made is None:
            if self.wide is None:
                made = self.masks >> item & 1
            elif item // WORD_BITS < self.wide.shape[1]:
                made = self.wide[:, item // WORD_BITS] >> (item % WORD_BITS) & 1
            else:
                made = np.zeros(len(self.wide), dtype=np.int64)
            made = self.columns[item] = _packed(made) if self.many else made.astype(np.int16)
        return made

    def _support(self, mask: int) -> int:
        """Rows of the patterns that hold all items of a mask."""
        found = self.supports.get(mask)
        if found is None:
            both, rest = None, mask
            while rest:
                low = rest & -rest
                bit = self._column(low.bit_length() - 1)
                both, rest = bit if both is None else both & bit, rest ^ low
            found = sum(int(np.bitwise_count(both[: len(p)] & p).sum(dtype=np.int64)) << b for b, p in enumerate(self.planes))
            if len(self.supports) > self.capacity:
                self.supports = {0: self.supports[0]}
            self.supports[mask] = found
        return found

    def _compute(self, mask: int) -> float:
        if not mask or not self.n:
            return 0.0
        size = mask.bit_count()
        if self.many and size <= BY_SUPPORT:
            below = [0]
            for b in bits(mask):
                below += [m | b for m in below]
            sums = np.array([self._support(m) for m in below], dtype=float).reshape((2,) * size)
            for axis in range(size):  # rows with all of some items -> rows with these and no other
                without, held = (tuple(v if i == axis else slice(None) for i in range(size)) for v in (0, 1))
                sums[without] -= sums[held]
            sums = sums.ravel()
        elif size <= 14:  # count by place
            place = np.zeros(len(self.counts), dtype=np.int16)
            for at, b in enumerate(bits(mask)):
                bit = self._column(b.bit_length() - 1)
                if self.many:
                    bit = np.unpackbits(bit.view(np.uint8), count=len(place), bitorder="little").astype(np.int16)
                place += bit << at
            sums = np.bincount(place, self.counts)
        elif self.wide is None:
            sums = np.bincount(np.unique(self.masks & mask, return_inverse=True)[1], self.counts)
        else:
            place = np.zeros(len(self.wide), dtype=np.int64)
            for i in range(self.wide.shape[1]):
                part = self.wide[:, i] & (mask >> (WORD_BITS * i) & ((1 << WORD_BITS) - 1))
                place = np.unique(place * (len(self.wide) + 1) + np.unique(part, return_inverse=True)[1], return_inverse=True)[1]
            sums = np.bincount(place, self.counts)
        sums = sums[sums > 0]
        return abs(float(np.log(self.n) - (sums * np.log(sums)).sum() / self.n))


class EntropyTable:
    """Entropies computed before; asking for one that is missing names it."""

    class Missing(KeyError):
        pass

    def __init__(self, table: dict[int, float], n: int):
        self.table, self.n, self.misses = table, float(n), 0

    def __call__(self, mask: int) -> float:
        if not mask:
            return 0.0
        try:
            return self.table[mask]
        except KeyError:
            raise EntropyTable.Missing(mask) from None
