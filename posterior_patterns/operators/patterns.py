"""Distinct transactions with their counts, and what is counted from them.

Every measure here is a function of pattern counts, so the rows of a data set are aggregated once
(map-side first, hence a pattern that dominates sparse data is no hot key) and never read again.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Itemsets that may be broadcast: 16 bytes each.
BROADCAST_ITEMSETS = 1_000_000
#: Items in a word of a wide transaction.
WORD_BITS = 62


def compress(baskets: DataFrame) -> DataFrame:
    """baskets(mask) or (words) -> distinct patterns with n."""
    key = "mask" if "mask" in baskets.columns else "words"
    return baskets.groupBy(key).agg(F.count("*").alias("n"))


def itemset_table(spark, masks: Iterable[int]) -> DataFrame:
    """Itemsets given on the driver, as (mask, size)."""
    rows = sorted(set(masks))
    return spark.createDataFrame([(m, m.bit_count()) for m in rows], "mask bigint, size int")


def label(mask: Column | str = "mask", k: int = 63) -> Column:
    """Item ids of a mask, ascending, joined by '-'."""
    col = F.col(mask) if isinstance(mask, str) else mask
    kept = F.filter(F.sequence(F.lit(1), F.lit(k)), lambda i: F.getbit(col, i - 1) == 1)
    return F.array_join(F.transform(kept, lambda i: i.cast("string")), "-")


def _small(itemsets: DataFrame) -> DataFrame:
    return F.broadcast(itemsets) if itemsets.count() <= BROADCAST_ITEMSETS else itemsets


def _bit(at: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("bigint"), at)


def single_items(spark, k: int) -> DataFrame:
    """(mask, size, top): the single items; top is the number of the greatest item, from 0."""
    return spark.range(k).select(_bit(F.col("id").cast("int")).alias("mask"), F.lit(1).alias("size"), F.col("id").cast("int").alias("top"))


def next_level(kept: DataFrame, k: int) -> DataFrame:
    """kept(mask, size, top) of one size -> the itemsets one larger all of whose subsets are kept."""
    rest = kept.select("mask", "size", "top", F.col("mask").bitwiseXOR(_bit(F.col("top"))).alias("rest"))
    other = rest.select("rest", F.col("top").alias("new"))
    grown = rest.join(other, "rest").filter("new > top").select(F.col("mask").bitwiseOR(_bit(F.col("new"))).alias("mask"), (F.col("size") + 1).alias("size"), F.col("new").alias("top"))
    below = F.filter(F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.when(F.getbit("mask", i) == 1, F.col("mask").bitwiseXOR(_bit(i)))), lambda m: m.isNotNull())
    met = grown.select("mask", "size", "top", F.explode(below).alias("sub")).join(kept.select(F.col("mask").alias("sub")), "sub", "left_semi")
    return met.groupBy("mask", "size", "top").agg(F.count("*").alias("held")).filter("held = size").select("mask", "size", "top")


def total(patterns: DataFrame) -> int:
    return int(patterns.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first().n)


def support(patterns: DataFrame, itemsets: DataFrame) -> DataFrame:
    """(mask, size, support): rows whose pattern holds the whole itemset; itemsets never met have 0."""
    x = itemsets.select(F.col("mask").alias("x"), "size")
    met = patterns.join(_small(x), (F.col("mask").bitwiseAND(F.col("x"))) == F.col("x")).groupBy("x").agg(F.sum("n").alias("support"))
    return x.join(met, "x", "left").select(F.col("x").alias("mask"), "size", F.coalesce("support", F.lit(0)).cast("bigint").alias("support"))


def frequency(patterns: DataFrame, itemsets: DataFrame) -> DataFrame:
    """(mask, size, support, fr)."""
    n = patterns.agg(F.sum("n").alias("rows"))
    return support(patterns, itemsets).crossJoin(F.broadcast(n)).select("mask", "size", "support", (F.col("support") / F.col("rows")).alias("fr"))


def cells(patterns: DataFrame, itemsets: DataFrame) -> DataFrame:
    """(x, size, cell, n): the occupied cells of each itemset's contingency table."""
    x = itemsets.select(F.col("mask").alias("x"), "size")
    projected = patterns.crossJoin(_small(x)).select("x", "size", F.col("mask").bitwiseAND(F.col("x")).alias("cell"), "n")
    return projected.groupBy("x", "size", "cell").agg(F.sum("n").alias("n"))


def submasks(mask: Column, k: int) -> Column:
    """All subsets of a mask of at most k items, as an array."""
    empty = F.array(F.lit(0).cast("bigint"))
    return F.aggregate(F.sequence(F.lit(0), F.lit(k - 1)), empty, lambda acc, i: F.when(F.getbit(mask, i) == 1, F.concat(acc, F.transform(acc, lambda s: s.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), i))))).otherwise(acc))


def cells_from_frequencies(supports: DataFrame, k: int) -> DataFrame:
    """(x, cell, n) by inclusion-exclusion from supports(mask, support) of all subsets, the empty set included."""
    x = supports.filter("mask <> 0").select(F.col("mask").alias("x"))
    grid = x.select("x", F.explode(submasks(F.col("x"), k)).alias("cell"))
    upper = grid.select("x", "cell", F.explode(submasks(F.col("x").bitwiseAND(F.bitwise_not("cell")), k)).alias("more"))
    signed = upper.select("x", "cell", F.col("cell").bitwiseOR(F.col("more")).alias("mask"), F.when(F.bit_count("more") % 2 == 0, 1).otherwise(-1).alias("sign"))
    return signed.join(supports.select("mask", "support"), "mask").groupBy("x", "cell").agg(F.sum(F.col("sign") * F.col("support")).alias("n")).filter("n > 0")


def smooth(patterns: DataFrame, k: int, eps: float) -> DataFrame:
    """(mask, p): (1 - eps) of the empirical mass plus eps spread over all 2^k cells."""
    spark = patterns.sparkSession
    n = total(patterns)
    grid = spark.range(1 << k).select(F.col("id").alias("mask"))
    held = grid.join(patterns, "mask", "left").select("mask", F.coalesce("n", F.lit(0)).alias("n"))
    return held.select("mask", (F.col("n") / n * (1 - eps) + F.lit(eps / (1 << k))).alias("p"))
