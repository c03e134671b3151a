"""What scores are compared with: frequency, entropy, index gap, frequent itemsets, independence tests, fixed models."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.durable import Durable
from . import entropy as entropies
from .bic import model_rows, required, score_models
from .family import best_tree, saturated, singletons, tree
from .patterns import cells, itemset_table, next_level, single_items, support, total
from .patterns import frequency as frequencies

#: Upper chi-square points by degrees of freedom, at .05, .01 and .001.
CHI_SQUARE = {1: (3.841459, 6.634897, 10.827566), 4: (9.487729, 13.276704, 18.466827), 11: (19.675138, 24.724970, 31.264134), 26: (38.885139, 45.641683, 54.051962)}


def frequency(scores: DataFrame, patterns: DataFrame) -> DataFrame:
    """scores(mask, ...) with fr."""
    wanted = scores.select("mask", F.bit_count("mask").alias("size")).distinct()
    return scores.join(frequencies(patterns, wanted).select("mask", "fr"), "mask")


def entropy(scores: DataFrame, patterns: DataFrame) -> DataFrame:
    """scores(mask, ...) with h."""
    wanted = scores.select("mask", F.bit_count("mask").alias("size")).distinct()
    return scores.join(entropies.entropy(patterns, wanted).select("mask", "h"), "mask")


def index_gap(mask: Column) -> Column:
    """Distance between the greatest and the least item in the natural order."""
    return (F.floor(F.log2(mask.cast("double"))) - F.floor(F.log2(mask.bitwiseAND(-mask).cast("double")))).cast("int")


def frequent(patterns: DataFrame, k: int, minsup: int, max_size: int | None = None) -> DataFrame:
    """(mask, size, support) of itemsets with at least minsup rows, level by level; levels stay in stored tables."""
    store, made, level = Durable(patterns.sparkSession, "frequent"), None, single_items(patterns.sparkSession, k)
    for size in range(1, (max_size or k) + 1):
        level = store.save(level, f"level{size}")
        kept = support(patterns, level).filter(F.col("support") >= minsup).join(level.select("mask", "top"), "mask")
        kept = store.save(kept, f"kept{size}")
        made = kept if made is None else made.unionByName(kept)
        if kept.isEmpty():
            break
        level = next_level(kept.select("mask", "size", "top"), k)
    return made.select("mask", F.col("size").cast("int").alias("size"), "support")


#: Copies of a pattern that one row stands for before it is repeated.
COPIES = 4096


def frequent_fpgrowth(patterns: DataFrame, k: int, minsup: int) -> DataFrame:
    """The same by Spark's own FP-growth, which knows no weights: each pattern is repeated n times, in runs of up to COPIES."""
    from pyspark.ml.fpm import FPGrowth

    items = F.filter(F.sequence(F.lit(1), F.lit(k)), lambda i: F.getbit("mask", i - 1) == 1)
    runs = patterns.filter("n > 0").select(items.alias("items"), "n", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("n") - 1, F.lit(COPIES).cast("bigint"))).alias("start"))
    left = F.least(F.col("n") - F.col("start"), F.lit(COPIES)).cast("int")
    rows = runs.repartition(patterns.sparkSession.sparkContext.defaultParallelism).select("items", F.explode(F.array_repeat(F.lit(1), left)).alias("one")).select("items")
    found = FPGrowth(itemsCol="items", minSupport=minsup / max(1, total(patterns)) * (1 - 1e-9)).fit(rows).freqItemsets
    mask = F.aggregate("items", F.lit(0).cast("bigint"), lambda a, i: a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), i - 1)))
    return found.select(mask.alias("mask"), F.size("items").cast("int").alias("size"), F.col("freq").alias("support")).filter(F.col("support") >= minsup)


def independence_g(patterns: DataFrame, itemsets: DataFrame) -> DataFrame:
    """(mask, size, g, df, lift): G = 2 sum O log(O/E) against independent items."""
    n = total(patterns)
    singles = itemsets.select(F.col("mask").alias("x"), "size", F.explode(F.filter(F.transform(F.sequence(F.lit(0), F.lit(62)), lambda i: F.when(F.getbit("mask", i) == 1, F.call_function("shiftleft", F.lit(1).cast("bigint"), i))), lambda m: m.isNotNull())).alias("item"))
    wanted = singles.select(F.col("item").alias("mask")).distinct().withColumn("size", F.lit(1))
    fr = support(patterns, wanted).select(F.col("mask").alias("item"), (F.col("support") / n).alias("f"))
    per_item = singles.join(fr, "item")
    found = cells(patterns, itemsets).join(per_item.select("x", "item", "f"), "x")
    chance = found.groupBy("x", "size", "cell", "n").agg(F.sum(F.log(F.when(F.col("cell").bitwiseAND(F.col("item")) != 0, F.col("f")).otherwise(1 - F.col("f")))).alias("log_e"))
    g = chance.groupBy("x", "size").agg((2 * F.sum(F.col("n") * (F.log(F.col("n") / n) - F.col("log_e")))).alias("g"), F.coalesce(F.max(F.when(F.col("cell") == F.col("x"), F.col("n") / n / F.exp("log_e"))), F.lit(0.0)).alias("lift"))
    df = (F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("size")) - F.col("size") - 1).cast("int")
    return g.select(F.col("x").alias("mask"), "size", F.abs("g").alias("g"), df.alias("df"), "lift")


def independence_test(patterns: DataFrame, itemsets: DataFrame, alpha: float = 0.05) -> DataFrame:
    """independence_g with the critical value and the verdict, for itemsets of two to five items."""
    at = {0.05: 0, 0.01: 1, 0.001: 2}[alpha]
    points = F.create_map(*(F.lit(v) for d, p in CHI_SQUARE.items() for v in (d, p[at])))
    made = independence_g(patterns, itemsets).withColumn("critical", F.element_at(points, F.col("df")))
    return made.withColumn("significant", F.col("g") > F.col("critical"))


def pair_information(patterns: DataFrame, k: int) -> DataFrame:
    """(x, y, mi) of all item pairs, in one pass."""
    spark = patterns.sparkSession
    wanted = [1 << i for i in range(k)] + [1 << i | 1 << j for i in range(k) for j in range(i)]
    h = entropies.entropy(patterns, itemset_table(spark, wanted))
    one = h.filter("size = 1").select(F.col("mask").alias("m"), F.col("h").alias("h1"))
    two = h.filter("size = 2").select("mask", "h", F.col("mask").bitwiseAND(-F.col("mask")).alias("lo")).withColumn("hi", F.col("mask").bitwiseXOR(F.col("lo")))
    met = two.join(one.select(F.col("m").alias("lo"), F.col("h1").alias("hl")), "lo").join(one.select(F.col("m").alias("hi"), F.col("h1").alias("hh")), "hi")
    place = lambda c: (F.round(F.log2(F.col(c).cast("double"))) + 1).cast("int")
    return met.select(place("lo").alias("x"), place("hi").alias("y"), F.abs(F.col("hl") + F.col("hh") - F.col("h")).alias("mi"))


def fixed_models(patterns: DataFrame, k: int) -> DataFrame:
    """(name, family_size, log_lik, log_bic) of independence, the best tree, and the saturated model."""
    spark, n = patterns.sparkSession, total(patterns)
    weights = {(r.x, r.y): r.mi for r in pair_information(patterns, k).collect()}  # K^2 / 2 rows
    names = {0: "independence", 1: "tree", 2: "saturated"}
    models = model_rows(spark, {0: singletons(k), 1: tree(k, best_tree(weights, k)), 2: saturated(k)})
    scored = score_models(models, entropies.entropy(patterns, required(models)), n)
    called = spark.createDataFrame(list(names.items()), "model_id bigint, name string")
    return called.join(scored, "model_id").select("name", "family_size", "log_lik", "log_bic")
