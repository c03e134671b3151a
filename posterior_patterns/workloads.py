"""The experiments over the given tables."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import baselines, bic, entropy, expmodel, measures, sampler, score
from .operators.family import mask_of, singletons
from .operators.patterns import compress, itemset_table, total
from .plans.durable import Durable
from .sources.encode import SPECS, to_baskets, word_baskets
from .sources.tables import example, load

#: The worked example's tree: pairs 12, 23, 24, 45.
EXAMPLE_TREE = [mask_of(p) for p in ((1, 2), (2, 3), (2, 4), (4, 5))]
SIGMAS_SYNTHETIC = [0.01, 0.05, 0.1, 0.2, 0.5, 0.9]
SIGMAS_REAL = [0.05, 0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9]


def patterns_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Patterns of an encoding, stored: whatever reads them, the rows are read once."""
    return Durable(spark, f"patterns-{name}").save(compress(to_baskets(spark, sf_dir, SPECS[name])), "patterns")


def named_patterns(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, int]:
    """(patterns, items) of an encoding, or of the most common words of all documents, as in words90."""
    if not name.startswith("words"):
        return patterns_of(spark, sf_dir, name), SPECS[name].k
    k = int(name.removeprefix("words"))
    baskets = word_baskets(load(spark, sf_dir, "documents"), k)
    return Durable(spark, f"patterns-{name}").save(compress(baskets), "patterns"), k


def ideal_family(name: str) -> list[int]:
    """Itemsets that describe a synthetic set by construction."""
    if name.startswith("ind"):
        return singletons(15)
    if name.startswith("path"):
        return singletons(15) + [3 << i for i in range(14)]
    if name == "thermo":
        return singletons(9) + [3 << i for i in range(8)]
    if name.startswith("planted"):
        return [*singletons(15), 3]
    raise ValueError(f"no family is known for {name}")


def two_model_example(spark: SparkSession) -> DataFrame:
    """(mask, score) with the tree and independence as the only models of the worked example."""
    patterns = compress(example(spark))
    models = bic.model_rows(spark, {0: EXAMPLE_TREE, 1: singletons(5)})
    weighted = bic.score_models(models, entropy.entropy(patterns, bic.required(models)), total(patterns))
    found = score.exact(weighted.select("model_id", "log_bic"), bic.members(models, 5))
    every = itemset_table(spark, range(1, 32))
    return every.join(found, "mask", "left").select("mask", "size", F.coalesce("score", F.lit(0.0)).alias("score"))


def sampled(spark: SparkSession, sf_dir: str, name: str, restarts: int, steps: int | None = None, seed: int = 1, **options) -> DataFrame:
    """Sampled models of an encoding."""
    return sampler.sample_models(patterns_of(spark, sf_dir, name), SPECS[name].k, restarts, steps, seed, **options)


def curve_of(spark: SparkSession, sf_dir: str, name: str, restarts: int, sigmas: list[float], **options) -> DataFrame:
    return measures.curve(score.estimate(sampled(spark, sf_dir, name, restarts, **options), SPECS[name].k), sigmas)


def score_against(spark: SparkSession, sf_dir: str, name: str, restarts: int, least: float = 0.05, **options) -> DataFrame:
    """One row of correlations of the score with frequency, entropy and index gap."""
    patterns = patterns_of(spark, sf_dir, name)
    found = score.estimate(sampler.sample_models(patterns, SPECS[name].k, restarts, seed=1, **options), SPECS[name].k)
    return measures.correlations(measures.scatter(found, patterns, least))


def run_report(spark: SparkSession, sf_dir: str, name: str, restarts: int, steps: int | None = None, **options) -> dict:
    """Time, steps and acceptance of a sampling run; patterns are compressed before the clock starts."""
    patterns, k = named_patterns(spark, sf_dir, name)
    n, began = total(patterns), time.time()
    models = sampler.sample_models(patterns, k, restarts, steps, 1, partitions=restarts, **options)
    return measures.run_report(models, n, k, time.time() - began)


def general_and_decomposable(spark: SparkSession, k: int = 3) -> DataFrame:
    """(mask, general, decomposable) scores of the worked example's first items."""
    rows = example(spark).select(F.col("mask").bitwiseAND((1 << k) - 1).alias("mask"))
    patterns = compress(rows)
    every = expmodel.score_general(expmodel.empirical(patterns, k), total(patterns), k)
    table = spark.createDataFrame(list(every.items()), "mask bigint, general double")
    return table.join(score.exact_decomposable(patterns, k).withColumnRenamed("score", "decomposable"), "mask")


def explosion(spark: SparkSession, sf_dir: str, name: str, alpha: float = 0.05) -> DataFrame:
    """How many itemsets of up to five items an independence test and the score call significant."""
    from itertools import combinations

    patterns = patterns_of(spark, sf_dir, name)
    k = min(SPECS[name].k, 10)
    wanted = [sum(1 << i for i in c) for r in range(2, 6) for c in combinations(range(k), r) if r in (2, 3, 4, 5)]
    found = baselines.independence_test(patterns, itemset_table(spark, wanted), alpha)
    return found.groupBy("size").agg(F.sum(F.col("significant").cast("int")).alias("significant"), F.count("*").alias("tested"))

