"""Measures of a score table: counts over thresholds, correlations, distance from a known family, convergence."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .baselines import entropy, frequency, index_gap
from .entropy import projections
from .moves import degrees
from .sampler import default_steps


def curve(scores: DataFrame, sigmas: list[float]) -> DataFrame:
    """(sigma, n_itemsets): how many itemsets score above each threshold."""
    grid = scores.sparkSession.createDataFrame([(float(s),) for s in sigmas], "sigma double")
    met = scores.select("score").join(F.broadcast(grid), F.col("score") > F.col("sigma")).groupBy("sigma").agg(F.count("*").alias("n"))
    return grid.join(met, "sigma", "left").select("sigma", F.coalesce("n", F.lit(0)).alias("n_itemsets"))


#: Itemsets beyond which they are counted by halving instead of one pass with every pattern, on at most so many patterns of 16 bytes.
MANY_ITEMSETS, SHIPPED_PATTERNS = 5000, 5_000_000


def scatter(scores: DataFrame, patterns: DataFrame, least: float = 0.05) -> DataFrame:
    """(mask, size, score, fr, h, gap) of itemsets of two or more items that score at least `least`."""
    kept = scores.filter((F.col("size") >= 2) & (F.col("score") >= least)).select("mask", "size", "score")
    kept = Durable(scores.sparkSession, "scatter").save(kept, "kept")
    if kept.count() > MANY_ITEMSETS and patterns.count() <= SHIPPED_PATTERNS:
        n = patterns.agg(F.sum("n").alias("rows"))
        met = kept.join(projections(patterns, kept), "mask").crossJoin(F.broadcast(n))
        return met.select("mask", "size", "score", (F.col("support") / F.col("rows")).alias("fr"), "h", index_gap(F.col("mask")).alias("gap"))
    return entropy(frequency(kept, patterns), patterns).withColumn("gap", index_gap(F.col("mask")))


def correlations(points: DataFrame) -> DataFrame:
    """One row (corr_fr, corr_h, corr_gap); the gap is that of pairs; null where a side is constant."""

    def corr(a: str, b: str, only=None):
        keep = F.lit(True) if only is None else only
        x, y = F.when(keep, F.col(a).cast("double")), F.when(keep, F.col(b).cast("double"))
        return F.try_divide(F.covar_pop(x, y), F.when((F.stddev_pop(x) > 1e-12) & (F.stddev_pop(y) > 1e-12), F.stddev_pop(x) * F.stddev_pop(y)))

    pairs = F.col("size") == 2
    return points.agg(F.count("*").alias("n"), corr("score", "fr").alias("corr_fr"), corr("score", "h").alias("corr_h"), corr("score", "gap", pairs).alias("corr_gap"))


def against_ideal(scores: DataFrame, ideal: list[int], sigma: float) -> DataFrame:
    """One row (hits, misses, extras, precision, recall) of the itemsets above sigma against a known family."""
    wanted = scores.sparkSession.createDataFrame([(m,) for m in ideal], "mask bigint").withColumn("wanted", F.lit(1))
    found = scores.filter(F.col("score") > sigma).select("mask").withColumn("found", F.lit(1))
    both = wanted.join(found, "mask", "full_outer").select(F.coalesce("wanted", F.lit(0)).alias("w"), F.coalesce("found", F.lit(0)).alias("f"))
    made = both.agg(F.coalesce(F.sum(F.col("w") * F.col("f")), F.lit(0)).alias("hits"), F.coalesce(F.sum(F.col("w") * (1 - F.col("f"))), F.lit(0)).alias("misses"), F.coalesce(F.sum((1 - F.col("w")) * F.col("f")), F.lit(0)).alias("extras"))
    return made.select("hits", "misses", "extras", F.when(F.col("hits") + F.col("extras") > 0, F.col("hits") / (F.col("hits") + F.col("extras"))).alias("precision"), F.when(F.col("hits") + F.col("misses") > 0, F.col("hits") / (F.col("hits") + F.col("misses"))).alias("recall"))


def candidate_extensions(maxs: list[int]) -> int:
    """Merges open to a family: how many itemsets compete to extend it."""
    return degrees(maxs)[1]


def run_report(models: DataFrame, n: int, k: int, seconds: float) -> dict:
    row = models.agg(F.count("*").alias("chains"), F.sum("steps").alias("steps"), F.sum("accepted").alias("accepted")).first()
    return {"N": n, "K": k, "chains": row.chains, "steps_per_chain": default_steps(k), "seconds": seconds, "steps_per_s": row.steps / seconds if seconds else None, "acceptance": row.accepted / row.steps if row.steps else None}


def tv_to_exact(models: DataFrame, posterior: DataFrame) -> DataFrame:
    """(tv): half the summed distance of sampled model shares and exact ones; both keyed by the sorted maximal sets as text."""
    n = models.agg(F.count("*").alias("n"))
    share = models.groupBy("family").agg(F.count("*").alias("c")).crossJoin(F.broadcast(n)).select("family", (F.col("c") / F.col("n")).alias("s"))
    both = share.join(posterior.select("family", "p"), "family", "full_outer")
    return both.agg((F.sum(F.abs(F.coalesce("s", F.lit(0.0)) - F.coalesce("p", F.lit(0.0)))) / 2).alias("tv"))
