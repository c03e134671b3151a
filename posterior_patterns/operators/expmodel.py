"""Exponential models: densities, maximum-likelihood fits, divergences.

Tables of all 2^K cells are only built for K <= 16 (densities) and K <= 12 (fits).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .bic import log_n
from .catalogue import general
from .family import junction_tree, maximal


def indicator(mask: Column, x: int | Column) -> Column:
    """1 where a pattern holds the whole itemset."""
    x = F.lit(x) if isinstance(x, int) else x
    return F.when(mask.bitwiseAND(x) == x, 1).otherwise(0)


def density(spark: SparkSession, k: int, params: dict[int, float]) -> DataFrame:
    """(mask, p): p proportional to exp of the sum of the parameters of the itemsets in the cell."""
    if k > 16:
        raise ValueError("densities are tabulated for up to 16 items")
    grid = spark.range(1 << k).select(F.col("id").alias("mask"))
    rows = [(m, float(r)) for m, r in params.items() if m] or [(0, 0.0)]
    given = spark.createDataFrame(rows, "x bigint, r double")
    summed = grid.join(F.broadcast(given), F.col("mask").bitwiseAND(F.col("x")) == F.col("x"), "left").groupBy("mask").agg(F.coalesce(F.sum("r"), F.lit(0.0)).alias("s"))
    raw = summed.crossJoin(F.broadcast(summed.agg(F.max("s").alias("top")))).select("mask", F.exp(F.col("s") - F.col("top")).alias("e"))
    return raw.crossJoin(F.broadcast(raw.agg(F.sum("e").alias("z")))).select("mask", (F.col("e") / F.col("z")).alias("p"))


def empirical(patterns: DataFrame, k: int) -> np.ndarray:
    """Cell probabilities of all 2^k cells on the driver."""
    if k > 12:
        raise ValueError("cell tables are fitted for up to 12 items")
    made = np.zeros(1 << k)
    for r in patterns.groupBy("mask").agg(F.sum("n").alias("n")).collect():  # at most 2^k rows
        made[r.mask] = r.n
    return made / made.sum() if made.sum() else made


def marginal(p: np.ndarray, x: int) -> np.ndarray:
    """Mass of each cell's projection onto x, at the projection's place."""
    cells = np.arange(len(p)) & x
    return np.bincount(cells, p, len(p))


def fit_ipf(q: np.ndarray, maxs: list[int], tolerance: float = 1e-10, max_iter: int = 2000) -> tuple[np.ndarray, int]:
    """Iterative proportional fitting: the distribution of greatest entropy with q's projections onto the maximal sets."""
    p = np.full(len(q), 1.0 / len(q))
    cells = [np.arange(len(q)) & m for m in maxs]
    goals = [marginal(q, m) for m in maxs]
    for i in range(1, max_iter + 1):
        worst = 0.0
        for at, goal in zip(cells, goals, strict=True):
            now = np.bincount(at, p, len(p))
            worst = max(worst, float(np.abs(now - goal).max()))
            p = p * np.divide(goal, now, out=np.zeros_like(goal), where=now > 0)[at]
        if worst < tolerance:
            return p, i
    return p, max_iter


def closed_form(q: np.ndarray, maxs: list[int]) -> np.ndarray:
    """The same for a decomposable family: projections onto maximal sets over those onto the intersections."""
    cell, p = np.arange(len(q)), np.ones(len(q))
    for m in maxs:
        p = p * marginal(q, m)[cell & m]
    for *_, s in junction_tree(maxs):
        if s:
            below = marginal(q, s)[cell & s]
            p = np.divide(p, below, out=np.zeros_like(p), where=below > 0)
    return p


def decomposable_density(patterns: DataFrame, maxs: list[int]) -> DataFrame:
    """(mask, n, p): the fitted density at every pattern, from clique and separator counts."""
    n = patterns.agg(F.sum("n").alias("rows"))
    made = patterns.crossJoin(F.broadcast(n)).withColumn("log_p", F.lit(0.0))
    for m, sign in [(m, 1) for m in maxs] + [(s, -1) for *_, s in junction_tree(maxs) if s]:
        table = patterns.groupBy(F.col("mask").bitwiseAND(F.lit(m)).alias("_cell")).agg(F.sum("n").alias("_n"))
        made = made.withColumn("_cell", F.col("mask").bitwiseAND(F.lit(m))).join(table, "_cell")
        made = made.withColumn("log_p", F.col("log_p") + sign * F.log(F.col("_n") / F.col("rows"))).drop("_cell", "_n")
    return made.select("mask", "n", F.exp("log_p").alias("p"))


def kl(p: DataFrame, q: DataFrame) -> DataFrame:
    """(kl): divergence of (mask, p) from (mask, p); infinite where q misses mass."""
    both = p.select("mask", F.col("p").alias("a")).join(q.select("mask", F.col("p").alias("b")), "mask", "full_outer")
    term = F.when(F.coalesce("a", F.lit(0.0)) <= 0, F.lit(0.0)).when(F.coalesce("b", F.lit(0.0)) <= 0, F.lit(float("inf"))).otherwise(F.col("a") * F.log(F.col("a") / F.col("b")))
    return both.agg(F.sum(term).alias("kl"))


def score_general(q: np.ndarray, n: int, k: int) -> dict[int, float]:
    """Scores over every model of k <= 4 items, decomposable or not, by fitting each."""
    weights, families = [], general(k)
    held = q > 0
    for f in families:
        p, _ = fit_ipf(q, maximal(f))
        lik = n * float((q[held] * np.log(np.maximum(p[held], 1e-300))).sum())
        weights.append(lik - 0.5 * log_n(n) * (len(f) - 1))
    w = np.exp(np.array(weights) - max(weights))
    w /= w.sum()
    return {m: float(sum(x for x, f in zip(w, families, strict=True) if m in f)) for m in range(1, 1 << k)}
