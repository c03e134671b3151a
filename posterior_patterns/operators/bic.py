"""Likelihood and BIC weight of decomposable models, and the change by one move.

The log-likelihood is -N times (entropies of the maximal sets less those of the junction tree's
intersections), the penalty half a log N for every member of the family but the empty set.  A split
of X between x and y loses 2^(|X|-2) parameters, so its weight rises by log N * 2^(|X|-3) and falls by
N times the conditional mutual information; a merge changes the weight by the opposite amount.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .family import closure, junction_tree, n_params

Entropy = Callable[[int], float]


def log_lik(maxs: list[int], entropy: Entropy, n: float) -> float:
    return -n * (sum(map(entropy, maxs)) - sum(entropy(s) for *_, s in junction_tree(maxs)))


def log_n(n: float) -> float:
    return math.log(n) if n > 0 else 0.0


def log_bic(maxs: list[int], entropy: Entropy, n: float) -> float:
    return log_lik(maxs, entropy, n) - 0.5 * log_n(n) * n_params(maxs)


def gain(entropy: Entropy, n: float, whole: int, x: int, y: int) -> float:
    """N (H(X) - H(X-x) - H(X-y) + H(X-xy)): minus N times the mutual information of x and y given the rest."""
    return n * (entropy(whole) - entropy(whole & ~x) - entropy(whole & ~y) + entropy(whole & ~x & ~y))


def move_delta(is_merge: bool, entropy: Entropy, n: float, s: int, x: int, y: int) -> float:
    whole = s | x | y
    change = gain(entropy, n, whole, x, y) + log_n(n) * 2.0 ** (whole.bit_count() - 3)
    return -change if is_merge else change


def model_rows(spark, families: dict[int, list[int]]) -> DataFrame:
    """Models given on the driver, as (model_id, maximal, separators, family_size)."""
    rows = []
    for i, maxs in families.items():
        seps = [s for *_, s in junction_tree(maxs)]
        rows.append((i, sorted(maxs), sorted(seps), n_params(maxs) + 1))
    return spark.createDataFrame(rows, "model_id bigint, maximal array<bigint>, separators array<bigint>, family_size bigint")


def required(models: DataFrame) -> DataFrame:
    """The itemsets whose entropies the models need."""
    both = models.select(F.explode(F.concat("maximal", "separators")).alias("mask")).filter("mask <> 0").distinct()
    return both.select("mask", F.bit_count("mask").alias("size"))


def score_models(models: DataFrame, entropies: DataFrame, n: int) -> DataFrame:
    """models -> (model_id, family_size, log_lik, log_bic)."""
    signed = models.select("model_id", "family_size", F.explode(F.concat(F.transform("maximal", lambda m: F.struct(m.alias("mask"), F.lit(1.0).alias("sign"))), F.transform("separators", lambda m: F.struct(m.alias("mask"), F.lit(-1.0).alias("sign"))))).alias("t"))
    met = signed.select("model_id", "family_size", "t.mask", "t.sign").join(entropies.select("mask", "h"), "mask", "left")
    summed = met.groupBy("model_id", "family_size").agg(F.sum(F.col("sign") * F.coalesce("h", F.lit(0.0))).alias("s"))
    return summed.select("model_id", "family_size", (F.col("s") * F.lit(-float(n))).alias("log_lik"), (F.col("s") * F.lit(-float(n)) - F.lit(0.5 * log_n(n)) * (F.col("family_size") - 1)).alias("log_bic"))


def members(models: DataFrame, k: int) -> DataFrame:
    """(model_id, mask) for every member of every family but the empty set."""
    from .patterns import submasks

    return models.select("model_id", F.explode("maximal").alias("m")).select("model_id", F.explode(submasks(F.col("m"), k)).alias("mask")).filter("mask <> 0").distinct()


def log_bic_by_members(models: DataFrame, weights: DataFrame, k: int) -> DataFrame:
    """(model_id, log_bic) as the sum of the members' Moebius weights: no junction tree."""
    return members(models, k).join(weights, "mask").groupBy("model_id").agg(F.sum("w").alias("log_bic"))


def family_sum(maxs: list[int], weight: Callable[[int], float]) -> float:
    return sum(weight(m) for m in closure(maxs) if m)
