"""Scores of itemsets: the posterior weight of the models whose family holds them, exact or sampled, and mining."""

from __future__ import annotations

from itertools import combinations_with_replacement

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .bic import members, model_rows, required, score_models
from .catalogue import decomposable
from .entropy import entropy
from .family import bits
from .patterns import _small, label, next_level, single_items, total


def posterior(weighted: DataFrame, prior: Column | None = None) -> DataFrame:
    """(model_id, log_bic) -> with p, by a shifted exponential."""
    lw = F.col("log_bic") + (prior if prior is not None else F.lit(0.0))
    top = weighted.agg(F.max(lw).alias("top"))
    raw = weighted.crossJoin(F.broadcast(top)).withColumn("e", F.exp(lw - F.col("top")))
    return raw.crossJoin(F.broadcast(raw.agg(F.sum("e").alias("all")))).select("model_id", "log_bic", (F.col("e") / F.col("all")).alias("p"))


def exact(weighted: DataFrame, belongs: DataFrame, prior: Column | None = None) -> DataFrame:
    """models (model_id, log_bic) and (model_id, mask) -> (mask, score)."""
    return belongs.join(posterior(weighted, prior), "model_id").groupBy("mask").agg(F.sum("p").alias("score"))


def named(scores: DataFrame, k: int = 63) -> DataFrame:
    """(itemset, size, score) from masks, scores to 6 decimals."""
    return scores.select(label("mask", k).alias("itemset"), F.bit_count("mask").cast("int").alias("size"), (F.round("score", 6) + F.lit(0.0)).alias("score"))


def exact_over(patterns: DataFrame, families: list[list[int]], k: int, log_prior: list[float] | None = None) -> DataFrame:
    """(mask, score) over a space of decomposable families of one's own, given by maximal sets, with log priors for them (else equal)."""
    spark, n = patterns.sparkSession, total(patterns)
    models = model_rows(spark, dict(enumerate(families)))
    weighted = score_models(models, entropy(patterns, required(models)), n).select("model_id", "log_bic")
    if log_prior is not None:
        prior = spark.createDataFrame([(i, float(v)) for i, v in enumerate(log_prior)], "model_id bigint, log_prior double")
        weighted = weighted.join(prior, "model_id").select("model_id", (F.col("log_bic") + F.col("log_prior")).alias("log_bic"))
    return exact(weighted, members(models, k))


def exact_decomposable(patterns: DataFrame, k: int) -> DataFrame:
    """(mask, score) over all decomposable families of k <= 6 items."""
    return exact_over(patterns, decomposable(k), k)


def estimate(models: DataFrame, k: int, max_size: int | None = None, id_cols: tuple[str, ...] = ("chain_id", "draw")) -> DataFrame:
    """Sampled (maximal array) -> (mask, size, hits, n_models, score, se): the share of models that hold an itemset."""
    from .patterns import submasks

    masks = models.select(*id_cols, F.explode("maximal").alias("m")).select(*id_cols, F.col("m").cast("bigint").alias("m"))
    found = masks.select(*id_cols, F.explode(submasks(F.col("m"), k)).alias("mask")).filter("mask <> 0")
    if max_size:
        found = found.filter(F.bit_count("mask") <= max_size)
    hits = found.distinct().groupBy("mask").agg(F.count("*").alias("hits"))
    return _shares(hits, models)


def estimate_wide(models: DataFrame, max_size: int = 3) -> DataFrame:
    """The same for any number of items, as (itemset, size, hits, n_models, score, se): itemsets of up to max_size items by name."""
    from itertools import combinations

    from .family import canonical

    def named_subsets(frames):
        for pdf in frames:
            rows = []
            for maximal in pdf["maximal"]:
                found = {c for m in maximal for r in range(1, max_size + 1) for c in combinations(tuple(bits(int(m))), r)}
                rows += [(canonical(sum(c)), len(c)) for c in found]
            yield pd.DataFrame(rows, columns=["itemset", "size"])

    hits = models.select("maximal").mapInPandas(named_subsets, "itemset string, size int").groupBy("itemset", "size").agg(F.count("*").alias("hits"))
    made = hits.crossJoin(F.broadcast(models.agg(F.count("*").alias("n_models")))).withColumn("score", F.col("hits") / F.col("n_models"))
    return made.select("itemset", "size", "hits", "n_models", "score", F.sqrt(F.col("score") * (1 - F.col("score")) / F.col("n_models")).alias("se"))


def _shares(hits: DataFrame, models: DataFrame) -> DataFrame:
    n = models.agg(F.count("*").alias("n_models"))
    made = hits.crossJoin(F.broadcast(n)).withColumn("score", F.col("hits") / F.col("n_models"))
    return made.select("mask", F.bit_count("mask").cast("int").alias("size"), "hits", "n_models", "score", F.sqrt(F.col("score") * (1 - F.col("score")) / F.col("n_models")).alias("se"))


def monotone_violations(scores: DataFrame, tolerance: float = 1e-9) -> DataFrame:
    """Pairs X < Y by one item where Y scores more; empty for true scores."""
    small, large = scores.select(F.col("mask").alias("x"), F.col("score").alias("sx")), scores.select(F.col("mask").alias("y"), F.col("score").alias("sy"))
    under = large.select("y", "sy", F.explode(F.filter(F.transform(F.sequence(F.lit(0), F.lit(62)), lambda i: F.when(F.getbit("y", i) == 1, F.col("y").bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), i)))), lambda m: m.isNotNull() & (m != 0))).alias("x"))
    return under.join(small, "x").filter(F.col("sy") > F.col("sx") + tolerance).select("x", "y", "sx", "sy")


def mine_explode(models: DataFrame, k: int, sigma: float, strict: bool = True) -> DataFrame:
    """All itemsets above sigma by counting every member of every family."""
    found = estimate(models, k)
    return found.filter(F.col("score") > sigma if strict else F.col("score") >= sigma)


def mine_levelwise(models: DataFrame, k: int, sigma: float, max_size: int | None = None) -> DataFrame:
    """The same, level by level: an itemset is counted only if all its subsets one smaller are above sigma."""
    keys, store = ("chain_id", "draw"), Durable(models.sparkSession, "levels")
    cliques = models.select(*keys, F.explode("maximal").alias("m")).select(*keys, F.col("m").cast("bigint").alias("m"))
    n, level, made = models.count(), single_items(models.sparkSession, k), None
    for size in range(1, (max_size or k) + 1):
        level = store.save(level, f"level{size}")
        held = cliques.join(_small(level.select("mask")), F.col("m").bitwiseAND(F.col("mask")) == F.col("mask"))
        hits = held.select(*keys, "mask").distinct().groupBy("mask").agg(F.count("*").alias("hits"))
        kept = store.save(hits.filter(F.col("hits") > sigma * n).join(level, "mask"), f"kept{size}")
        made = kept if made is None else made.unionByName(kept)
        if kept.isEmpty():
            break
        level = next_level(kept.select("mask", "size", "top"), k)
    return _shares(made.select("mask", "hits"), models)


_PAIRS = "number long, x int, y int"


def vertical(models: DataFrame) -> DataFrame:
    """(number, x, y): for every pair of items, and every item with itself, the models that link them; any number of items."""
    numbered = models.select("maximal", (F.row_number().over(Window.orderBy("chain_id", "draw")) - 1).cast("long").alias("number"))

    def linked(frames):
        for pdf in frames:
            rows = []
            for number, maximal in zip(pdf["number"], pdf["maximal"], strict=True):
                pairs = {p for m in maximal for p in combinations_with_replacement([b.bit_length() for b in bits(int(m))], 2)}
                rows += [(number, x, y) for x, y in pairs]
            yield pd.DataFrame(rows, columns=["number", "x", "y"])

    return numbered.select("number", "maximal").mapInPandas(linked, _PAIRS)


def pair_bitmaps(models: DataFrame) -> dict[tuple[int, int], int]:
    """The models of each pair as one number, from K^2 / 2 times R / 62 words: bounded by items and models, not by data."""
    word, bit = F.floor(F.col("number") / 62).alias("word"), F.call_function("shiftleft", F.lit(1).cast("bigint"), (F.col("number") % 62).cast("int"))
    made: dict[tuple[int, int], int] = {}
    for r in vertical(models).groupBy("x", "y", word).agg(F.bit_or(bit).alias("bits")).toArrow().to_pylist():
        made[r["x"], r["y"]] = made.get((r["x"], r["y"]), 0) | r["bits"] << (62 * r["word"])
    return made


def _dig(pair: dict[tuple[int, int], int], k: int, first: int, least: float):
    """(items, hits) of all itemsets from a least item on with more hits than `least`, depth first."""
    stack = [((first,), pair.get((first, first), 0))]
    while stack:
        items, held = stack.pop()
        if held.bit_count() <= least:
            continue
        yield items, held.bit_count()
        for new in range(items[-1] + 1, k + 1):
            both = held
            for i in items:
                both &= pair.get((i, new), 0)
                if not both:
                    break
            if both:
                stack.append(((*items, new), both))


def mine_dfs_named(models: DataFrame, k: int, sigma: float) -> DataFrame:
    """(itemset, size, hits, n_models, score, se) of all itemsets above sigma, for any number of items.

    Depth first from each least item: in a family of a chordal graph an itemset belongs iff all its pairs do, so
    the models of a set are an AND of bitmaps of its pairs.
    """
    n = models.count()
    shared = models.sparkSession.sparkContext.broadcast(pair_bitmaps(models))

    def dig(frames):
        for pdf in frames:
            rows = [("-".join(map(str, items)), len(items), hits) for first in pdf["id"] for items, hits in _dig(shared.value, k, int(first) + 1, sigma * n)]
            yield pd.DataFrame(rows, columns=["itemset", "size", "hits"])

    made = models.sparkSession.range(0, k, 1, k).mapInPandas(dig, "itemset string, size int, hits bigint")
    score = F.col("hits") / F.lit(max(1, n))
    return made.select("*", F.lit(n).cast("bigint").alias("n_models"), score.alias("score"), F.sqrt(score * (1 - score) / F.lit(max(1, n))).alias("se"))


def mine_dfs(models: DataFrame, k: int, sigma: float) -> DataFrame:
    """The same as (mask, size, hits, n_models, score, se), for up to 62 items."""
    bit = lambda i: F.call_function("shiftleft", F.lit(1).cast("bigint"), i.cast("int") - 1)
    mask = F.aggregate(F.split("itemset", "-"), F.lit(0).cast("bigint"), lambda a, i: a.bitwiseOR(bit(i)))
    return mine_dfs_named(models, k, sigma).select(mask.alias("mask"), "size", "hits", "n_models", "score", "se")


def top_k(scores: DataFrame, size: int = 2, k: int = 4) -> DataFrame:
    return scores.filter(F.col("size") == size).orderBy(F.col("score").desc(), "itemset" if "itemset" in scores.columns else "mask").limit(k)


def holders(models: DataFrame, itemset: int) -> DataFrame:
    """The sampled models whose family holds an itemset, of any width: what its score is made of."""

    @F.pandas_udf("boolean")
    def holds(maximal: pd.Series) -> pd.Series:
        return maximal.map(lambda ms: any(int(m) & itemset == itemset for m in ms))

    return models.filter(holds("maximal"))


def explain(patterns: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs(x, y) of masks -> fr(x), fr(xy), p(y | x)."""
    from .patterns import support

    n = total(patterns)
    both = pairs.withColumn("xy", F.col("x").bitwiseOR(F.col("y")))
    wanted = both.select(F.explode(F.array("x", "xy")).alias("mask")).distinct().withColumn("size", F.bit_count("mask"))
    s = support(patterns, wanted).select("mask", "support")
    met = both.join(s.select(F.col("mask").alias("x"), F.col("support").alias("sx")), "x").join(s.select(F.col("mask").alias("xy"), F.col("support").alias("sxy")), "xy")
    return met.select("x", "y", (F.col("sx") / n).alias("fr_x"), (F.col("sxy") / n).alias("fr_xy"), F.when(F.col("sx") > 0, F.col("sxy") / F.col("sx")).alias("p_y_given_x"))
