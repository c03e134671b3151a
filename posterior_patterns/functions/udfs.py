"""Functions of families for SQL: vectorised UDFs, an entropy aggregate, and table functions.

Item masks in arrays; register(spark) makes all of them callable from spark.sql.
"""

from __future__ import annotations

import math
from collections import Counter

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from ..operators import family, moves


@pandas_udf("boolean")
def is_decomposable(maxs: pd.Series) -> pd.Series:
    return pd.Series([None if m is None else family.is_decomposable([int(x) for x in m]) for m in maxs], dtype="object")


@pandas_udf("array<bigint>")
def junction_separators(maxs: pd.Series) -> pd.Series:
    return maxs.map(lambda m: None if m is None else sorted(s for *_, s in family.junction_tree([int(x) for x in m])))


@pandas_udf("bigint")
def family_size(maxs: pd.Series) -> pd.Series:
    return pd.Series([None if m is None else family.family_size([int(x) for x in m]) for m in maxs], dtype="object")


@pandas_udf("string")
def canonical(mask: pd.Series) -> pd.Series:
    return mask.map(lambda m: None if pd.isna(m) else family.canonical(int(m)))


@pandas_udf("double")
def entropy_agg(key: pd.Series) -> float:
    """Entropy in nats of a grouped column, for groups that fit a worker; group_entropy takes any."""
    counts = Counter(key.dropna())
    n = sum(counts.values())
    return math.log(n) - sum(c * math.log(c) for c in counts.values()) / n if n else 0.0


def group_entropy(df: DataFrame, group: str, key: str) -> DataFrame:
    """(group, h): entropy in nats of the keys of each group, by two aggregations; null keys don't count."""
    counts = df.filter(F.col(key).isNotNull()).groupBy(group, key).agg(F.count("*").alias("n"))
    summed = counts.groupBy(group).agg(F.sum("n").alias("rows"), F.sum(F.col("n") * F.log("n")).alias("s"))
    return summed.select(group, F.abs(F.log("rows") - F.col("s") / F.col("rows")).alias("h"))


@F.udtf(returnType="mask bigint, size int")
class Subsets:
    """Non-empty subsets of a mask with at most max_size items."""

    def eval(self, mask: int, max_size: int):
        if mask is not None:
            for s in family.subsets(mask):
                if s and s.bit_count() <= max_size:
                    yield s, s.bit_count()


@F.udtf(returnType="op string, s bigint, x bigint, y bigint")
class LegalMoves:
    """Legal merges and splits of a family given by its maximal sets."""

    def eval(self, maxs: list):
        if maxs:
            for whole, x, y in moves.legal_splits(list(maxs)):
                yield "split", whole & ~(x | y), x, y
            for s, x, y in moves.legal_merges(list(maxs)):
                yield "merge", s, x, y


def register(spark: SparkSession) -> None:
    for f in (is_decomposable, junction_separators, family_size, canonical, entropy_agg):
        spark.udf.register(f.__name__, f)
    spark.udtf.register("subsets", Subsets)
    spark.udtf.register("legal_moves", LegalMoves)
