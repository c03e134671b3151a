"""Connected components of a link table by alternating large-star and small-star steps.

Every step is a pair of aggregations and a join on node ids, so no component is ever
gathered in one place; each round is written to the shared folder, and the previous one is
deleted.  Rounds needed grow with the logarithm of the diameter.  A caller may let few links
of whole numbers be joined on the driver, in one job and with the same result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.durable import Durable


def _large_star(links: DataFrame) -> DataFrame:
    both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.filter("v > u").join(least, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(links: DataFrame) -> DataFrame:
    """links hold u > v."""
    least = links.groupBy("u").agg(F.min("v").alias("m"))
    moved = links.join(least, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v")))


def least_reachable(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of the links that aren't the least of their component, and that least."""
    nodes, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    x, y, root = at[: len(a)], at[len(a) :], np.arange(len(nodes))
    while True:
        least = np.minimum(root[x], root[y])
        lower = root.copy()
        np.minimum.at(lower, root[x], least)
        np.minimum.at(lower, root[y], least)
        while not np.array_equal(lower, lower[lower]):
            lower = lower[lower]
        if np.array_equal(lower, root):
            break
        root = lower
    moved = root != np.arange(len(nodes))
    return nodes[moved], nodes[root[moved]]


def components(links: DataFrame, store: Durable, name: str = "cc", max_rounds: int = 60, few: int = 0) -> DataFrame:
    """links(a, b) of one orderable type -> (node, root): root is the least node reachable.

    Self-links and repeated links are harmless; nodes without a link to another don't appear.
    Up to `few` links of longs are joined on the driver.
    """
    ordered = links.filter("a is not null and b is not null and a <> b")
    ordered = ordered.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    now, before = store.save(ordered, f"{name}0"), None
    if few and dict(now.dtypes)["u"] == "bigint" and now.count() <= few:
        got = now.toArrow()  # bounded by few
        node, root = least_reachable(got.column("v").to_numpy(), got.column("u").to_numpy())
        return store.spark.createDataFrame(pa.table({"node": node, "root": root}), "node long, root long")
    for i in range(1, max_rounds + 1):
        step = _small_star(_large_star(now).distinct()).distinct()
        after = store.save(step, f"{name}{i}")
        mark = after.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        store.drop(f"{name}{i - 1}")
        now = after
        if mark == before:
            break
        before = mark
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
