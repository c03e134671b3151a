"""Where transactions come from: the given Parquet tables, basket text files, 0/1 matrices, samples, and a worked example."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
#: The worked example: nine rows of five items, the first item leftmost.
EXAMPLE_ROWS = ("10000", "11001", "00000", "11111", "11011", "01100", "00100", "00101", "01111")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"no such table: {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def row_mask(bits: str) -> int:
    return sum(1 << i for i, b in enumerate(bits) if b == "1")


def example(spark: SparkSession) -> DataFrame:
    """The nine rows as (tid, mask)."""
    return spark.createDataFrame([(i, row_mask(r)) for i, r in enumerate(EXAMPLE_ROWS)], "tid bigint, mask bigint")


def mask_of_items(items) -> F.Column:
    """Item numbers (1..62) in an array column -> mask."""
    return F.aggregate(F.array_distinct(items), F.lit(0).cast("bigint"), lambda a, i: a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), i.cast("int") - 1)))


def baskets_text(spark: SparkSession, path: str) -> DataFrame:
    """One transaction a line, item numbers separated by blanks -> (items, mask); mask is null beyond item 62."""
    lines = spark.read.text(path).select(F.filter(F.split(F.trim("value"), r"\s+"), lambda s: s != "").alias("s"))
    items = lines.select(F.array_sort(F.array_distinct(F.transform("s", lambda s: s.cast("int")))).alias("items"))
    return items.select("items", F.when(F.coalesce(F.array_max("items"), F.lit(0)) <= 62, mask_of_items(F.col("items"))).alias("mask"))


def matrix_csv(spark: SparkSession, path: str, header: bool = False) -> DataFrame:
    """A dense 0/1 matrix, one column an item (up to 62) -> (mask)."""
    raw = spark.read.csv(path, header=header, inferSchema=False)
    if len(raw.columns) > 62:
        raise ValueError("a mask holds up to 62 items")
    parts = [F.when(F.trim(F.col(f"`{c}`")) == "1", F.lit(1 << i)).otherwise(F.lit(0)).cast("bigint") for i, c in enumerate(raw.columns)]
    made = parts[0]
    for p in parts[1:]:
        made = made.bitwiseOR(p)
    return raw.select(made.alias("mask"))


def matrix_json(spark: SparkSession, path: str, items: list[str]) -> DataFrame:
    """JSON lines with a flag for each item -> (mask); a missing flag is absent."""
    raw = spark.read.schema(", ".join(f"`{i}` int" for i in items)).json(path)
    made = F.lit(0).cast("bigint")
    for n, i in enumerate(items):
        made = made.bitwiseOR(F.when(F.col(f"`{i}`") == 1, F.lit(1 << n)).otherwise(F.lit(0)).cast("bigint"))
    return raw.select(made.alias("mask"))


def sample(df: DataFrame, fraction: float, seed: int = 0) -> DataFrame:
    """A Bernoulli row sample: an approximation, offered apart from the exact methods."""
    return df.sample(False, fraction, seed)
