"""Where results go."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write(df: DataFrame, path: str, partition_by: tuple[str, ...] = ()) -> None:
    """Parquet, partitioned (scores by size, models by run)."""
    df.write.mode("overwrite").partitionBy(*partition_by).parquet(path)
