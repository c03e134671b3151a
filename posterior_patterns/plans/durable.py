"""Intermediate tables that outlive executors.

A :class:`Durable` writes named Parquet tables below the folder that the session
gives in ``spark.checkpoint.dir``; reading one back cuts the lineage, prunes
columns and survives the loss of any executor.  Only a local master without that
setting (unit tests) gets a temporary folder.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_LEFT: list["Durable"] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder every executor and the driver share."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise ValueError("spark.checkpoint.dir must name a folder shared by the cluster")
    made = "file://" + tempfile.mkdtemp(prefix="posterior-patterns-")
    spark.conf.set("spark.checkpoint.dir", made)
    return made


class Durable:
    """Tables of one computation, under one folder of their own."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
        _LEFT.append(self)

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        """Write df once and return the stored table."""
        target = self.path(name)
        df.write.mode("overwrite").parquet(target)
        return self.spark.read.schema(df.schema).parquet(target)

    def drop(self, name: str = "") -> None:
        """Delete one table, or all of them."""
        jvm = self.spark._jvm
        target = jvm.org.apache.hadoop.fs.Path(self.path(name) if name else self.root)
        target.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _release() -> None:
    for made in _LEFT:
        try:
            if made.spark.sparkContext._jsc is not None:
                made.drop()
        except Exception:  # the session is gone: the cluster's own retention removes the folder
            return
