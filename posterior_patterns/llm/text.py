"""What the text operators share: words, Arrow maps over documents, group-wise text pickers."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: Words are maximal runs of anything but space and U+0009..U+000D.
WORD = r"[^\x20\x09-\x0D]+"
#: Rows in an Arrow batch at most, so that long texts don't add up in a worker.
BATCH_ROWS = 512


def words(data: bytes) -> list[bytes]:
    """Lower-cased (A-Z only) words of UTF-8 bytes; bytes.split() cuts at exactly the six characters above."""
    return data.lower().split()


_SPACE = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
#: A number for each byte, and a base for places; both odd multiples of fixed values, mixed below.
_BYTE = (np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95)) ^ np.uint64(0x2545F4914F6CDD1D)
_BASE = 0x9E3779B97F4A7C15
_POWERS = {b: np.array([1], dtype=np.uint64) for b in (_BASE, pow(_BASE, -1, 1 << 64))}


def powers(base: int, n: int) -> np.ndarray:
    """base^0 .. base^n modulo 2^64, from a table that grows with the longest text."""
    if len(_POWERS.setdefault(base, np.array([1], dtype=np.uint64))) <= n:
        made = np.full(max(n + 1, 2 * len(_POWERS[base])), base, dtype=np.uint64)
        made[0] = 1
        _POWERS[base] = np.cumprod(made, dtype=np.uint64)
    return _POWERS[base][: n + 1]


def mixed(h: np.ndarray) -> np.ndarray:
    """64-bit hashes whose bits all depend on all bits."""
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def word_hashes(data: bytes) -> np.ndarray:
    """64-bit hashes of the words() of a text, in order, without making the words."""
    b = np.frombuffer(data.lower(), dtype=np.uint8)
    edges = np.flatnonzero(np.diff(np.concatenate(([True], _SPACE[b], [True]))))
    starts, ends = edges[::2], edges[1::2]
    sums = np.concatenate((np.zeros(1, dtype=np.uint64), np.cumsum(_BYTE[b] * powers(_BASE, len(b))[: len(b)], dtype=np.uint64)))
    inverse = powers(pow(_BASE, -1, 1 << 64), len(b))
    return mixed((sums[ends] - sums[starts]) * inverse[starts] + (ends - starts).astype(np.uint64))


def blob(text: Column) -> Column:
    """UTF-8 bytes of a text; null counts as empty."""
    return F.coalesce(text.cast("string"), F.lit("")).cast("binary")


def arrow_map(df: DataFrame, fn: Callable[..., Iterator[tuple]], schema: str | StructType) -> DataFrame:
    """Apply fn(*columns as Python lists) to Arrow batches; fn returns the output columns as lists."""
    bound_batches(df)
    kind = df.sparkSession.createDataFrame([], schema).schema
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = fn(*(c.to_pylist() for c in batch.columns))
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(made, arrow, strict=True)], schema=arrow)

    return df.mapInArrow(run, kind)


def digest(text: Column) -> Column:
    """128-bit content hash as binary."""
    return F.unhex(F.md5(blob(text)))


#: Classes with more than one part in so many of all rows are broadcast; there are at most so many of them.
HOT_PARTS = 1000


def with_class(rows: DataFrame, classes: DataFrame, key: str, size: str, spread: str) -> DataFrame:
    """rows left-joined to stored classes (one row for each string or binary `key`, `size` rows have it), as a struct column `class`.

    Hot classes, at most HOT_PARTS, are broadcast, and their rows go through the shuffle of the others under the hash
    of the column `spread`, so a class with a third of all rows does not land in one task.
    """
    total = classes.agg(F.sum(size).alias("n")).first().n or 0
    is_hot = F.col(size) * HOT_PARTS > F.lit(total)
    held = F.struct(*(F.col(c) for c in classes.columns if c != key))
    hot = classes.filter(is_hot).select(F.col(key).alias("_hot_key"), held.alias("_hot"))
    cold = classes.filter(~is_hot).select(F.col(key).alias("_cold_key"), held.alias("_cold"))
    met = rows.join(F.broadcast(hot), F.col(key) == F.col("_hot_key"), "left")
    scattered = F.md5(F.concat(F.lit("spread"), F.xxhash64(spread).cast("string")).cast("binary")).cast(dict(rows.dtypes)[key])
    met = met.withColumn("_key", F.when(F.col("_hot_key").isNull(), F.col(key)).otherwise(scattered))
    met = met.join(cold, F.col("_key") == F.col("_cold_key"), "left")
    return met.select(*(rows[c] for c in rows.columns), F.coalesce("_hot", "_cold").alias("class"))


def bound_batches(df: DataFrame) -> None:
    """Arrow batches of at most BATCH_ROWS rows in df's session."""
    conf = df.sparkSession.conf
    if int(conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH_ROWS:
        conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))


#: Digests of distinct new contents that may be broadcast, 32 bytes each.
BROADCAST_DIGESTS = 100_000


def one_of_each_new(rows: DataFrame, new: DataFrame, key: str) -> DataFrame:
    """rows(key, data) -> (key, data) for every key of the stored table new(key), each once.

    Copies collapse in the map tasks; where few contents are new, only their texts are shuffled.
    """
    few = new.count() <= BROADCAST_DIGESTS
    if few:
        rows = rows.join(F.broadcast(new), key, "left_semi")
    once = rows.groupBy(key).agg(F.first("data").alias("data"))
    return once if few else once.join(new, key, "left_semi")


def free_name(df: DataFrame, name: str) -> str:
    """A column name that df lacks."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name
