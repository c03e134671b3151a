"""Pattern counts and baskets kept up to date from a stream of events.

Rows are independent and all measures follow from pattern counts, which add up over batches.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.durable import Durable

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"
TYPES = ("view", "click", "signup", "purchase", "error")
#: Predicates of a running event transaction.
ITEMS = ("event_type = 'view'", "event_type = 'click'", "value > 50", "hour(ts) >= 12", "user_id % 2 = 0")


def read_events(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """A stream over a folder or a glob of Parquet files."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def type_mask() -> F.Column:
    made = F.lit(0)
    for i, t in enumerate(TYPES):
        made = made + F.when(F.col("event_type") == t, 1 << i).otherwise(0)
    return made.cast("bigint")


def event_mask() -> F.Column:
    return F.expr("CAST(" + " + ".join(f"(CASE WHEN {e} THEN {1 << i} ELSE 0 END)" for i, e in enumerate(ITEMS)) + " AS BIGINT)")


def pattern_counts(events: DataFrame) -> DataFrame:
    """Running (mask, n)."""
    return events.select(event_mask().alias("mask")).groupBy("mask").agg(F.count("*").alias("n"))


def tumbling_baskets(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "2 hours") -> DataFrame:
    """(user_id, start, mask): the event types of a user in each window; later rows than the watermark are dropped."""
    frame = F.window("ts", width, slide) if slide else F.window("ts", width)
    made = events.withWatermark("ts", late).groupBy("user_id", frame.alias("w")).agg(F.bit_or(type_mask()).alias("mask"))
    return made.select("user_id", F.col("w.start").alias("start"), "mask")


def session_baskets(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    """(user_id, start, mask, events) of sessions that end after a gap."""
    made = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.bit_or(type_mask()).alias("mask"), F.count("*").alias("events"))
    return made.select("user_id", F.col("w.start").alias("start"), "mask", "events")


def deduplicated(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """Events whose id came again within the watermark are dropped."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_catalog(events: DataFrame, catalog: DataFrame) -> DataFrame:
    """Stream-static join with a small item catalogue (event_type, item_id)."""
    return events.join(F.broadcast(catalog), "event_type")


def decayed_support(events: DataFrame, half_life_s: float = 86_400.0) -> DataFrame:
    """(event_type, weight, last): support that halves every half life, updated per batch by a stateful operator."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        weight, last = state.get if state.exists else (0.0, 0.0)
        times = sorted(t for f in frames for t in f["ts"].astype("int64").tolist())
        for t in times:
            now = t / (1e9 if t > 1e17 else 1e6)
            weight = weight * 0.5 ** (max(0.0, now - last) / half_life_s if last else 0.0) + 1.0
            last = max(last, now)
        state.update((weight, last))
        yield pd.DataFrame({"event_type": [key[0]], "weight": [weight], "last": [last]})

    return events.select("event_type", "ts").groupBy("event_type").applyInPandasWithState(update, "event_type string, weight double, last double", "weight double, last double", "update", "NoTimeout")


def run_to_end(stream: DataFrame, name: str, mode: str = "complete", progress: list | None = None) -> DataFrame:
    """Run over all that is there now and return the result, which is written batch by batch to the shared folder.

    Complete mode gives the last batch, the others all batches with repeats of a retried one replaced.  The
    checkpoint lies in the shared folder too; `progress` receives the query's progress reports.
    """
    store, done = Durable(stream.sparkSession, f"stream-{name}"), []

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(store.path(f"result/batch={batch_id}"))
        done.append(batch_id)

    query = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", store.path("checkpoint")).trigger(availableNow=True).start()
    query.awaitTermination()
    if progress is not None:
        progress += query.recentProgress
    if not done:
        return stream.sparkSession.createDataFrame([], stream.schema)
    paths = [store.path(f"result/batch={i}") for i in sorted(set(done))]
    return stream.sparkSession.read.schema(stream.schema).parquet(*(paths[-1:] if mode == "complete" else paths))


def dropped_late(progress: list) -> int:
    """Rows, or groups of them, dropped behind the watermark, from the progress reports of a query."""
    return sum(op["numRowsDroppedByWatermark"] for p in progress for op in p["stateOperators"])


def rescore(stream: DataFrame, k: int, restarts: int, steps: int, sink: str, seed: int = 0):
    """Re-score the masks of every micro-batch's closed windows and append the scores to a Parquet table."""
    from ..operators.patterns import compress
    from ..operators.sampler import sample_models
    from ..operators.score import estimate

    def each(batch: DataFrame, batch_id: int) -> None:
        if batch.isEmpty():
            return
        models = sample_models(compress(batch.select("mask")), k, restarts, steps, seed + batch_id)
        estimate(models, k).withColumn("batch", F.lit(batch_id)).write.mode("append").parquet(sink)

    return stream.writeStream.foreachBatch(each).outputMode("append").option("checkpointLocation", Durable(stream.sparkSession, "rescore").path("checkpoint")).trigger(availableNow=True)
