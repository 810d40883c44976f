"""Profiles of a live column, drift against its stored vector, a value index kept as state, and annotation of new tables."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle


def windows(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Count, mean and distinct users of each event type in tumbling or sliding windows; rows later than ``late`` are dropped."""
    w = F.window("ts", size, slide or size)
    return events.withWatermark("ts", late).groupBy(w, "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"), F.approx_count_distinct("user_id").alias("users"))


def sessions(events: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    """Sessions of each user: a pause of ``gap`` ends one."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Values that were sent again within the watermark are dropped."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def late_rows(query) -> int:
    """How many rows of a running or ended query came after the watermark and were dropped."""
    return sum(state.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for state in p["stateOperators"])


def histogram_drift(batch: DataFrame, stored: list[float], mean: float, deviation: float) -> DataFrame:
    """Cosine of the histogram of a window's values (z-scored with the stored moments) with the stored vector."""
    bins = len(stored)
    z = F.round((F.col("value") - mean) / (deviation or 1.0), 9)
    place = F.greatest(F.lit(0), F.least(F.lit(bins - 1), F.floor((z + 4) / 8 * bins))).cast("int")
    counts = batch.groupBy("window", place.alias("bin")).agg(F.count("*").alias("c"))
    base = F.array(*[F.lit(float(x)) for x in stored])
    dot = F.sum(F.col("c") * F.element_at(base, F.col("bin") + 1))
    norm = float(sum(x * x for x in stored) ** 0.5) or 1.0
    return counts.groupBy("window").agg((dot / (F.sqrt(F.sum(F.col("c") * F.col("c"))) * norm)).alias("similarity"))


def value_types() -> StatefulProcessor:
    """The processor of ``value_index``; a local class, so it travels by value."""

    class ValueTypes(StatefulProcessor):
        """For each value hash the labels seen so far; a value without labels is passed on as open."""

        def init(self, handle: StatefulProcessorHandle) -> None:
            self.labels = handle.getMapState("labels", "label string", "n long")

        def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
            values: set[str] = set()
            for f in rows:
                values |= set(f["value"])
                for label in f["label"].dropna():
                    n = self.labels.getValue((label,))[0] if self.labels.containsKey((label,)) else 0
                    self.labels.updateValue((label,), (n + 1,))
            known = sorted(k[0] for k in self.labels.keys())
            yield pd.DataFrame({"value": sorted(values), "labels": ["|".join(known)] * len(values)})

        def close(self) -> None:
            pass

    return ValueTypes()


def value_index(stream: DataFrame) -> DataFrame:
    """(value, labels) as (value, label or null) rows arrive."""
    keyed = stream.withColumn("value_hash", F.xxhash64("value"))
    return keyed.groupBy("value_hash").transformWithStateInPandas(value_types(), "value string, labels string", "Update", "None")


def upsert(stream: DataFrame, keys: list[str], folder: str, checkpoint: str):
    """Keep the last row of each key of an update stream as a table: every batch writes a new version, which ``latest`` reads.

    A batch that runs again after a failure writes its own version again.
    """
    def each(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        rows = batch.withColumn("__epoch", F.lit(epoch))
        if epoch:
            before = spark.read.parquet(f"{folder}/v{epoch - 1}")
            rows = before.join(batch.select(*keys).distinct(), keys, "left_anti").unionByName(rows)
        rows.write.mode("overwrite").parquet(f"{folder}/v{epoch}")

    return stream.writeStream.outputMode("update").foreachBatch(each).option("checkpointLocation", checkpoint).start()


def latest(spark: SparkSession, folder: str, epoch: int) -> DataFrame:
    """The version of an upserted table that a batch wrote."""
    return spark.read.parquet(f"{folder}/v{epoch}").drop("__epoch")


def annotate_batches(stream: DataFrame, index: DataFrame, sink: str, queue: str, checkpoint: str):
    """Start annotating cells (column_id, value) of new tables: known values get their types, other columns are queued for discovery."""
    def each(batch: DataFrame, epoch: int) -> None:
        values = batch.select("column_id", "value").distinct()
        held = values.withColumn("value_hash", F.xxhash64("value")).join(index, ["value_hash", "value"])
        labels = held.select("column_id", "label").distinct().withColumn("epoch", F.lit(epoch))
        labels.write.mode("append").parquet(sink)
        values.select("column_id").distinct().join(labels.select("column_id").distinct(), "column_id", "left_anti").write.mode("append").parquet(queue)

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).start()
