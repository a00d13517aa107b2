"""Summaries of a stream: windows with sketches, sessions, late rows, a store kept up to date, and scores from kept state."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import scratch, zoned


def source(spark: SparkSession, sf_dir: str, table: str = "events", files_per_trigger: int = 1) -> DataFrame:
    """The table's files as a stream, its time as TIMESTAMP."""
    path = f"{sf_dir}/{table}.parquet"
    there = spark.read.parquet(path)
    reader = spark.readStream.schema(there.schema).option("maxFilesPerTrigger", files_per_trigger)
    if there.inputFiles()[0].rstrip("/").endswith(f"/{table}.parquet"):  # one file, not a folder of them
        reader, path = reader.option("pathGlobFilter", f"{table}.parquet"), sf_dir
    return reader.parquet(path).withColumn("ts", zoned("ts"))


def daily(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """Tumbling days: rows, sum, mean, sketches of distinct users and of values."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n_rows"), F.count("value").alias("n_valid"), F.avg("value").alias("mean"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users"), F.expr("kll_sketch_agg_double(value)").alias("kll"))


def sliding(stream: DataFrame, width: str = "7 days", step: str = "1 day", late: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n_rows"), F.avg("value").alias("mean"))


def sessions(stream: DataFrame, gap: str = "2 hours", late: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n_rows"))


def deduplicated(stream: DataFrame, late: str = "1 day") -> DataFrame:
    """First row of each event id; rows that come more than ``late`` after later ones are dropped, as the kept state is bounded by it."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_groups(stream: DataFrame, groups: DataFrame) -> DataFrame:
    """Stream-static join with an assignment (event_type, cluster) that is a row per kind."""
    return stream.join(F.broadcast(groups), "event_type", "left")


def follow_ups(stream: DataFrame, other: DataFrame, within: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Stream-stream interval join: purchases with the same user's clicks of the time before."""
    a = stream.withWatermark("ts", late).filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("u"), F.col("ts").alias("pt"))
    b = other.withWatermark("ts", late).filter("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("v"), F.col("ts").alias("ct"))
    return a.join(b, F.expr(f"u = v AND ct <= pt AND ct >= pt - INTERVAL {within}")).select("purchase", "click", "u")


def stateful_z(windows: DataFrame, k: int = 7) -> DataFrame:
    """(feature, ds, z) from the last ``k`` values kept per feature: ``windows`` is a stream of (feature, ds, value)."""

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches)).sort_values("ds")
        kept = list(state.get[0]) if state.exists else []
        out = []
        for ds, value in zip(rows["ds"], rows["value"]):
            z = None
            if len(kept) == k:
                base, spread = sum(kept) / k, pd.Series(kept).std()
                tolerance = 1e-9 * max(1.0, abs(base))
                z = (value - base) / spread if spread > tolerance else 0.0 if abs(value - base) <= tolerance else 10.0 if value > base else -10.0
            out.append((key[0], ds, z))
            kept = [*kept, float(value)][-k:]
        state.update((kept,))
        yield pd.DataFrame(out, columns=["feature", "ds", "z"])

    return windows.groupBy("feature").applyInPandasWithState(step, "feature string, ds date, z double", "kept array<double>", "append", "NoTimeout")


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Everything the stream gives for what is there now, through foreachBatch into Parquet; read back as a table.

    Each batch has a folder of its own, so a batch that is repeated replaces its rows; in complete mode a batch replaces all."""
    spark = stream.sparkSession
    path, marks = scratch(spark, "stream"), scratch(spark, "stream-state")
    schema = stream.schema
    replaced = "static" if mode == "complete" else "dynamic"

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("micro_batch", F.lit(number)).write.mode("overwrite").option("partitionOverwriteMode", replaced).partitionBy("micro_batch").parquet(path)

    stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", marks).trigger(availableNow=True).start().awaitTermination()
    try:
        return spark.read.schema(schema).parquet(path).select(*schema.names)
    except AnalysisException as e:  # there was no batch
        if e.getCondition() != "PATH_NOT_FOUND":
            raise
        return spark.createDataFrame([], schema)


def upsert_each(stream: DataFrame, upsert: Callable[[DataFrame, int], None], marks: str) -> None:
    """Run ``upsert`` on every micro-batch and its number until what is there is read.

    A partition's rows may come in several batches, so what is written must add up by batch, as ``store.add_states`` does."""
    stream.writeStream.foreachBatch(upsert).option("checkpointLocation", marks).trigger(availableNow=True).start().awaitTermination()
