"""The summary store: a Parquet table by (dataset, ds) that every method reads instead of the data."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.stats import w1
from ..sources.features import Dataset
from ..sources.tables import scratch
from .summary import summarize

_DONE: dict[tuple, tuple[str, object]] = {}


def _labelled(summary: DataFrame, dataset: str) -> DataFrame:
    """With the folder names of the store: the dataset's and the partition's."""
    label = F.date_format("ds", "yyyyMMddHHmm") if dict(summary.dtypes)["ds"] in ("date", "timestamp_ntz", "timestamp") else F.col("ds").cast("string")
    return summary.withColumns({"dataset": F.lit(dataset), "part": label})


def upsert(summary: DataFrame, path: str, dataset: str) -> None:
    """Write whole partitions; those of the same (dataset, ds) are replaced, others stay, so a repeated run leaves one copy."""
    _labelled(summary, dataset).repartition("part").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("dataset", "part").parquet(path)


def add_states(states: DataFrame, path: str, dataset: str, batch: int) -> None:
    """Write one batch's part of each partition beside those of other batches; a batch that is repeated replaces its own part alone."""
    _labelled(states, dataset).withColumn("micro_batch", F.lit(batch)).repartition("part").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("dataset", "part", "micro_batch").parquet(path)


def _read(spark: SparkSession, path: str, dataset: str, until: str | None) -> DataFrame:
    rows = spark.read.parquet(path).filter(F.col("dataset") == dataset)
    return (rows.filter(F.col("part") <= until) if until else rows).drop("dataset", "part")


def history(spark: SparkSession, path: str, dataset: str, until: str | None = None) -> DataFrame:
    """Stored summaries of a dataset, up to a partition label; both filters prune folders.

    Where percentiles are stored, each partition's gap to the one before it, ``w1_prev``, is made here: it stays right
    when the partition before is written later or again.
    """
    rows = _read(spark, path, dataset, until)
    if "quantiles" not in rows.columns:
        return rows
    return rows.withColumn("w1_prev", w1(F.col("quantiles"), F.lag("quantiles").over(Window.partitionBy("feature").orderBy("ds"))))


def merged_states(spark: SparkSession, path: str, dataset: str, merge: Callable[[DataFrame, Column], DataFrame], until: str | None = None) -> DataFrame:
    """The states of ``add_states``, those of one partition combined by ``merge`` (states, partition) -> DataFrame."""
    return merge(_read(spark, path, dataset, until).drop("micro_batch"), F.col("ds"))


def update(spark: SparkSession, path: str, data: Dataset, sf_dir: str, ds) -> None:
    """Summarise one new partition, and nothing else, into the store; its gap to the partition before is made when the history is read."""
    rows = data.rows(spark, sf_dir).filter(F.col("ds") == F.lit(ds))
    upsert(summarize(rows, data.features).drop("w1_prev"), path, data.name)


def summary_of(spark: SparkSession, sf_dir: str, data: Dataset) -> DataFrame:
    """The dataset's summaries, made once per session and kept in the shared scratch folder.

    They are found again by the plan of the rows and every feature's expression; files that are written anew under an old
    path within a session are not noticed."""
    rows = data.rows(spark, sf_dir)
    key = (spark.sparkContext.applicationId, sf_dir, data.name, rows.semanticHash(), tuple((f.name, f.kind, f.expr) for f in data.features))
    if key not in _DONE:
        made = summarize(rows, data.features)
        path = scratch(spark, "summaries")
        made.coalesce(4).write.parquet(path)
        _DONE[key] = (path, made.schema)
    path, schema = _DONE[key]
    return spark.read.schema(schema).parquet(path)
