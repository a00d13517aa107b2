"""From scores to alerts, and from alerts to the decision on a retrained model."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _past():
    return Window.orderBy("ds").rowsBetween(Window.unboundedPreceding, -1)  # one row a partition


def alert_fixed(scores: DataFrame, tau: float) -> DataFrame:
    return scores.withColumn("threshold", F.lit(float(tau))).withColumn("alert", F.coalesce(F.col("score") >= tau, F.lit(False)))


def alert_sigma(scores: DataFrame, m: float = 3.0) -> DataFrame:
    """Above the mean plus m deviations of the scores before; needs two of them."""
    rows = scores.withColumns({"mu": F.avg("score").over(_past()), "sd": F.stddev_samp("score").over(_past())})
    return rows.withColumn("threshold", F.col("mu") + m * F.col("sd")).withColumn("alert", F.coalesce(F.col("score") > F.col("threshold"), F.lit(False))).drop("mu", "sd")


def alert_quantile(scores: DataFrame, q: float = 0.95) -> DataFrame:
    """Above a percentile of the scores before."""
    return scores.withColumn("threshold", F.expr(f"percentile(score, {q}D)").over(_past())).withColumn("alert", F.coalesce(F.col("score") > F.col("threshold"), F.lit(False)))


def alert_policy(drop: DataFrame, clustered: DataFrame, tau_drop: float, tau_clustered: float, k: int = 7) -> DataFrame:
    """Completeness drop while history is short (the first partitions with a base), the clustered score from then on.

    The clustered score has its first value one partition after the drop; whatever has no value yet raises nothing."""
    rows = drop.select("ds", F.col("score").alias("drop")).join(clustered.select("ds", F.col("score").alias("far")), "ds", "left")
    early = F.row_number().over(Window.orderBy("ds")) <= 2 * k
    rows = rows.withColumn("rule", F.when(early, "completeness_drop").otherwise("clustered"))
    score = F.when(F.col("rule") == "clustered", F.col("far")).otherwise(F.col("drop"))
    tau = F.when(F.col("rule") == "clustered", tau_clustered).otherwise(tau_drop)
    return rows.select("ds", "rule", score.alias("score"), tau.alias("threshold")).withColumn("alert", F.coalesce(F.col("score") >= F.col("threshold"), F.lit(False)))


def promotion_decision(model_ok: DataFrame, alerts: DataFrame) -> DataFrame:
    """Publish a retrained model if its own check passes and no alert is up; a partition without alert row is no alert."""
    joined = model_ok.select("ds", "ok").join(alerts.select("ds", "alert"), "ds", "left")
    return joined.withColumn("publish", F.col("ok") & ~F.coalesce("alert", F.lit(False)))


def recommend(summary: DataFrame, labels: DataFrame | None = None, k: int = 7) -> DataFrame:
    """Which method suits a pipeline: its age, width, share of low-cardinality features and rate of failures, and the advice.

    Young pipelines have no history to compare with; frequent failures leave few clean neighbours, where the plain
    baseline orders alerts well; embeddings and other distribution-heavy features call for the two-sample test."""
    traits = summary.agg(F.count_distinct("ds").alias("partitions"), F.count_distinct("feature").alias("features"))
    wide = summary.groupBy("feature").agg(F.avg("n_distinct").alias("d"), F.avg("n_valid").alias("v")).agg(F.avg((F.col("d") <= 20).cast("double")).alias("low_cardinality"))
    rate = labels.agg(F.avg("y").alias("failure_rate")) if labels is not None else summary.sparkSession.range(1).select(F.lit(None).cast("double").alias("failure_rate"))
    advice = F.when(F.col("partitions") <= 2 * k, "completeness_drop").when(F.col("failure_rate") > 0.4, "knn_baseline").when((F.col("features") < 10) & (F.col("low_cardinality") < 0.2), "two_sample_w1").otherwise("clustered")
    return traits.crossJoin(wide).crossJoin(rate).withColumn("advice", advice)  # three single rows


def alert_volume(alerts: DataFrame, labels: DataFrame) -> DataFrame:
    """Alerts and false alerts per calendar week: what people on call see."""
    rows = alerts.join(labels.select("ds", "y"), "ds", "left")
    return rows.groupBy(F.date_trunc("week", "ds").cast("date").alias("week")).agg(F.sum(F.col("alert").cast("long")).alias("alerts"), F.sum((F.col("alert") & (F.coalesce("y", F.lit(0)) == 0)).cast("long")).alias("false_alerts"))
