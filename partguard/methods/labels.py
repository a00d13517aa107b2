"""Ground truth: three signals of a proxy model's performance, three levels, and the injected plan."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.faults import FaultPlan

#: Least rise of the normalised loss, calibration error and fall of the label rate, by level.
LEVELS = {1: (0.02, 0.3, 0.3), 2: (0.04, 0.4, 0.4), 3: (0.06, 0.5, 0.5)}
PSEUDO = 20.0


def plan_labels(spark: SparkSession, plan: FaultPlan, level: int = 1, days: int = 30) -> DataFrame:
    """(ds, level, y): the injected truth."""
    truth = plan.truth(level)
    return spark.createDataFrame([(f"2024-01-{d:02d}", level, int(d in truth)) for d in range(1, days + 1)], "ds string, level int, y int").withColumn("ds", F.col("ds").cast("date"))


def proxy_signals(rows: DataFrame, k: int = 7) -> DataFrame:
    """(ds, ne, cross_entropy_up, calib_error, label_rate, label_shift) of a model retrained every day.

    The prediction of a row is the click rate of its value's band over the k days before, with
    twenty pseudo-rows at the base rate; null is a band of its own. Counts by (day, band) are all that is used."""
    band = F.when(F.col("v").isNull(), 0).when(F.col("v") < 5, 1).when(F.col("v") < 20, 2).when(F.col("v") < 50, 3).otherwise(4)
    counts = rows.groupBy("ds", band.alias("band")).agg(F.count("*").alias("n"), F.sum("clicked").alias("c"))
    grid = counts.select("ds").distinct().crossJoin(counts.select("band").distinct())  # days by five bands
    dense = grid.join(counts, ["ds", "band"], "left").fillna(0, ["n", "c"])
    before = Window.partitionBy("band").orderBy("ds").rowsBetween(-k, -1)
    past = dense.withColumns({"pn": F.sum("n").over(before), "pc": F.sum("c").over(before), "nth": F.row_number().over(Window.partitionBy("band").orderBy("ds"))})
    day = Window.partitionBy("ds")
    past = past.withColumn("base", F.sum("pc").over(day) / F.sum("pn").over(day)).withColumn("p", (F.col("pc") + PSEUDO * F.col("base")) / (F.col("pn") + PSEUDO))
    loss = -(F.col("c") * F.ln("p") + (F.col("n") - F.col("c")) * F.ln(1 - F.col("p")))
    daily = past.groupBy("ds").agg(F.min("nth").alias("nth"), F.sum("n").alias("n"), F.sum("c").alias("c"), F.sum(loss).alias("loss"), F.sum(F.col("n") * F.col("p")).alias("expected"))
    rate = F.col("c") / F.col("n")
    entropy = -(rate * F.ln(rate) + (1 - rate) * F.ln(1 - rate))
    ready = F.col("nth") > k
    daily = daily.withColumns({"label_rate": rate, "ne": F.when(ready & (rate > 0) & (rate < 1), F.col("loss") / F.col("n") / entropy), "calib_error": F.when(ready & (F.col("c") > 0), F.abs(F.col("expected") / F.col("c") - 1))})
    w = Window.orderBy("ds").rowsBetween(-k, -1)  # one row a partition
    return daily.select("ds", "nth", "ne", (F.col("ne") - F.when(F.count("ne").over(w) >= 1, F.avg("ne").over(w))).alias("cross_entropy_up"), "calib_error", "label_rate", F.when(ready, 1 - F.col("label_rate") / F.avg("label_rate").over(w)).alias("label_shift"))


def failure_labels(signals: DataFrame, level: int, thresholds: tuple[float, float, float] | None = None, observe: str = "same") -> DataFrame:
    """(ds, level, y): any of the three signals at the level; ``observe`` "next": a partition is judged by the day after it."""
    loss, calibration, shift = thresholds or LEVELS[level]
    hit = F.coalesce(F.col("cross_entropy_up") >= loss, F.lit(False)) | F.coalesce(F.col("calib_error") >= calibration, F.lit(False)) | F.coalesce(F.col("label_shift") >= shift, F.lit(False))
    y = hit.cast("int")
    if observe == "next":
        y = F.coalesce(F.lead(y).over(Window.orderBy("ds")), F.lit(0))
    return signals.select("ds", F.lit(level).alias("level"), y.alias("y"))


def performance_drop(metrics: DataFrame, metric: str, drop: float = 0.05, k: int = 7) -> DataFrame:
    """Partitions whose metric lies at least ``drop`` below the mean of the k before."""
    w = Window.orderBy("ds").rowsBetween(-k, -1)
    rows = metrics.withColumn("base", F.when(F.row_number().over(Window.orderBy("ds")) > k, F.avg(metric).over(w)))
    return rows.select("ds", metric, "base", F.coalesce(F.col(metric) <= (1 - drop) * F.col("base"), F.lit(False)).cast("int").alias("y"))


def quality_model(spark: SparkSession, docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(ds, n, accuracy) of a linear model on counts of the text, refitted for each batch on all batches before it: the stand-in with real signal.

    The model is least squares with a small ridge on the label as 0 or 1, cut at a half. It needs only sums of products,
    which are kept by batch and run up to the batch before; every labelled batch after the first gets a row. A row a batch passes through the window without key.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    share = lambda pattern: F.length(F.regexp_replace(text, pattern, "")) / F.greatest(F.length(text), F.lit(1))
    rows = docs.join(labels, "doc_id").filter("quality is not null").select(F.floor(F.col("doc_id") / 50).alias("ds"), F.col("quality").cast("double").alias("label"), F.lit(1.0).alias("one"), (1 - share(r"[^\w\s]")).alias("marks"), (1 - share(r"[A-Z]")).alias("upper"), F.log1p(F.length(text)).alias("size"))
    x = ["one", "marks", "upper", "size"]
    products = {f"{a}_{b}": F.sum(F.col(a) * F.col(b)) for i, a in enumerate(x) for b in [*x[i:], "label"]}
    batches = rows.groupBy("ds").agg(*(v.alias(k) for k, v in products.items()))
    before = Window.orderBy("ds").rowsBetween(Window.unboundedPreceding, -1)
    past = batches.select("ds", *(F.sum(k).over(before).alias(k) for k in products)).filter("one_one is not null")

    @F.pandas_udf("array<double>")
    def fit(sums: pd.DataFrame) -> pd.Series:
        out = []
        for r in sums.to_dict("records"):
            square = np.array([[r[f"{x[min(i, j)]}_{x[max(i, j)]}"] for j in range(len(x))] for i in range(len(x))])
            out.append(np.linalg.solve(square + 1e-6 * np.eye(len(x)), np.array([r[f"{a}_label"] for a in x])))
        return pd.Series(out)

    models = past.select("ds", fit(F.struct(*products)).alias("w"))
    prediction = (sum(F.col("w")[i] * F.col(a) for i, a in enumerate(x)) >= 0.5).cast("double")
    return rows.join(models, "ds").groupBy("ds").agg(F.count("*").alias("n"), F.avg((prediction == F.col("label")).cast("double")).alias("accuracy"))
