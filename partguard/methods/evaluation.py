"""Accuracy of scores against labels: precision, recall, average precision, precision at a recall, ratios; and cost."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

Keys = tuple[str, ...]


def pr_curve(scored: DataFrame, keys: Keys = ()) -> DataFrame:
    """(keys, tau, alerts, hits, precision, recall) at every distinct score, over rows with score and label (score, y); ties share a threshold."""
    rows = scored.filter("score is not null and y is not null")
    at = rows.groupBy(*keys, F.col("score").alias("tau")).agg(F.count("*").alias("n"), F.sum("y").alias("p"))
    down = Window.partitionBy(*keys).orderBy(F.desc("tau")).rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy(*keys)
    out = at.select(*keys, "tau", F.sum("n").over(down).alias("alerts"), F.sum("p").over(down).alias("hits"), F.sum("p").over(whole).alias("positives"))
    return out.select(*keys, "tau", "alerts", "hits", "positives", (F.col("hits") / F.col("alerts")).alias("precision"), F.try_divide("hits", F.col("positives")).alias("recall"))


def measures(scored: DataFrame, keys: Keys = (), recall: float = 0.9, best: bool = False) -> DataFrame:
    """(keys, precision_at, ap, n_scored, n_pos): precision at the highest threshold that reaches the recall, or the best from there on; average precision as a step sum."""
    curve = pr_curve(scored, keys)
    step = F.col("recall") - F.coalesce(F.lag("recall").over(Window.partitionBy(*keys).orderBy(F.desc("tau"))), F.lit(0.0))
    reached = F.col("recall") >= recall - 1e-12
    at = F.max(F.when(reached, F.col("precision"))) if best else F.max_by(F.when(reached, F.col("precision")), F.when(reached, F.col("tau")))
    got = curve.withColumn("step", step).groupBy(*keys).agg(at.alias("precision_at"), F.sum(F.col("step") * F.col("precision")).alias("ap"), F.max("alerts").alias("n_scored"), F.max("positives").alias("n_pos"))
    return got


def cumulative(scored: DataFrame, threshold: float) -> DataFrame:
    """(ds, precision, recall) of a fixed threshold over all partitions so far."""
    w = Window.orderBy("ds").rowsBetween(Window.unboundedPreceding, 0)
    rows = scored.filter("score is not null and y is not null").withColumn("a", (F.col("score") >= threshold).cast("int"))
    return rows.select("ds", F.try_divide(F.sum(F.col("a") * F.col("y")).over(w), F.sum("a").over(w)).alias("precision"), F.try_divide(F.sum(F.col("a") * F.col("y")).over(w), F.sum("y").over(w)).alias("recall"))


def failure_rate(labels: DataFrame) -> DataFrame:
    return labels.groupBy("level").agg(F.avg("y").alias("rate"), F.sum("y").alias("failures"), F.count("*").alias("n"))


def improvement(results: DataFrame, baseline: str) -> DataFrame:
    """(dataset, method, precision_factor, ap_factor): ratios to the baseline at each level, then their mean."""
    base = results.filter(F.col("method") == baseline).select("dataset", "level", F.col("precision_at").alias("bp"), F.col("ap").alias("ba"))
    return results.join(base, ["dataset", "level"]).groupBy("dataset", "method").agg(F.avg(F.try_divide("precision_at", F.col("bp"))).alias("precision_factor"), F.avg(F.try_divide("ap", F.col("ba"))).alias("ap_factor"))


def timed(make: Callable[[], DataFrame], trials: int = 3) -> float:
    """Mean seconds to compute a frame whole, without keeping it."""
    spent = []
    for _ in range(trials):
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        spent.append(time.perf_counter() - began)
    return sum(spent) / trials


def sizes(raw: DataFrame, summary: DataFrame) -> DataFrame:
    """Rows of the data against rows of its summary."""
    return raw.agg(F.count("*").alias("raw_rows")).crossJoin(summary.agg(F.count("*").alias("summary_rows"))).withColumn("ratio", F.col("summary_rows") / F.col("raw_rows"))
