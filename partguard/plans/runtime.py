"""Runtime of one table's scores against the number of features: python -m partguard.plans.runtime SF_DIR N..."""

from __future__ import annotations

import sys
import time

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.stats import percentiles, w1
from ..methods import cluster as cl
from ..methods import clustered as cd
from ..methods import scores as sc
from ..methods.evaluation import timed
from ..sources.features import widened
from ..sources.tables import stored


def wide_summary(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """Summaries of ``n`` made features in array form: values are counted before they are summarised, as elsewhere."""
    rows, _ = widened(spark, sf_dir, n)
    counts = rows.select("ds", F.posexplode("x").alias("p", "num")).groupBy("ds", "p", "num").agg(F.count("*").alias("n"))
    valid = F.when(F.col("num").isNotNull(), F.col("n"))
    total, square = F.sum(F.col("num") * F.col("n")), F.sum(F.col("num") * F.col("num") * F.col("n"))
    s = counts.groupBy("ds", "p").agg(F.sum("n").alias("n_rows"), F.sum(valid).alias("n_valid"), total.alias("t"), square.alias("q"), F.min("num").alias("min"), F.max("num").alias("max"), F.count(valid).alias("n_distinct"), F.max(valid).alias("top_count"), percentiles("num", "n").alias("quantiles"))
    s = s.select("ds", F.format_string("f%05d", "p").alias("feature"), "n_rows", "n_valid", (F.col("n_valid") / F.col("n_rows")).alias("completeness"), (F.col("t") / F.col("n_valid")).alias("mean"), F.sqrt((F.col("q") - F.col("t") * F.col("t") / F.col("n_valid")) / (F.col("n_valid") - 1)).alias("stddev"), "min", "max", "n_distinct", (F.col("top_count") / F.col("n_rows")).alias("top_freq"), "quantiles")
    return s.withColumn("w1_prev", w1(F.col("quantiles"), F.lag("quantiles").over(Window.partitionBy("feature").orderBy("ds"))))


def study(spark: SparkSession, sf_dir: str, n: int, trials: int = 3) -> dict[str, float]:
    """Mean seconds, by method, to score the last partition against the stored summaries of all; the validator also for all partitions at once, and its fit apart.

    The two-sample test takes one trial beyond 2,000 features."""
    s = stored(wide_summary(spark, sf_dir, n), "wide")
    last = s.agg(F.max("ds")).first()[0]
    today = F.col("ds") == F.lit(last)
    began = time.perf_counter()
    groups = stored(cd.groups_frame(spark, cl.fit_groups(s.filter(~today), v=12)[0]), "groups")
    fit = time.perf_counter() - began
    out = {"knn_baseline": timed(lambda: sc.knn_score(s).filter(today), trials), "completeness_drop": timed(lambda: sc.completeness_drop(s).filter(today), trials), "zscore": timed(lambda: sc.zscore_score(s).filter(today), trials)}
    out["clustered"] = timed(lambda: cd.clustered_score(s, groups).filter(today), trials)
    out["clustered_with_fit"] = out["clustered"] + fit
    out["clustered_all_partitions"] = timed(lambda: cd.clustered_score(s, groups), trials)
    out["two_sample_w1"] = timed(lambda: sc.two_sample_score(sc.resample(sc.distances(s, "w1").filter(today).repartition(8, "feature"), "w1")), trials if n <= 2000 else 1)
    return out


if __name__ == "__main__":
    session = SparkSession.builder.master("local[8]").config(map={"spark.driver.memory": "12g", "spark.sql.shuffle.partitions": "8", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.warehouse.dir": "/tmp/runtime-warehouse"}).getOrCreate()
    session.sparkContext.setLogLevel("ERROR")
    for size in map(int, sys.argv[2:]):
        print(size, {k: round(v, 2) for k, v in study(session, sys.argv[1], size).items()}, flush=True)
