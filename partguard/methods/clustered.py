"""The clustered validator: deviations averaged over groups of features, compared with those of clean earlier partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..operators.rolling import six_z
from .cluster import fit_groups

STAT_ORDER = {"completeness": 0, "mean": 1, "stddev": 2, "n_distinct": 3, "top_freq": 4, "w1_prev": 5}


def groups_frame(spark: SparkSession, groups: dict[str, int], version: str = "v1") -> DataFrame:
    return spark.createDataFrame([(f, int(c), version) for f, c in sorted(groups.items())], "feature string, cluster int, version string")


def cluster_means(z: DataFrame, groups: DataFrame) -> DataFrame:
    """(ds, cluster, stat, value): mean deviation of a group's features, 0 if none is known; the assignment, a row per feature, is broadcast."""
    return z.join(F.broadcast(groups.select("feature", "cluster")), "feature").groupBy("ds", "cluster", "stat").agg(F.coalesce(F.avg("absz"), F.lit(0.0)).alias("value"))


def matrix(means: DataFrame) -> DataFrame:
    """(ds, x): all of a partition's cells in one array, by cluster, then statistic."""
    order = F.coalesce(*(F.when(F.col("stat") == q, i) for q, i in STAT_ORDER.items()))
    return means.groupBy("ds").agg(F.sort_array(F.collect_list(F.struct("cluster", order.alias("q"), "value"))).alias("c")).select("ds", F.transform("c", lambda e: e["value"]).alias("x"))


def row_distances(means: DataFrame, nth: DataFrame, p: int = 1, k: int = 7, horizon: int | None = None) -> DataFrame:
    """(ds, t, other, u, d) of every row after the first k with the earlier ones: T rows of 6v numbers meet by (cluster, stat)."""
    keys = [c for c in ("version", "cluster", "stat") if c in means.columns]
    rows = means.join(F.broadcast(nth), "ds").filter(F.col("t") > k)
    other = rows.select(F.col("ds").alias("other"), F.col("t").alias("u"), *keys, F.col("value").alias("y"))
    scored = rows.filter("scored") if "scored" in means.columns else rows
    near = scored.join(other, keys).filter("u < t" if horizon is None else f"u < t AND u >= t - {horizon}")
    gap = F.abs(F.col("value") - F.col("y"))
    return near.groupBy("ds", "t", "other", "u").agg((F.sum(gap) if p == 1 else F.sqrt(F.sum(gap * gap))).alias("d"))


def ordinal(summary: DataFrame) -> DataFrame:
    """(ds, t): partitions numbered from 1, a row each."""
    return summary.select("ds").distinct().withColumn("t", F.row_number().over(Window.orderBy("ds")))


def neighbor_score(means: DataFrame, nth: DataFrame, share: float = 0.2, p: int = 1, k: int = 7, labels: DataFrame | None = None, neighbors: str = "clean", horizon: int | None = None, label_lag: int = 0) -> DataFrame:
    """Mean of the floor(share*t) smallest distances to earlier rows not known to be corrupted; at least one, as many as there are.

    ``labels`` (ds, y); a label counts once it is older than ``label_lag`` partitions. ``neighbors``: clean, corrupt or all."""
    d = row_distances(means, nth, p, k, horizon)
    if labels is not None and neighbors != "all":
        d = d.join(F.broadcast(labels.select(F.col("ds").alias("other"), "y")), "other", "left")
        known = F.coalesce((F.col("y") == 1) & (F.col("u") < F.col("t") - label_lag), F.lit(False))
        d = d.filter(known if neighbors == "corrupt" else ~known)
    ranked = d.withColumn("r", F.row_number().over(Window.partitionBy("ds").orderBy("d", "u"))).filter(F.col("r") <= F.greatest(F.lit(1), F.floor(F.lit(share) * F.col("t"))))
    return nth.select("ds").join(ranked.groupBy("ds").agg(F.avg("d").alias("score")), "ds", "left")


def clustered_score(summary: DataFrame, groups: DataFrame, k: int = 7, **how) -> DataFrame:
    return neighbor_score(cluster_means(six_z(summary, k), groups), ordinal(summary), k=k, **how)


def scheduled_groups(summary: DataFrame, method: str = "spectral", every: int = 7, k: int = 7, **fit) -> DataFrame:
    """(feature, cluster, version, since, before): assignments fitted anew for every ``every`` partitions, each on the partitions before those it is for.

    The first is for the first partition that can be scored, the k+2nd; the last has no ``before``. The list of
    partitions and a fit's assignment, a row per feature, pass through the driver; features that come up after a fit wait for the next one.
    """
    days = sorted(r["ds"] for r in summary.select("ds").distinct().collect())
    rows = []
    for i in range(k + 1, len(days), every):
        groups, _ = fit_groups(summary, method, until=days[i - 1], **fit)
        rows += [(f, int(c), f"until {days[i - 1]}", days[i], days[i + every] if i + every < len(days) else None) for f, c in sorted(groups.items())]
    ds = summary.schema["ds"].dataType
    return summary.sparkSession.createDataFrame(rows, StructType().add("feature", "string").add("cluster", "integer").add("version", "string").add("since", ds).add("before", ds))


def scheduled_means(z: DataFrame, fits: DataFrame) -> DataFrame:
    """Like ``cluster_means`` under every version, up to the last partition it is for; ``scored`` marks those it is for, the earlier ones are what they are compared with."""
    cells = z.join(fits, "feature").filter("before IS NULL OR ds < before")
    return cells.groupBy("version", "ds", "cluster", "stat", (F.col("ds") >= F.col("since")).alias("scored")).agg(F.coalesce(F.avg("absz"), F.lit(0.0)).alias("value"))


def refitted_score(summary: DataFrame, fits: DataFrame, k: int = 7, **how) -> DataFrame:
    """(ds, score, version): each partition under the groups fitted on partitions before it; all rows that it is compared with are in the same version."""
    scores = neighbor_score(scheduled_means(six_z(summary, k), fits), ordinal(summary), k=k, **how)
    blocks = fits.select("version", "since", "before").distinct()
    return scores.join(F.broadcast(blocks), F.expr("ds >= since AND (before IS NULL OR ds < before)"), "left").select("ds", "score", "version")


def threshold_from_z(zmax: float, v: int, stats: int = 1) -> float:
    """A score threshold that can be read: the largest deviation one lets pass, times the number of clusters (and of statistics, if asked)."""
    return zmax * v * stats


def rank_clusters(means: DataFrame, ds, how: str = "sum") -> DataFrame:
    """Clusters of a partition by the sum (or the largest) of their six cells."""
    total = means.filter(F.col("ds") == F.lit(ds)).groupBy("cluster").agg((F.sum if how == "sum" else F.max)("value").alias("value"))
    return total.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("value"), "cluster")))


def rank_features(z: DataFrame, groups: DataFrame, means: DataFrame, ds, top: int = 2) -> DataFrame:
    """Inside the ``top`` clusters, (feature, stat) by deviation."""
    best = rank_clusters(means, ds).filter(F.col("rank") <= top).select("cluster", F.col("rank").alias("cluster_rank"))
    rows = z.filter((F.col("ds") == F.lit(ds)) & F.col("absz").isNotNull()).join(F.broadcast(groups.select("feature", "cluster")), "feature").join(F.broadcast(best), "cluster")
    return rows.select("cluster", "cluster_rank", "feature", "stat", "absz", F.row_number().over(Window.partitionBy("cluster").orderBy(F.desc("absz"), "feature", "stat")).alias("rank"))


def similar_incidents(means: DataFrame, nth: DataFrame, labels: DataFrame, ds, k: int = 7, p: int = 1) -> DataFrame:
    """Earlier corrupted partitions, nearest first: what an alert looks like may have been seen before."""
    d = row_distances(means, nth, p, k).filter(F.col("ds") == F.lit(ds))
    return d.join(F.broadcast(labels.filter("y = 1").select(F.col("ds").alias("other"))), "other").select("other", "d", F.row_number().over(Window.orderBy("d", "other")).alias("rank"))


def alert_report(z: DataFrame, groups: DataFrame, means: DataFrame, ds, top: int = 2, features: int = 5) -> DataFrame:
    """One row of JSON for whoever is on call: partition, weekday, clusters with their worst features."""
    worst = rank_features(z, groups, means, ds, top).filter(F.col("rank") <= features)
    per = worst.groupBy("cluster", "cluster_rank").agg(F.sort_array(F.collect_list(F.struct("rank", "feature", "stat", F.round("absz", 6).alias("absz")))).alias("features"))
    body = F.struct(F.lit(ds).alias("ds"), F.sort_array(F.collect_list(F.struct("cluster_rank", "cluster", "features"))).alias("clusters"))
    return per.agg(F.to_json(body).alias("report"))
