"""Scores of partitions from their summaries: the adaptations, the nearest-neighbour baseline and the plain references."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.stats import DISTANCES
from ..operators.rolling import changes, rolling_quantiles

SEVEN = ("completeness", "n_distinct", "top_freq", "max", "mean", "min", "stddev")


def _scored(rows: DataFrame, contribution: Column) -> DataFrame:
    """Mean contribution of a partition's features; null while no feature has a base."""
    known = F.col("s").isNotNull() & F.col("base").isNotNull()
    return rows.withColumn("c", F.when(known, F.coalesce(contribution, F.lit(0.0)))).groupBy("ds").agg(F.avg("c").alias("score"))


def general_score(summary: DataFrame, stat: str, norm: str = "rel", absolute: bool = False, k: int = 7, **how) -> DataFrame:
    """Mean relative change or z-score of the features, signed unless ``absolute``."""
    x = F.col(norm)
    return _scored(changes(summary, stat, k=k, **how), F.abs(x) if absolute else x)


def completeness_drop(summary: DataFrame, delta: float = 0.3, direction: str = "drop", k: int = 7) -> DataFrame:
    """Mean absolute loss of completeness of the features that lost at least the share ``delta`` of their base."""
    signed = {"drop": -F.col("rel"), "rise": F.col("rel"), "both": F.abs("rel")}[direction]
    return _scored(changes(summary, "completeness", k=k), F.when(signed >= delta, F.abs("rel") * F.col("base")).otherwise(0.0))


def completeness_alerts(summary: DataFrame, drop: float = 0.3, k: int = 7) -> DataFrame:
    """(ds, feature, rel): one alert for each feature that lost over ``drop`` of its base, unweighted: the practice that raises too many."""
    return changes(summary, "completeness", k=k).filter(F.col("rel") < -drop).select("ds", "feature", "rel")


def delta_sweep(summary: DataFrame, deltas: list[float], k: int = 7) -> DataFrame:
    """(delta, ds, score) for all deltas from one pass."""
    rows = changes(summary, "completeness", k=k).select("ds", "s", "base", "rel", F.explode(F.array(*map(F.lit, deltas))).alias("delta"))
    known = F.col("s").isNotNull() & F.col("base").isNotNull()
    hit = F.coalesce(-F.col("rel") >= F.col("delta"), F.lit(False))
    return rows.withColumn("c", F.when(known, F.when(hit, F.abs("rel") * F.col("base")).otherwise(0.0))).groupBy("delta", "ds").agg(F.avg("c").alias("score"))


def zscore_score(summary: DataFrame, stat: str = "completeness", tau: float = 3.0, contrib: str = "sum", k: int = 7, **how) -> DataFrame:
    """Mean |z| of the features, where only |z| >= tau counts; ``indicator``: the share of such features."""
    z = F.abs("z")
    return _scored(changes(summary, stat, k=k, **how), F.when(z >= tau, F.lit(1.0) if contrib == "indicator" else z).otherwise(0.0))


def distances(summary: DataFrame, kind: str, k: int = 7) -> DataFrame:
    """(ds, feature, h, quantiles, reference): distance of a partition's percentiles to the mean percentiles of the k before."""
    return rolling_quantiles(summary, k).withColumn("h", F.when(F.col("reference").isNotNull(), DISTANCES[kind](F.col("quantiles"), F.col("reference")))).select("ds", "feature", "h", "quantiles", "reference")


def distance_score(summary: DataFrame, kind: str, k: int = 7) -> DataFrame:
    """Mean distance of the features: large distances alone, without a test."""
    return distances(summary, kind, k).groupBy("ds").agg(F.avg("h").alias("score"))


def resample(dist: DataFrame, kind: str, times: int = 200, seed: int = 17, tail: str = "upper", sort: bool = True) -> DataFrame:
    """Add ``p``: pool both vectors, deal the 198 numbers into halves ``times`` times, and compare the distances with the observed one.

    p = (1 + resampled at least as far) / (1 + times); ``tail`` "literal": the share that is not
    farther. Rows are drawn with a seed of their own (feature, ds), so a task that runs again gives
    the same. Without ``sort`` the halves are compared in drawn order.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            p = []
            for q, r, key in zip(pdf["quantiles"], pdf["reference"], pdf["key"]):
                if r is None:
                    p.append(None)
                    continue
                pool = np.concatenate([np.asarray(q, float), np.asarray(r, float)])
                order = np.random.default_rng([seed, key & 0xFFFFFFFF]).random((times, 198)).argsort(1)
                a, b = pool[order[:, :99]], pool[order[:, 99:]]
                if sort:
                    a, b = np.sort(a, 1), np.sort(b, 1)
                gap = np.abs(a - b)
                seen = np.abs(pool[:99] - pool[99:])
                # the spread term of the pooled numbers is the same for every deal: it orders nothing
                far, own = (gap.max(1), seen.max()) if kind == "ks" else (gap.sum(1), seen.sum())
                tol = 1e-12 * max(1.0, abs(own))
                p.append((1 + int((far >= own - tol).sum())) / (1 + times) if tail == "upper" else int((far <= own + tol).sum()) / times)
            out = pdf[["ds", "feature", "h"]].copy()
            out["p"] = pd.Series(p, dtype="float64", index=out.index)
            yield out

    kind_ds = dict(dist.dtypes)["ds"]
    keyed = dist.withColumn("key", F.xxhash64("feature", F.col("ds").cast("string")))
    return keyed.mapInPandas(run, f"ds {kind_ds}, feature string, h double, p double")


def resample_hashed(dist: DataFrame, kind: str, times: int = 39) -> DataFrame:
    """The same test with deals by rank of a hash of (feature, ds, deal, place), in built-in functions alone, so that SQL elsewhere repeats it."""
    pool = dist.filter("reference is not null").withColumn("pool", F.concat("quantiles", "reference"))
    each = pool.select("ds", "feature", "h", F.explode(F.sequence(F.lit(1), F.lit(times))).alias("deal"), "pool")
    key = lambda i: F.md5(F.concat_ws("|", "feature", F.col("ds").cast("string"), F.col("deal").cast("string"), (i + 1).cast("string")).cast("binary"))
    dealt = F.array_sort(F.transform("pool", lambda x, i: F.struct(key(i).alias("k"), x.alias("x"))))
    half = lambda lo: F.array_sort(F.transform(F.slice("dealt", lo, 99), lambda e: e["x"]))
    far = DISTANCES["w1" if kind == "dts" else kind](half(1), half(100))
    own = DISTANCES["w1" if kind == "dts" else kind](F.slice("pool", 1, 99), F.slice("pool", 100, 99))
    hit = (far >= own - 1e-9 * F.greatest(F.lit(1.0), F.abs(own))).cast("int")
    return each.withColumn("dealt", dealt).select("ds", "feature", "h", hit.alias("hit")).groupBy("ds", "feature").agg(F.first("h").alias("h"), ((1 + F.sum("hit")) / F.lit(1 + times)).alias("p"))


def two_sample_score(tested: DataFrame, alpha: float = 0.05) -> DataFrame:
    """Share of a partition's features whose p-value is at most alpha."""
    return tested.groupBy("ds").agg(F.avg(F.when(F.col("p").isNotNull(), (F.col("p") <= alpha).cast("double"))).alias("score"))


def stat_rows(summary: DataFrame, stats: tuple[str, ...] = SEVEN) -> DataFrame:
    """(ds, feature, stat, x): the statistics as rows, those a feature lacks left out."""
    return summary.select("ds", "feature", F.inline(F.array(*(F.struct(F.lit(q).alias("stat"), F.col(q).cast("double").alias("x")) for q in stats)))).filter("x is not null")


def rescaled(rows: DataFrame, how: str) -> DataFrame:
    """within_vector: each partition's entries to [0, 1] over that partition; per_dimension: each entry over its own history up to today; none."""
    if how == "none":
        return rows
    w = Window.partitionBy("ds") if how == "within_vector" else Window.partitionBy("feature", "stat").orderBy("ds").rowsBetween(Window.unboundedPreceding, 0)
    low, high = F.min("x").over(w), F.max("x").over(w)
    return rows.withColumn("x", F.coalesce(F.try_divide(F.col("x") - low, high - low), F.lit(0.0)))


def vector_distances(rows: DataFrame, metric: str = "euclidean", horizon: int | None = None) -> DataFrame:
    """(ds, other, d) of every partition with every earlier one; an entry that one side lacks counts as 0 there.

    The join is by (feature, stat) and partial sums leave each task before the shuffle: T*T/2 rows at most."""
    nth = rows.select("ds").distinct().withColumn("t", F.row_number().over(Window.orderBy("ds")))  # one row a partition
    grid = nth.crossJoin(F.broadcast(rows.select("feature", "stat").distinct()))
    dense = grid.join(rows, ["ds", "feature", "stat"], "left").withColumn("x", F.coalesce("x", F.lit(0.0)))
    other = dense.select(F.col("ds").alias("other"), "feature", "stat", F.col("x").alias("y"), F.col("t").alias("u"))
    pairs = dense.join(other, ["feature", "stat"]).filter("u < t" if horizon is None else f"u < t AND u >= t - {horizon}")
    gap = F.abs(F.col("x") - F.col("y"))
    total = {"euclidean": F.sqrt(F.sum(gap * gap)), "l1": F.sum(gap), "chebyshev": F.max(gap)}[metric]
    return pairs.groupBy("ds", "other").agg(total.alias("d"))


def knn_score(summary: DataFrame, neighbors: int = 5, metric: str = "euclidean", agg: str = "mean", rescale: str = "within_vector", stats: tuple[str, ...] = SEVEN, rows: DataFrame | None = None) -> DataFrame:
    """Distance of a partition's vector of seven statistics to its nearest earlier ones: the baseline."""
    vectors = rescaled(stat_rows(summary, stats) if rows is None else rows, rescale)
    ranked = vector_distances(vectors, metric).withColumn("r", F.row_number().over(Window.partitionBy("ds").orderBy("d", "other"))).filter(F.col("r") <= neighbors)
    score = {"mean": F.avg("d"), "max": F.max("d"), "median": F.median("d")}[agg]
    return vectors.select("ds").distinct().join(ranked.groupBy("ds").agg(score.alias("score")), "ds", "left")


def pca_score(summary: DataFrame, explained: float = 0.95, stats: tuple[str, ...] = SEVEN, k: int = 7) -> DataFrame:
    """Distance from the past in the space of principal components: partitions by features and statistics, standardised; T by T on the driver.

    Scores are means of squared component values over their variance on all earlier partitions; null before k partitions."""
    spark = summary.sparkSession
    rows = stat_rows(summary, stats).toPandas()
    wide = rows.pivot_table(index="ds", columns=["feature", "stat"], values="x").sort_index()
    raw = wide.to_numpy(float)
    out = []
    days = wide.index.tolist()
    for t in range(len(raw)):
        if t < k:
            out.append((days[t], None))
            continue
        held = ~np.isnan(raw[:t])
        mean = np.where(held, raw[:t], 0).sum(0) / np.maximum(held.sum(0), 1)
        x = np.where(np.isnan(raw[: t + 1]), mean, raw[: t + 1])  # a missing entry takes the mean of its past
        past = x[:t]
        std = past.std(0, ddof=1)
        scale = np.where(std > 1e-9, std, 1.0)
        a, today = (past - mean) / scale, np.where(std > 1e-9, (x[t] - mean) / scale, 0.0)
        values, vectors = np.linalg.eigh(a @ a.T)
        order = np.argsort(values)[::-1]
        values, vectors = values[order], vectors[:, order]
        keep = values > 1e-9
        m = int(np.searchsorted(np.cumsum(values[keep]) / values[keep].sum(), explained) + 1) if keep.any() else 0
        m = min(m, int(keep.sum()))
        axes = (a.T @ vectors[:, :m]) / np.sqrt(values[:m]) if m else np.zeros((a.shape[1], 0))
        parts = (today @ axes) ** 2 / (values[:m] / max(1, t - 1)) if m else np.zeros(0)
        out.append((days[t], float(parts.mean()) if m else 0.0))
    return spark.createDataFrame(out, f"ds {dict(summary.dtypes)['ds']}, score double")


def constant_score(summary: DataFrame, value: float) -> DataFrame:
    """Always block (1) or never (0)."""
    return summary.select("ds").distinct().withColumn("score", F.lit(float(value)))


def constraint_check(rows: DataFrame, rules: list[tuple[str, str]], ds: str = "ds") -> DataFrame:
    """(ds, rule, violations, share): rows that break hand-written predicates, all rules in one pass; null breaks a rule."""
    made = rows.groupBy(F.col(ds).alias("ds")).agg(F.count("*").alias("n"), *(F.sum((~F.coalesce(F.expr(p), F.lit(False))).cast("long")).alias(f"r{i}") for i, (_, p) in enumerate(rules)))
    return made.select("ds", F.inline(F.array(*(F.struct(F.lit(name).alias("rule"), F.col(f"r{i}").alias("violations"), (F.col(f"r{i}") / F.col("n")).alias("share")) for i, (name, _) in enumerate(rules)))))


def schema_check(rows: DataFrame, types: dict[str, str], bounds: dict[str, tuple[float, float]], ds: str = "ds") -> DataFrame:
    """Static validation: columns of the wrong type fail on every row, values outside their bounds on theirs."""
    have = dict(rows.dtypes)
    rules = [(f"type:{c}", "true" if have.get(c) == t else "false") for c, t in types.items()]
    rules += [(f"bounds:{c}", f"`{c}` BETWEEN {lo} AND {hi}") for c, (lo, hi) in bounds.items()]
    return constraint_check(rows, rules, ds)


def fd_check(rows: DataFrame, lhs: str, rhs: str, ds: str = "ds") -> DataFrame:
    """Share of values of ``lhs`` that meet more than one value of ``rhs`` in a partition."""
    pairs = rows.select(F.col(ds).alias("ds"), F.col(lhs).alias("l"), F.col(rhs).alias("r")).distinct()
    return pairs.groupBy("ds", "l").agg(F.count("*").alias("n")).groupBy("ds").agg(F.count("*").alias("groups"), F.sum((F.col("n") > 1).cast("long")).alias("broken")).withColumn("share", F.col("broken") / F.col("groups"))
