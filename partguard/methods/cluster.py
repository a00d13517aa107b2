"""Groups of features that move together, from summaries of past partitions alone."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.rolling import SIX
from .scores import stat_rows

FLAT = -1
#: Most features for which the weights of all pairs are held by the driver: 32 MB of them.
DENSE_LIMIT = 2_000


def stat_covariance(summary: DataFrame, stats: tuple[str, ...] = SIX, until=None, kind: str = "correlation") -> DataFrame:
    """(stat, f1, f2, cov) for f1 <= f2 over partitions up to ``until``; correlations with a flat feature are 0."""
    rows = stat_rows(summary if until is None else summary.filter(F.col("ds") <= F.lit(until)), stats)
    left, right = rows.select("ds", "stat", F.col("feature").alias("f1"), F.col("x").alias("a")), rows.select("ds", "stat", F.col("feature").alias("f2"), F.col("x").alias("b"))
    made = left.join(right, ["ds", "stat"]).filter("f1 <= f2").groupBy("stat", "f1", "f2")
    if kind == "covariance":
        return made.agg(F.covar_samp("a", "b").alias("cov"))
    sa, sb = F.stddev_samp("a"), F.stddev_samp("b")
    flat = (sa <= 1e-9 * F.greatest(F.lit(1.0), F.abs(F.avg("a")))) | (sb <= 1e-9 * F.greatest(F.lit(1.0), F.abs(F.avg("b"))))
    return made.agg(F.when(flat | sa.isNull() | sb.isNull(), 0.0).otherwise(F.try_divide(F.covar_samp("a", "b"), sa * sb)).alias("cov"))


def feature_graph(cov: DataFrame, top: int | None = None) -> DataFrame:
    """(src, dst, weight): absolute covariances summed over the statistics; with ``top`` only each feature's strongest edges."""
    edges = cov.filter("f1 < f2").groupBy(F.col("f1").alias("src"), F.col("f2").alias("dst")).agg(F.sum(F.abs("cov")).alias("weight"))
    if top is None:
        return edges
    from pyspark.sql import Window

    both = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    strong = both.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("weight"), "dst"))).filter(F.col("r") <= top)
    return strong.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "weight").distinct()


def stat_matrices(summary: DataFrame, stats: tuple[str, ...] = SIX, until=None) -> tuple[list[str], dict[str, np.ndarray]]:
    """Per statistic the partitions-by-features table, standardised by feature, flat features as 0: T times n numbers each."""
    rows = summary if until is None else summary.filter(F.col("ds") <= F.lit(until))
    table = rows.select(F.col("ds").cast("string").alias("ds"), "feature", *(F.col(q).cast("double").alias(q) for q in stats)).toArrow()
    row, days = pd.factorize(table["ds"].to_pandas(), sort=True)
    column, features = pd.factorize(table["feature"].to_pandas(), sort=True)
    names, out = features.tolist(), {}
    for q in stats:
        x = np.full((len(days), len(names)), np.nan)
        x[row, column] = table[q].to_numpy()
        held = ~np.isnan(x)
        x = np.where(held, x, np.where(held, x, 0.0).sum(0) / np.maximum(held.sum(0), 1))
        mean, std = x.mean(0), x.std(0, ddof=1) if len(x) > 1 else np.zeros(x.shape[1])
        live = std > 1e-9 * np.maximum(1, np.abs(mean))
        out[q] = np.where(live, (x - mean) / np.where(live, std, 1), 0.0)
    return names, out


def choose_clusters(matrices: dict[str, np.ndarray], explained: float = 0.95) -> tuple[int, dict[str, int]]:
    """Number of clusters: per statistic the fewest principal components that explain the share, then the largest of those.

    The T by T Gram matrix has the covariance matrix' spectrum, so the count of features costs nothing here."""
    per = {}
    for q, x in matrices.items():
        values = np.clip(np.linalg.eigvalsh(x @ x.T)[::-1], 0, None)
        per[q] = int(np.searchsorted(np.cumsum(values) / values.sum(), explained - 1e-12) + 1) if values.sum() > 1e-12 else 0
    n = next(iter(matrices.values())).shape[1]
    return max(1, min(n, max(per.values()))), per


def _kmeans(x: np.ndarray, k: int, seed: int, restarts: int = 10) -> np.ndarray:
    rng, best, kept = np.random.default_rng(seed), np.inf, np.zeros(len(x), int)
    for _ in range(restarts):
        centres = [x[rng.integers(len(x))]]
        for _ in range(k - 1):
            d = np.min([((x - c) ** 2).sum(1) for c in centres], axis=0)
            centres.append(x[rng.choice(len(x), p=d / d.sum()) if d.sum() > 1e-12 else rng.integers(len(x))])
        c = np.array(centres)
        for _ in range(100):
            d = ((x[:, None] - c[None]) ** 2).sum(2)
            labels = d.argmin(1)
            new = np.array([x[labels == j].mean(0) if (labels == j).any() else x[d.min(1).argmax()] for j in range(k)])
            if np.allclose(new, c):
                break
            c = new
        cost = ((x - c[labels]) ** 2).sum()
        if cost < best - 1e-12:
            best, kept = cost, labels
    return kept


def canonical(names: list, labels) -> dict:
    """Labels renumbered by their smallest member's name."""
    first: dict = {}
    for name, label in sorted(zip(names, labels)):
        first.setdefault(label, len(first))
    return {name: first[label] for name, label in zip(names, labels)}


def spectral(names: list[str], weight: np.ndarray, v: int, seed: int = 3) -> dict[str, int]:
    """Normalised spectral clustering into at most ``v`` groups; features without any edge share one reserved group, the last."""
    degree = weight.sum(1)
    live = np.flatnonzero(degree > 1e-12)
    labels = np.full(len(names), FLAT)
    if len(live):
        room = max(1, v - (len(live) < len(names)))
        if room >= len(live):
            labels[live] = np.arange(len(live))
        else:
            w = weight[np.ix_(live, live)]
            root = 1 / np.sqrt(w.sum(1))
            _, vectors = np.linalg.eigh(np.eye(len(live)) - root[:, None] * w * root[None])
            u = vectors[:, :room]
            u = u / np.maximum(np.linalg.norm(u, axis=1, keepdims=True), 1e-12)
            labels[live] = _kmeans(u, room, seed)
    return canonical(names, labels.tolist())


def graph_matrix(names: list[str], matrices: dict[str, np.ndarray]) -> np.ndarray:
    """Summed absolute correlations of all features, diagonal 0."""
    total = np.zeros((len(names), len(names)))
    for x in matrices.values():
        total += np.abs(x.T @ x) / max(1, len(x) - 1)
    np.fill_diagonal(total, 0)
    return total


def sparse_graph(summary: DataFrame, names: list[str], matrices: dict[str, np.ndarray], top: int = 10, block: int = 256) -> DataFrame:
    """The graph of very many features, each with its strongest edges: blocks of features against all, on the executors.

    What is broadcast is T times n numbers per statistic, a few MB at twenty thousand features; the n by n matrix never exists."""
    spark = summary.sparkSession
    shared = spark.sparkContext.broadcast((names, {q: x.astype(np.float32) for q, x in matrices.items()}))
    starts = spark.range(0, len(names), block, numPartitions=max(1, -(-len(names) // block)))

    def work(batches):
        names, mats = shared.value
        for pdf in batches:
            for i in pdf["id"]:
                total = sum(np.abs(x[:, i : i + block].T @ x) / max(1, len(x) - 1) for x in mats.values())
                own = np.arange(len(total))
                total[own, i + own] = 0
                near = np.argpartition(-total, min(top, total.shape[1] - 1), axis=1)[:, :top]
                made = pd.DataFrame({"a": np.repeat(i + own, near.shape[1]), "b": near.ravel(), "weight": np.take_along_axis(total, near, 1).ravel()})
                made = made[made["weight"] > 1e-12]
                yield pd.DataFrame({"src": made[["a", "b"]].min(axis=1), "dst": made[["a", "b"]].max(axis=1), "weight": made["weight"].astype(float)})

    return starts.mapInPandas(work, "src long, dst long, weight double").groupBy("src", "dst").agg(F.max("weight").alias("weight"))


def pic(summary: DataFrame | None, edges: DataFrame, names: list[str], v: int, iterations: int = 20) -> dict[str, int]:
    """Power iteration clustering on an edge table of feature numbers: the distributed form for very many features."""
    from pyspark.ml.clustering import PowerIterationClustering

    found = PowerIterationClustering(k=v, maxIter=iterations, initMode="random", weightCol="weight").assignClusters(edges).collect()  # a row per feature
    label = {r["id"]: r["cluster"] for r in found}
    return canonical(names, [label.get(i, FLAT) for i in range(len(names))])


def groups_from_components(edges: DataFrame, names: list, at_least: float) -> dict:
    """Connected components of the edges of a weight or more, by a forest over the n features; the edges come in a stream, so the driver holds one partition of them."""
    parent = {n: n for n in names}

    def root(n):
        while parent[n] != n:
            parent[n] = n = parent[parent[n]]
        return n

    for r in edges.filter(F.col("weight") >= at_least).select("src", "dst").toLocalIterator():
        a, b = sorted((root(r["src"]), root(r["dst"])))
        parent[b] = a
    return canonical(names, [root(n) for n in names])


def fit_groups(summary: DataFrame, method: str = "spectral", until=None, explained: float = 0.95, seed: int = 3, v: int | None = None, given: dict[str, int] | None = None, threshold: float = 3.0, dense: int = DENSE_LIMIT) -> tuple[dict[str, int], int]:
    """Assignment of features to groups, and their number. ``method``: spectral, pic, components, kmeans, single, identity or given.

    Above ``dense`` features no table of all pairs is made: spectral becomes pic, its power iteration on executors, and
    components takes each feature's ten strongest edges, which executors find block by block.
    """
    names, matrices = stat_matrices(summary, until=until)
    v = v or choose_clusters(matrices, explained)[0]
    if method == "given":
        out = canonical(names, [(given or {}).get(n, FLAT) for n in names])
    elif method == "single":
        out = {n: 0 for n in names}
    elif method == "identity":
        out = {n: i for i, n in enumerate(names)}
    elif method == "kmeans":
        out = canonical(names, _kmeans(np.concatenate(list(matrices.values())).T, min(v, len(names)), seed).tolist())
    elif method == "components" and len(names) > dense:
        strong = sparse_graph(summary, names, matrices)
        numbers = groups_from_components(strong, list(range(len(names))), threshold)
        out = canonical(names, [numbers[i] for i in range(len(names))])
    elif method == "components":
        out = groups_from_components(feature_graph(stat_covariance(summary, until=until)), names, threshold)
    elif method == "pic" or len(names) > dense:
        out = pic(summary, sparse_graph(summary, names, matrices), names, v)
    else:
        out = spectral(names, graph_matrix(names, matrices), v, seed)
    return out, max(out.values()) + 1
