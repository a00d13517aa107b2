"""Normalisation over time: every statistic against the same feature's earlier partitions, today left out."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

EPS, CAP = 1e-9, 10.0
SIX = ("completeness", "mean", "stddev", "n_distinct", "top_freq", "w1_prev")


def _window(keys: tuple[str, ...] = ("feature",)):
    return Window.partitionBy(*keys).orderBy("ds")


def rolling(summary: DataFrame, stat: str, k: int = 7, ddof: int = 1, partial: bool = False, keys: tuple[str, ...] = ("feature",), season: int | None = None, clean_only: str | None = None) -> DataFrame:
    """Add ``s``, ``base`` and ``spread``: the statistic, its mean and deviation over the ``k`` partitions before.

    Both are null before k partitions exist (with ``partial``: two) and the spread also below two
    values. ``season``: only every season-th partition counts, e.g. the same weekday. ``clean_only``:
    a 0/1 column; rows with 1 leave the base.
    """
    keys = (*keys, "slot") if season else keys
    rows = summary.withColumn("s", F.col(stat).cast("double"))
    if season:
        rows = rows.withColumn("slot", F.datediff("ds", F.lit("1970-01-05").cast("date")) % season)
    w = _window(keys)
    before = w.rowsBetween(-k, -1)
    if clean_only:
        history = F.slice(F.reverse(F.collect_list(F.when(F.col(clean_only) == 0, F.col("s"))).over(w.rowsBetween(Window.unboundedPreceding, -1))), 1, k)
        return rows.withColumn("h", history).withColumn("base", F.when(F.size("h") >= (2 if partial else k), F.aggregate("h", F.lit(0.0), lambda a, x: a + x) / F.nullif(F.size("h"), F.lit(0)))).withColumn("spread", F.when(F.size("h") >= 2, F.sqrt(F.aggregate("h", F.lit(0.0), lambda a, x: a + (x - F.col("base")) * (x - F.col("base"))) / (F.size("h") - ddof)))).drop("h")
    enough = F.row_number().over(w) > (2 if partial else k)
    deviation = F.stddev_samp("s") if ddof else F.stddev_pop("s")
    return rows.withColumn("base", F.when(enough, F.avg("s").over(before))).withColumn("spread", F.when(enough & (F.count("s").over(before) >= 2), deviation.over(before)))


def rel_change() -> Column:
    return F.when(F.col("base") != 0, (F.col("s") - F.col("base")) / F.col("base"))


def z_change(eps: float = EPS, cap: float = CAP, on_flat: str = "cap") -> Column:
    """(s - base) / spread; over a flat history 0 if nothing changed, else ±cap (``on_flat`` "null": null)."""
    gap = F.col("s") - F.col("base")
    tolerance = eps * F.greatest(F.lit(1.0), F.abs("base"))
    flat = F.when(F.abs(gap) <= tolerance, 0.0).otherwise(F.signum(gap) * cap) if on_flat == "cap" else F.lit(None).cast("double")
    return F.when(F.col("spread") <= tolerance, flat).otherwise(F.try_divide(gap, F.col("spread")))


def changes(summary: DataFrame, stat: str, **how) -> DataFrame:
    """(ds, feature, s, base, spread, rel, z) of one statistic."""
    flat = {k: how.pop(k) for k in ("eps", "cap", "on_flat") if k in how}
    return rolling(summary, stat, **how).withColumn("rel", rel_change()).withColumn("z", z_change(**flat))


def six_z(summary: DataFrame, k: int = 7, stats: tuple[str, ...] = SIX) -> DataFrame:
    """(ds, feature, stat, absz) of all six statistics, from one window sort and one unpivot."""
    w = _window()
    before = w.rowsBetween(-k, -1)
    rows = summary.select("ds", "feature", *(F.col(q).cast("double").alias(q) for q in stats), F.row_number().over(w).alias("nth"))
    cells = []
    for q in stats:
        # the first partition has no gap to a partition before it, so its statistic starts a partition later
        enough = F.col("nth") > k + (q == "w1_prev")
        base, spread = F.when(enough, F.avg(q).over(before)), F.when(enough & (F.count(q).over(before) >= 2), F.stddev_samp(q).over(before))
        cells.append((q, base, spread))
    wide = rows.select("ds", "feature", *stats, *(b.alias(f"b_{q}") for q, b, _ in cells), *(s.alias(f"d_{q}") for q, _, s in cells))
    each = [F.struct(F.lit(q).alias("stat"), F.col(q).alias("s"), F.col(f"b_{q}").alias("base"), F.col(f"d_{q}").alias("spread")) for q in stats]
    return wide.select("ds", "feature", F.inline(F.array(*each))).select("ds", "feature", "stat", F.abs(z_change()).alias("absz"))


def dynamic_bounds(summary: DataFrame, stat: str, m: float = 3.0, k: int = 7) -> DataFrame:
    return rolling(summary, stat, k).withColumns({"lo": F.col("base") - m * F.col("spread"), "hi": F.col("base") + m * F.col("spread")}).withColumn("inside", F.col("s").between(F.col("lo"), F.col("hi")))


def static_bounds(summary: DataFrame, stat: str, lo: float, hi: float) -> DataFrame:
    return summary.withColumn("s", F.col(stat).cast("double")).withColumn("inside", F.col("s").between(lo, hi))


def vs_previous(summary: DataFrame, stat: str) -> DataFrame:
    """Relative change to the partition before."""
    rows = summary.withColumn("s", F.col(stat).cast("double")).withColumn("base", F.lag(F.col(stat).cast("double")).over(_window()))
    return rows.withColumn("rel", rel_change())


def vs_history(summary: DataFrame) -> DataFrame:
    """Completeness, mean and deviation of the bag union of all earlier partitions, from pooled counts and moments, with relative changes."""
    before = _window().rowsBetween(Window.unboundedPreceding, -1)
    n = F.when(F.col("mean").isNotNull(), F.col("n_valid")).otherwise(0).cast("double")
    m, m2 = F.coalesce("mean", F.lit(0.0)), F.coalesce(F.col("stddev") * F.col("stddev") * (F.col("n_valid") - 1), F.lit(0.0))
    rows = summary.withColumns({"pn": F.sum(n).over(before), "ps": F.sum(n * m).over(before), "pq": F.sum(m2 + n * m * m).over(before), "pv": F.sum("n_valid").over(before), "pr": F.sum("n_rows").over(before)})
    rows = rows.withColumns({"h_completeness": F.col("pv") / F.col("pr"), "h_mean": F.try_divide("ps", F.col("pn"))})
    rows = rows.withColumn("h_stddev", F.when(F.col("pn") > 1, F.sqrt(F.greatest(F.col("pq") - F.col("pn") * F.col("h_mean") * F.col("h_mean"), F.lit(0.0)) / (F.col("pn") - 1))))
    rel = lambda q: F.when(F.col(f"h_{q}") != 0, (F.col(q) - F.col(f"h_{q}")) / F.col(f"h_{q}"))
    return rows.withColumns({f"rel_{q}": rel(q) for q in ("completeness", "mean", "stddev")}).drop("pn", "ps", "pq", "pv", "pr")


def ewma(summary: DataFrame, stat: str, alpha: float = 0.3, depth: int = 14) -> DataFrame:
    """Exponentially weighted mean of the ``depth`` partitions before, newest first: weights (1-alpha)**i over their sum."""
    rows = summary.withColumn("s", F.col(stat).cast("double"))
    lags = [(F.lag("s", i + 1).over(_window()), (1 - alpha) ** i) for i in range(depth)]
    wide = rows.select("*", *(x.alias(f"l{i}") for i, (x, _) in enumerate(lags)))
    top = sum((F.coalesce(F.col(f"l{i}") * w, F.lit(0.0)) for i, (_, w) in enumerate(lags)), F.lit(0.0))
    low = sum((F.when(F.col(f"l{i}").isNotNull(), w).otherwise(0.0) for i, (_, w) in enumerate(lags)), F.lit(0.0))
    return wide.withColumn("base", F.when(low > 0, top / low)).drop(*(f"l{i}" for i in range(depth)))


def rolling_quantiles(summary: DataFrame, k: int = 7) -> DataFrame:
    """Position-wise mean of the percentile vectors of the ``k`` partitions before, as ``reference``."""
    before = _window().rowsBetween(-k, -1)
    vectors = F.collect_list("quantiles").over(before)
    mean = F.transform(F.sequence(F.lit(0), F.lit(98)), lambda i: F.aggregate("v", F.lit(0.0), lambda a, x: a + F.get(x, i)) / F.size("v"))
    rows = summary.filter(F.col("quantiles").isNotNull()).withColumns({"v": vectors, "nth": F.row_number().over(_window())})
    return rows.withColumn("reference", F.when(F.size("v") == k, mean)).drop("v", "nth")


def interval_frame(summary: DataFrame, stat: str, days: int = 7) -> DataFrame:
    """Mean over the partitions of the ``days`` days before, by date: days without a partition don't stretch the window."""
    w = Window.partitionBy("feature").orderBy(F.datediff("ds", F.lit("1970-01-01").cast("date"))).rangeBetween(-days, -1)
    return summary.withColumn("s", F.col(stat).cast("double")).withColumn("base", F.avg(F.col(stat).cast("double")).over(w))


def with_calendar(df: DataFrame, holidays: DataFrame | None = None) -> DataFrame:
    """Weekday (1: Monday), weekend and, from a small table of dates ``ds``, holiday."""
    out = df.withColumn("weekday", F.weekday("ds") + 1).withColumn("weekend", F.weekday("ds") >= 5)
    if holidays is None:
        return out.withColumn("holiday", F.lit(False))
    return out.join(F.broadcast(holidays.select("ds").distinct().withColumn("holiday", F.lit(True))), "ds", "left").withColumn("holiday", F.coalesce("holiday", F.lit(False)))
