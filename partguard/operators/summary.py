"""Partition summaries: one row for each partition and feature, exact or sketched, merged and updated."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.stats import PERCENT_SQL, percentiles, pooled, w1
from ..plans.planner import chunks, mode
from ..sources.features import Feature

SCALARS = ("completeness", "mean", "stddev", "min", "max", "n_distinct", "top_freq")
FREQUENT_SHARE = 0.01


def long_form(rows: DataFrame, features: list[Feature], ds: str = "ds") -> DataFrame:
    """(ds, feature, kind, num, txt): a row for each value; NaN is no value. One scan, one generator."""
    def value(f: Feature) -> Column:
        x = F.expr(f.expr)
        num = F.lit(None).cast("double") if f.kind == "C" else F.nanvl(x.cast("double"), F.lit(None).cast("double"))
        return F.struct(F.lit(f.name).alias("feature"), F.lit(f.kind).alias("kind"), num.alias("num"), (x.cast("string") if f.kind == "C" else F.lit(None).cast("string")).alias("txt"))

    return rows.select(F.col(ds).alias("ds"), F.inline(F.array(*map(value, features))))


def summarize(rows: DataFrame, features: list[Feature], ds: str = "ds", quantiles: bool = True, share: float = FREQUENT_SHARE) -> DataFrame:
    """Exact summaries through value frequencies.

    Values are counted by (partition, feature, value) first, which combines before the shuffle and
    has no key that holds more than one state per value; distinct and top counts, moments and percentiles then
    come from the frequencies in one more aggregation. Spark's own count(distinct) would copy every row once for each feature.
    """
    counts = long_form(rows, features, ds).groupBy("ds", "feature", "kind", "num", "txt").agg(F.count("*").alias("n"))
    valid = F.when(F.col("num").isNotNull() | F.col("txt").isNotNull(), F.col("n"))
    first = counts.groupBy("ds", "feature", "kind").agg(
        F.sum("n").alias("n_rows"), F.coalesce(F.sum(valid), F.lit(0)).alias("n_valid"), F.sum(F.col("num") * F.col("n")).alias("total"),
        F.min("num").alias("min"), F.max("num").alias("max"), F.count(valid).alias("n_distinct"), F.coalesce(F.max(valid), F.lit(0)).alias("top_count"),
        *([percentiles("num", "n").alias("quantiles")] if quantiles else []),
    )
    centre = first.select("ds", "feature", F.try_divide("total", F.col("n_valid")).alias("mean"), "n_rows", "n_valid")
    second = counts.join(centre.select("ds", "feature", F.col("mean").alias("c"), F.col("n_rows").alias("r")), ["ds", "feature"]).groupBy("ds", "feature").agg(
        F.sum(F.col("n") * (F.col("num") - F.col("c")) * (F.col("num") - F.col("c"))).alias("m2"),
        F.sum(F.when(valid.isNotNull() & (F.col("n") >= share * F.col("r")), 1).otherwise(0)).alias("n_frequent"),
    )
    out = first.join(second, ["ds", "feature"]).withColumns({
        "completeness": F.col("n_valid") / F.col("n_rows"),
        "mean": F.when(F.col("kind") != "C", F.try_divide("total", F.col("n_valid"))),
        "stddev": F.when((F.col("kind") != "C") & (F.col("n_valid") > 1), F.sqrt(F.greatest(F.col("m2"), F.lit(0.0)) / (F.col("n_valid") - 1))),
        "top_freq": F.col("top_count") / F.col("n_rows"),
    }).drop("total")
    if not quantiles:
        return out
    prev = F.lag("quantiles").over(Window.partitionBy("feature").orderBy("ds"))
    return out.withColumn("w1_prev", w1(F.col("quantiles"), prev))


def summarize_wide(rows: DataFrame, features: list[Feature], ds: str = "ds", approximate: bool = False, width: int = 100) -> DataFrame:
    """Scalar summaries with one aggregate per feature and statistic, ``width`` features per plan, without a generator.

    Distinct counts are sketched, or exact from the distinct values of ``long_form`` in a second scan: several count(distinct) in one
    plan would copy every row for each of them before the first aggregation."""
    parts = []
    for chunk in chunks(features, width):
        aggs = [F.count("*").alias("n_rows")]
        for f in chunk:
            x = F.expr(f.expr)
            num = F.lit(None).cast("double") if f.kind == "C" else x.cast("double")
            sketched = [F.approx_count_distinct(x, 0.02).alias("n_distinct")] if approximate else []
            aggs.append(F.struct(F.lit(f.name).alias("feature"), F.count(x).alias("n_valid"), F.avg(num).alias("mean"), F.stddev_samp(num).alias("stddev"), F.min(num).alias("min"), F.max(num).alias("max"), *sketched).alias(f.name))
        wide = rows.groupBy(F.col(ds).alias("ds")).agg(*aggs)
        cells = [F.col(f"`{f.name}`") for f in chunk]
        parts.append(wide.select("ds", "n_rows", F.inline(F.array(*cells))))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    if not approximate:
        valid = F.when(F.col("num").isNotNull() | F.col("txt").isNotNull(), 1)
        values = long_form(rows, features, ds).select("ds", "feature", "num", "txt").distinct()
        out = out.join(values.groupBy("ds", "feature").agg(F.count(valid).alias("n_distinct")), ["ds", "feature"])
    return out.withColumn("completeness", F.col("n_valid") / F.col("n_rows"))


def summarize_sketch(rows: DataFrame, features: list[Feature], ds: str = "ds", lg_k: int = 12) -> DataFrame:
    """Mergeable summaries of bounded size: counts, moments, extremes, an HLL sketch of the values, a KLL sketch of the numbers and a top-item sketch. One scan, states of fixed size combined before the shuffle."""
    long = long_form(rows, features, ds).withColumn("key", F.coalesce("txt", F.col("num").cast("string")))
    return long.groupBy("ds", "feature", "kind").agg(
        F.count("*").alias("n_rows"), F.count("key").alias("n_valid"), F.avg("num").alias("mean"), (F.var_pop("num") * F.count("num")).alias("m2"), F.min("num").alias("min"), F.max("num").alias("max"),
        F.hll_sketch_agg("key", lg_k).alias("hll"), F.expr("kll_sketch_agg_double(num)").alias("kll"), F.expr("approx_top_k_accumulate(key, 1000)").alias("items"),
    )


def merge_sketches(summaries: DataFrame, ds: Column) -> DataFrame:
    """Summaries of unions (hours to days, shards to a day) from those of their parts; no row of the data is read again."""
    n, mean, m2 = pooled(F.col("n_num"), F.coalesce("mean", F.lit(0.0)), F.coalesce("m2", F.lit(0.0)))
    parts = summaries.withColumn("n_num", F.when(F.col("kind") == "C", F.lit(0)).otherwise(F.col("n_valid")))
    return parts.groupBy(ds.alias("ds"), "feature", "kind").agg(
        F.sum("n_rows").alias("n_rows"), F.sum("n_valid").alias("n_valid"), mean.alias("mean"), m2.alias("m2"), F.min("min").alias("min"), F.max("max").alias("max"),
        F.hll_union_agg("hll").alias("hll"), F.expr("kll_merge_agg_double(kll)").alias("kll"), F.expr("approx_top_k_combine(items)").alias("items"),
    )


def read_sketches(summaries: DataFrame) -> DataFrame:
    """The statistics that sketches hold: estimated distinct count, percentiles and top item's share, with exact completeness and moments.

    Of very many values without a frequent one, the top-item sketch names none, as all counts lie within its error (some 0.3 % of the rows);
    the mean count of a value, the least that the top one can have, then stands for the top count."""
    top = F.expr("get(filter(approx_top_k_estimate(items, 2), e -> e.item IS NOT NULL), 0).count")
    least = F.try_divide("n_valid", F.hll_sketch_estimate("hll"))
    return summaries.select(
        "ds", "feature", "kind", "n_rows", "n_valid", (F.col("n_valid") / F.col("n_rows")).alias("completeness"), "mean", F.when((F.col("kind") != "C") & (F.col("n_valid") > 1), F.sqrt(F.greatest("m2", F.lit(0.0)) / (F.col("n_valid") - 1))).alias("stddev"), "min", "max",
        F.hll_sketch_estimate("hll").alias("n_distinct"), (F.coalesce(top, least, F.lit(0)) / F.col("n_rows")).alias("top_freq"), F.when(F.col("min").isNotNull(), F.expr(f"kll_sketch_get_quantile_double(kll, {PERCENT_SQL})")).alias("quantiles"),
    )


def summarize_map(rows: DataFrame, map_column: str, ds: str = "ds") -> DataFrame:
    """Scalar summaries of a map of named numbers; a key that a row lacks counts as missing: the partition's rows are the denominator, and every key has a row in every partition."""
    sizes = rows.groupBy(F.col(ds).alias("ds")).agg(F.count("*").alias("n_rows"))
    cells = rows.select(F.col(ds).alias("ds"), F.explode(map_column).alias("feature", "num")).groupBy("ds", "feature").agg(F.count("num").alias("n_valid"), F.avg("num").alias("mean"), F.min("num").alias("min"), F.max("num").alias("max"))
    grid = sizes.crossJoin(F.broadcast(cells.select("feature").distinct()))  # partitions by features: two small sets
    return grid.join(cells, ["ds", "feature"], "left").withColumn("n_valid", F.coalesce("n_valid", F.lit(0))).withColumn("completeness", F.col("n_valid") / F.col("n_rows"))


def summarize_array(rows: DataFrame, array_column: str, ds: str = "ds") -> DataFrame:
    """Scalar summaries by position of an array, and of its norm."""
    x = F.col(array_column)
    norm = F.sqrt(F.aggregate(x, F.lit(0.0), lambda s, v: s + v.cast("double") * v.cast("double")))
    cells = rows.select(F.col(ds).alias("ds"), F.posexplode(x).alias("p", "num")).select("ds", F.format_string("dim_%02d", "p").alias("feature"), F.col("num").cast("double").alias("num"))
    every = cells.unionByName(rows.select(F.col(ds).alias("ds"), F.lit("norm").alias("feature"), norm.alias("num")))
    return every.groupBy("ds", "feature").agg(F.count("num").alias("n_valid"), F.avg("num").alias("mean"), F.stddev_samp("num").alias("stddev"), F.min("num").alias("min"), F.max("num").alias("max"))


def summarize_planned(rows: DataFrame, features: list[Feature], ds: str = "ds", needs_quantiles: bool = True) -> DataFrame:
    """Summaries in the form that ``planner.mode`` picks for the number of features and the rows of the largest partition, counted from the partition column alone."""
    largest = rows.groupBy(F.col(ds).alias("ds")).count().agg(F.coalesce(F.max("count"), F.lit(0))).first()[0]
    how = mode(len(features), largest, needs_quantiles)
    if how == "sketch":
        return read_sketches(summarize_sketch(rows, features, ds))
    return summarize(rows, features, ds, needs_quantiles) if how == "long" else summarize_wide(rows, features, ds)
