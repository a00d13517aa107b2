"""Statistics as columns: percentile lists, pooled moments, distances of percentile vectors."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The 99 percentages, as literals: Spark's percentile takes no computed ones.
PERCENTS = [i / 100 for i in range(1, 100)]
PERCENT_SQL = "array(" + ", ".join(f"{p}D" for p in PERCENTS) + ")"
DUCK_PERCENTS = "[" + ", ".join(map(str, PERCENTS)) + "]"


def percentiles(value: str, weight: str | None = None) -> Column:
    """99 percentiles by linear interpolation, of values or of values with multiplicities."""
    return F.expr(f"percentile({value}, {PERCENT_SQL}{', ' + weight if weight else ''})")


def pooled(n: Column, mean: Column, m2: Column) -> tuple[Column, Column, Column]:
    """Count, mean and sum of squared deviations of a union, from those of its parts: aggregate columns."""
    total = F.sum(n)
    centre = F.try_divide(F.sum(n * mean), total)
    return total, centre, F.sum(m2) + F.sum(n * mean * mean) - total * centre * centre


def w1(a: Column, b: Column, mean: bool = False) -> Column:
    """Sum (or mean) of absolute gaps of two percentile vectors."""
    total = F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x - y)), F.lit(0.0), lambda s, x: s + x)
    return total / F.size(a) if mean else total


def ks(a: Column, b: Column) -> Column:
    """Largest absolute gap of two percentile vectors, on the quantile axis."""
    return F.array_max(F.zip_with(a, b, lambda x, y: F.abs(x - y)))


def ks_probability(a: Column, b: Column) -> Column:
    """Largest gap of the two step functions: at each value of either, the share of entries at or below it."""
    share = lambda v, x: F.size(F.filter(v, lambda y: y <= x)) / F.size(v)
    return F.array_max(F.transform(F.concat(a, b), lambda x: F.abs(share(a, x) - share(b, x))))


def spread_term(a: Column, b: Column, scale: bool = True) -> Column:
    """Population variance of both vectors together, scaled jointly to [0, 1] unless ``scale`` is off."""
    both = F.concat(a, b)
    low, high = F.array_min(both), F.array_max(both)
    n = F.size(both).cast("double")
    mean = F.aggregate(both, F.lit(0.0), lambda s, x: s + x) / n
    square = F.aggregate(both, F.lit(0.0), lambda s, x: s + (x - mean) * (x - mean)) / n
    return F.try_divide(square, (high - low) * (high - low)) if scale else square


def dts(a: Column, b: Column, scale: bool = True) -> Column:
    """Gap sum over D(1-D), D the spread term; on vectors scaled jointly to [0, 1] by default; 0 where nothing varies."""
    d = spread_term(a, b, scale)
    both = F.concat(a, b)
    gap = F.try_divide(w1(a, b), F.array_max(both) - F.array_min(both)) if scale else w1(a, b)
    return F.coalesce(F.try_divide(gap, d * (1 - d)), F.lit(0.0))


DISTANCES = {"ks": ks, "w1": w1, "dts": dts, "ks_probability": ks_probability}


def histogram_bin(value: Column, low: float, high: float, bins: int) -> Column:
    """Number of the fixed bin, 0 below and bins + 1 from ``high`` on."""
    return F.when(value < low, 0).when(value >= high, bins + 1).otherwise(F.floor((value - low) / ((high - low) / bins)) + 1)
