"""Choices made while a plan is built: which statistics are needed, how wide a plan may be, exact or sketched."""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Sequence

#: What each method reads of a summary.
NEEDS = {
    "completeness_drop": {"completeness"},
    "zscore": {"completeness"},
    "two_sample": {"quantiles"},
    "knn": {"completeness", "n_distinct", "top_freq", "max", "mean", "min", "stddev"},
    "clustered": {"completeness", "mean", "stddev", "n_distinct", "top_freq", "w1_prev"},
    "general": {"completeness", "mean", "stddev", "n_distinct", "top_freq"},
}


def required_stats(methods: Iterable[str]) -> set[str]:
    """Union of the statistics that the methods read; gaps between percentile vectors need the vectors."""
    out: set[str] = set().union(*(NEEDS[m] for m in methods))
    return out | {"quantiles"} if "w1_prev" in out else out


def chunks(items: Sequence, width: int) -> Iterator[Sequence]:
    for i in range(0, len(items), width):
        yield items[i : i + width]


def mode(n_features: int, rows_per_partition: int, needs_quantiles: bool) -> str:
    """wide: an aggregate for each feature, up to 200; chunked: such plans of 100 features, up to 2,000; long: a row for each value.
    Sketches where a partition's values of a feature would not fit a task's memory: beyond ten million rows."""
    if rows_per_partition > 10_000_000:
        return "sketch"
    if needs_quantiles or n_features > 2_000:
        return "long"
    return "wide" if n_features <= 200 else "chunked"
