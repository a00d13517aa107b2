"""Connected components of a graph given as an edge table, without gathering any component in one place."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored


def components(edges: DataFrame) -> DataFrame:
    """(id, component) for every id of ``edges`` (a, b: long): the smallest id reachable.

    Alternates two star contractions. Every node first hangs its larger neighbours on its smallest
    one, then its smaller neighbours, until each tree is a star. Only minima by node are
    aggregated, partly before the shuffle; a node of very many edges takes part in a join that
    adaptive execution can split. Rounds grow with the logarithm of the longest path.
    """
    now = stored(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct(), "edges")
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(low, "u").filter("v > u and v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        down = stored(large.unionByName(low.filter("m < u").select("u", F.col("m").alias("v"))), "edges")
        least = down.groupBy("u").agg(F.min("v").alias("m"))
        small = down.join(least, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        now = stored(small.unionByName(least.select("u", F.col("m").alias("v"))).distinct(), "edges")
        # stars: nobody has two parents, and no parent has one
        twice = now.groupBy("u").agg(F.count("*").alias("n")).filter("n > 1").select("u")
        if twice.unionByName(now.join(now.select(F.col("u").alias("v")), "v", "left_semi").select("u")).isEmpty():
            break
    return now.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(now.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())
