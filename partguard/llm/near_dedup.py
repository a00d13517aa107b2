"""Near-duplicate documents: minhash with tensored tables, every candidate link confirmed on the full shingle sets."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import load, slices, small_batches, stored, text_of
from .components import components

_GOLD = np.uint64(0x9E3779B97F4A7C15)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Shingler:
    """64-bit hashes of the distinct runs of ``size`` words, ascending; ASCII letters in lower case, words parted by ASCII white space."""

    def __init__(self, size: int, limit: int = 60_000):
        self.size, self.limit, self.known = size, limit, {}

    def of(self, text: str) -> np.ndarray:
        words = text.encode("utf-8", "surrogatepass").lower().split()
        if not words:
            return np.zeros(0, np.uint64)
        known = self.known
        try:
            h = np.array([known[w] for w in words], np.uint64)
        except KeyError:
            if len(known) > self.limit:
                known.clear()
            for w in words:
                if w not in known:
                    known[w] = xxhash.xxh3_64_intdigest(w)
            h = np.array([known[w] for w in words], np.uint64)
        size = min(self.size, len(h))  # fewer words: the whole sequence is the one shingle
        acc = np.full(len(h) - size + 1, size, np.uint64)
        for k in range(size):
            acc = _mix(acc * _GOLD + h[k : len(h) - size + 1 + k])
        return np.unique(acc)


class Tensor:
    """Keys of two small collections of minhash tuples; a table is a pair of them, one of each.

    ``first`` tuples of ``rows[0]`` minhashes and ``second`` tuples of ``rows[1]``: so many tables
    as their product from minhashes as their sum. Two sets of similarity s share no table with a
    probability of at most (1-s**rows[0])**first + (1-s**rows[1])**second; here 0.0005 at 0.8.
    """

    def __init__(self, first: int = 12, second: int = 8, rows: tuple[int, int] = (3, 2), seed: int = 11):
        self.first, self.second, self.rows = first, second, rows
        self.multipliers = np.random.default_rng(seed).integers(1, 1 << 63, first * rows[0] + second * rows[1], dtype=np.uint64) * np.uint64(2) + np.uint64(1)

    def of(self, shingles: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        low = np.full(len(self.multipliers), np.iinfo(np.uint64).max, np.uint64)
        for i in range(0, len(shingles), 4096):
            x = shingles[None, i : i + 4096] * self.multipliers[:, None]
            x ^= x >> np.uint64(32)
            x *= _GOLD
            np.minimum(low, x.min(1), out=low)
        cut = self.first * self.rows[0]
        return tuple(reduce(lambda acc, c: _mix(acc * _GOLD + c), part.reshape(n, -1).T, np.arange(n, dtype=np.uint64)).astype(np.int64) for part, n in ((low[:cut], self.first), (low[cut:], self.second)))


def shingled(docs: DataFrame, size: int, tensor: Tensor) -> DataFrame:
    """(doc_id, n_shingles, set_key, firsts, seconds) per document; the key is a 128-bit hash of the set, null for an empty one."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(size)
        for batch in slices(batches):
            n, keys, firsts, seconds = [], [], [], []
            for text in batch.column("text").to_pylist():
                s = shingler.of(text)
                n.append(len(s))
                a, b = tensor.of(s) if len(s) else (None, None)
                keys.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                firsts.append(a)
                seconds.append(b)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(keys, pa.binary()), pa.array(firsts, pa.list_(pa.int64())), pa.array(seconds, pa.list_(pa.int64()))], ["doc_id", "n_shingles", "set_key", "firsts", "seconds"])

    return docs.mapInArrow(make, "doc_id long, n_shingles long, set_key binary, firsts array<long>, seconds array<long>")


def shingle_sets(docs: DataFrame, size: int) -> DataFrame:
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(size)
        for batch in slices(batches):
            sets = [shingler.of(x).astype(np.int64) for x in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(sets, pa.list_(pa.int64()))], ["id", "shingles"])

    return docs.mapInArrow(make, "id long, shingles array<long>")


def confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Add ``linked`` to pairs (a, b): whether the full sets meet the similarity."""
    left = sets.select(F.col("id").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("id").alias("b"), F.col("shingles").alias("sb"))
    both = F.size(F.array_intersect("sa", "sb"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", (100 * both >= percent * (F.size("sa") + F.size("sb") - both)).alias("linked"))


def prefix_pairs(sets: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) of ``nodes`` (id, n, component) in different components that may meet the similarity: exact, none is missed.

    In one order of all shingles, rare ones first, two sets of the similarity share a shingle among
    the first n - ceil(percent * n / 100) + 1 of each; and what follows the first shingle that they
    share, in either, must be enough for the overlap they need. A text with so many shingles of its own that
    they fill its prefix drops out without a pair, and shingles of one component make none.
    """
    each = sets.join(nodes.select("id"), "id", "left_semi").select("id", F.explode("shingles").alias("shingle"))
    of = each.groupBy("shingle").agg(F.count("*").alias("df"))
    ranked = each.join(of, "shingle").withColumn("r", F.row_number().over(Window.partitionBy("id").orderBy("df", "shingle")))
    head = ranked.filter("df > 1").join(nodes, "id").filter(F.expr(f"r <= n - ceil({percent} * n / 100.0) + 1")).select("shingle", "id", "n", "component", "r")
    mixed = head.groupBy("shingle").agg(F.min("component").alias("low"), F.max("component").alias("high")).filter("low < high").select("shingle")
    head = stored(head.join(mixed, "shingle", "left_semi"), "prefixes")
    other = head.select("shingle", F.col("id").alias("b"), F.col("n").alias("m"), F.col("component").alias("other"), F.col("r").alias("q"))
    fits = f"100 * least(n, m) >= {percent} * greatest(n, m) AND 1 + least(n - r, m - q) >= ceil({percent} * (n + m) / {100.0 + percent})"
    return head.join(other, "shingle").filter(f"id < b AND component <> other AND {fits}").select(F.col("id").alias("a"), "b").distinct()


def links(docs: DataFrame, reps: DataFrame, size: int, percent: int) -> DataFrame:
    """Edges (a, b), of confirmed links, that join all representatives which any confirmed candidate pair would join.

    ``reps`` has (id, n, firsts, seconds), one row per distinct set. Each bucket of a table is a set
    of candidates. Twice each bucket picks one of its members as hub, first by a hash, then the one
    that was linked in most of its tests, the likeliest centre, and the others are checked against
    it: rows in proportion to the bucket, not to its square. Buckets whose members are all joined
    then drop out. What is left is compared by an exact prefix filter, so that no pair in a bucket is passed over.
    """
    spread = reps.select("id", "n", F.posexplode("firsts").alias("i", "x"), "seconds").select("id", "n", "i", "x", F.posexplode("seconds").alias("j", "y")).select("id", "n", F.xxhash64("i", "x", "j", "y").alias("key"))
    shared = spread.groupBy("key").agg(F.min("id").alias("low"), F.max("id").alias("high")).filter("low < high").select("key")
    members = stored(spread.join(shared, "key", "left_semi"), "buckets")
    sets = stored(shingle_sets(docs.join(members.select(F.col("id")).distinct(), F.col("doc_id") == F.col("id"), "left_semi").select(F.col("doc_id").alias("id"), "text"), size), "sets")
    near = f"100 * least(n, m) >= {percent} * greatest(n, m)"

    def against_hubs(rows: DataFrame, rate) -> DataFrame:
        rank = F.struct(-rate, F.xxhash64("id"), F.col("id"))
        hub = rows.groupBy("key").agg(F.min(F.struct(rank.alias("rank"), F.col("id").alias("hub"), F.col("n").alias("m"))).alias("h")).select("key", "h.hub", "h.m")
        return rows.join(hub, "key").filter(f"id <> hub AND {near}").select(F.least("id", "hub").alias("a"), F.greatest("id", "hub").alias("b")).distinct()

    first = stored(confirm(against_hubs(members, F.lit(0.0)), sets, percent), "links")
    rates = first.select(F.explode(F.array("a", "b")).alias("id"), F.col("linked").cast("int").alias("l")).groupBy("id").agg((F.sum("l") / (F.count("*") + 1)).alias("rate"))
    again = against_hubs(members.join(rates, "id", "left"), F.coalesce("rate", F.lit(0.0))).join(first.select("a", "b"), ["a", "b"], "left_anti")
    second = stored(confirm(again, sets, percent), "links")
    tested = first.unionByName(second)
    joined = components(tested.filter("linked").select("a", "b"))
    labelled = members.join(joined, "id", "left").select("id", "n", "key", F.coalesce("component", "id").alias("component"))
    open_keys = labelled.groupBy("key").agg(F.min("component").alias("low"), F.max("component").alias("high")).filter("low < high").select("key")
    nodes = stored(labelled.join(open_keys, "key", "left_semi").select("id", "n", "component").distinct(), "open")
    rest = confirm(prefix_pairs(sets, nodes, percent).join(tested.select("a", "b"), ["a", "b"], "left_anti"), sets, percent)
    return joined.select(F.col("id").alias("a"), F.col("component").alias("b")).unionByName(rest.filter("linked").select("a", "b"))


def near_duplicates(docs: DataFrame, shingle: int = 5, percent: int = 80, tensor: Tensor | None = None, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (the smallest id reachable over links) and kept (it is that id).

    Documents with one set are one node from the start, so copies cost a row each. Null and empty
    texts have no shingle and link with nothing, nor do rows without id, whose component is null and which are kept.
    Rows that share an id are one document if they link, and each keeps its row.
    """
    small_batches(docs.sparkSession)
    source = docs.select(F.col(id_column).cast("long").alias("doc_id"), text_of(text_column).alias("text"))
    base = stored(shingled(source, shingle, tensor or Tensor()), "minhash")
    nodes = base.filter("doc_id is not null and set_key is not null")
    low = nodes.groupBy("set_key").agg(F.min("doc_id").alias("id"))
    reps = nodes.join(low.select(F.col("id").alias("doc_id"), "set_key"), ["doc_id", "set_key"], "left_semi").dropDuplicates(["doc_id", "set_key"]).select(F.col("doc_id").alias("id"), F.col("n_shingles").alias("n"), "firsts", "seconds")
    joined = components(links(source, reps, shingle, percent))
    of_set = low.join(joined, "id", "left").select("set_key", F.coalesce("component", "id").alias("of_set"))
    return base.join(of_set, "set_key", "left").select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("of_set", "doc_id")).alias("component_id")).withColumn("kept", F.coalesce(F.col("component_id") == F.col("doc_id"), F.lit(True)))


def op7_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(load(spark, sf_dir, "documents"), shingle=2)
