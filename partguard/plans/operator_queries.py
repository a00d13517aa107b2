"""One query for each kind of operator that users of the methods combine with them, in DataFrame form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import udfs
from ..functions.stats import DISTANCES
from ..methods import clustered as cd
from ..methods import labels as lb
from ..operators.store import add_states, history, merged_states, summary_of, update, upsert
from ..operators.summary import merge_sketches, read_sketches, summarize_sketch
from ..sources import faults as ft
from ..sources.features import EVENTS, EVENTS_HIGH, Dataset
from ..sources.tables import load, read_export, scratch, views, write_export
from ..streaming import stream as st
from .catalog import _D as CLUSTERED_SQL
from .catalog import _groups as given_groups
from .catalog import CLEAN, LOW, add, clean, low
from . import oracles as o

# Joins --------------------------------------------------------------------------------------------

_DL = lambda how: lambda spark, d: load(spark, d, "documents").join(load(spark, d, "labels"), "doc_id", how)
for _how in ("inner", "left", "right", "full"):
    add(f"join_{_how}", "lang n:l labelled:l", lambda spark, d, h=_how: _DL(h)(spark, d).groupBy("lang").agg(F.count("*").alias("n"), F.count("quality").alias("labelled")), [f"r AS (SELECT lang, count(*) AS n, count(quality) AS labelled FROM documents {_how} JOIN labels USING (doc_id) GROUP BY lang)"])
for _how, _sql in (("left_semi", "IN"), ("left_anti", "NOT IN")):
    add(f"join_{_how}", "lang n:l", lambda spark, d, h=_how: _DL(h)(spark, d).groupBy("lang").agg(F.count("*").alias("n")), [f"r AS (SELECT lang, count(*) AS n FROM documents WHERE doc_id {_sql} (SELECT doc_id FROM labels) GROUP BY lang)"])
for _hint in ("broadcast", "merge", "shuffle_hash"):
    add(f"join_hint_{_hint}", "n_name n:l", lambda spark, d, h=_hint: load(spark, d, "customer").join(load(spark, d, "nation").hint(h), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")), ["r AS (SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name)"])
add("join_range_horizon", "ds:s feature base:6", lambda spark, d: _range_base(spark, d), [*o.summary(LOW), *o.changes("completeness")], "c")


def _range_base(spark: SparkSession, d: str) -> DataFrame:
    """The rolling base by a band join instead of a window: a cross-check of both."""
    s = low(spark, d).select("ds", "feature", "completeness", F.dense_rank().over(Window.partitionBy("feature").orderBy("ds")).alias("t"))
    past = s.select("feature", F.col("completeness").alias("c"), F.col("t").alias("u"))
    base = s.join(past, "feature", "left").filter("u IS NULL OR (u < t AND u >= t - 7) OR t = 1").groupBy("ds", "feature", "t").agg(F.avg(F.when((F.col("u") < F.col("t")), F.col("c"))).alias("b"))
    return base.select("ds", "feature", F.when(F.col("t") > 7, F.col("b")).alias("base"))


add("join_cross_grid", "ds:s feature present", lambda spark, d: clean(spark, d).select("ds").distinct().crossJoin(F.broadcast(clean(spark, d).select("feature").distinct())).join(low(spark, d).filter("n_valid > 0").select("ds", "feature", F.lit(True).alias("p")), ["ds", "feature"], "left").withColumn("present", F.coalesce("p", F.lit(False))),
    [*o.summary(LOW), "r AS (SELECT d.ds, f.feature, coalesce(s.n_valid > 0, FALSE) AS present FROM (SELECT DISTINCT ds FROM s) d CROSS JOIN (SELECT DISTINCT feature FROM s) f LEFT JOIN s ON s.ds = d.ds AND s.feature = f.feature)"])


def _asof(spark: SparkSession, d: str) -> DataFrame:
    """Latest order of each customer at or before an order date that is a quarter's first day: union and last non-null over a window."""
    orders = load(spark, d, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").cast("date").alias("at"), F.col("o_totalprice").alias("v"))
    last = orders.groupBy("k", "at").agg(F.max("v").alias("v"))
    probes = orders.select("k").distinct().select("k", F.lit("1998-01-01").cast("date").alias("at"))
    both = last.select("k", "at", "v", F.lit(0).alias("probe")).unionByName(probes.select("k", "at", F.lit(None).cast("double").alias("v"), F.lit(1).alias("probe")))
    w = Window.partitionBy("k").orderBy("at", "probe").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("seen", F.last("v", ignorenulls=True).over(w)).filter("probe = 1").select("k", F.col("seen").alias("price"))


add("asof_latest_order", "k:l price:2", _asof, ["r AS (SELECT k, (SELECT max(o_totalprice) FROM orders o WHERE o_custkey = k AND o_orderdate = (SELECT max(o_orderdate) FROM orders p WHERE p.o_custkey = k AND p.o_orderdate <= TIMESTAMP '1998-01-01')) AS price FROM (SELECT DISTINCT o_custkey AS k FROM orders))"])
add("join_lateral", "ds:s feature rank:l value:3", lambda spark, d: _lateral(spark, d), [*o.summary(CLEAN), "r AS (SELECT ds, feature, i AS rank, quantiles[i] AS value FROM s, (SELECT unnest([25, 50, 75]) AS i) WHERE kind = 'N')"])


def _lateral(spark: SparkSession, d: str) -> DataFrame:
    s = clean(spark, d).filter("kind = 'N'").select("ds", "feature", "quantiles")
    s.createOrReplaceTempView("partition_summaries")
    return spark.sql("SELECT ds, feature, rank, element_at(quantiles, rank) AS value FROM partition_summaries, LATERAL (SELECT explode(array(25, 50, 75)) AS rank)")


# Aggregations, grouping sets, windows ----------------------------------------------------------------

add("agg_moments", "l_returnflag n:l mean:4 sd:4 var_pop:4 skew:4 low:2 high:2 med:3 r:5 cov:3", lambda spark, d: load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.avg("l_quantity").alias("mean"), F.stddev("l_quantity").alias("sd"), F.var_pop("l_quantity").alias("var_pop"), F.skewness("l_extendedprice").alias("skew"), F.min("l_quantity").alias("low"), F.max("l_quantity").alias("high"), F.median("l_extendedprice").alias("med"), F.corr("l_quantity", "l_extendedprice").alias("r"), F.covar_samp("l_quantity", "l_discount").alias("cov")),
    ["m AS (SELECT l_returnflag AS f, avg(l_extendedprice) AS mu, stddev_pop(l_extendedprice) AS sp FROM lineitem GROUP BY 1)", "r AS (SELECT l_returnflag, count(*) AS n, avg(l_quantity) AS mean, stddev_samp(l_quantity) AS sd, var_pop(l_quantity) AS var_pop, avg(pow((l_extendedprice - mu) / sp, 3)) AS skew, min(l_quantity) AS low, max(l_quantity) AS high, median(l_extendedprice) AS med, corr(l_quantity, l_extendedprice) AS r, covar_samp(l_quantity, l_discount) AS cov FROM lineitem JOIN m ON f = l_returnflag GROUP BY l_returnflag)"])
add("agg_filtered", "event_type n:l big:l users:l top:2 bottom:l", lambda spark, d: load(spark, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.count_if(F.col("value") > 50).alias("big"), F.count_distinct("user_id").alias("users"), F.max("value").alias("top"), F.min("event_id").alias("bottom")), ["r AS (SELECT event_type, count(*) AS n, count(*) FILTER (value > 50) AS big, count(DISTINCT user_id) AS users, max(value) AS top, min(event_id) AS bottom FROM events GROUP BY event_type)"])
add("agg_extremes", "event_type first_id:l all_pos some_big", lambda spark, d: load(spark, d, "events").groupBy("event_type").agg(F.min_by("event_id", F.struct("value", "event_id")).alias("first_id"), F.bool_and(F.col("value") > 0).alias("all_pos"), F.bool_or(F.col("value") > 500).alias("some_big")), ["r AS (SELECT event_type, arg_min(event_id, (value, event_id)) AS first_id, bool_and(value > 0) AS all_pos, bool_or(value > 500) AS some_big FROM events GROUP BY event_type)"])
add("grouping_rollup", "event_type day:s n:l level:l", lambda spark, d: load(spark, d, "events").withColumn("day", F.col("ts").cast("date")).rollup("event_type", "day").agg(F.count("*").alias("n"), F.grouping_id().alias("level")), ["r AS (SELECT event_type, CAST(ts AS DATE) AS day, count(*) AS n, grouping(event_type, CAST(ts AS DATE)) AS level FROM events GROUP BY ROLLUP (event_type, CAST(ts AS DATE)))"])
add("grouping_cube", "event_type weekday:l n:l", lambda spark, d: load(spark, d, "events").withColumn("weekday", F.weekday("ts") + 1).cube("event_type", "weekday").agg(F.count("*").alias("n")), ["r AS (SELECT event_type, isodow(ts) AS weekday, count(*) AS n FROM events GROUP BY CUBE (event_type, isodow(ts)))"])
add("grouping_sets", "l_returnflag l_linestatus n:l", lambda spark, d: (views(spark, d, "lineitem"), spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())"))[1], ["r AS (SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ()))"])
_W = "PARTITION BY event_type ORDER BY value DESC, event_id"
_win = lambda: Window.partitionBy("event_type").orderBy(F.desc("value"), "event_id")
add("window_ranks", "event_id:l rn:l rk:l dr:l pr:6 cd:6 nt:l", lambda spark, d: load(spark, d, "events").select("event_id", F.row_number().over(_win()).alias("rn"), F.rank().over(_win()).alias("rk"), F.dense_rank().over(_win()).alias("dr"), F.percent_rank().over(_win()).alias("pr"), F.cume_dist().over(_win()).alias("cd"), F.ntile(10).over(_win()).alias("nt")), [f"r AS (SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd, ntile(10) OVER w AS nt FROM events WINDOW w AS ({_W}))"])
add("window_offsets", "event_id:l before:2 after:2 top:2 third:2", lambda spark, d: load(spark, d, "events").select("event_id", F.lag("value").over(_win()).alias("before"), F.lead("value", 2).over(_win()).alias("after"), F.first("value").over(_win()).alias("top"), F.nth_value("value", 3).over(_win()).alias("third")), [f"r AS (SELECT event_id, lag(value) OVER w AS before, lead(value, 2) OVER w AS after, first_value(value) OVER w AS top, nth_value(value, 3) OVER w AS third FROM events WINDOW w AS ({_W}))"])
add("window_frames", "event_id:l s3:3 run:2", lambda spark, d: load(spark, d, "events").select("event_id", F.avg("value").over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(-2, 0)).alias("s3"), F.sum("value").over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)).alias("run")), ["r AS (SELECT event_id, avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS s3, sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS run FROM events)"])
add("topk_global", "event_id:l value:2", lambda spark, d: load(spark, d, "events").select("event_id", "value").orderBy(F.desc("value"), "event_id").limit(20), ["r AS (SELECT event_id, value FROM events ORDER BY value DESC, event_id LIMIT 20)"])
add("topk_per_group", "event_type event_id:l value:2", lambda spark, d: load(spark, d, "events").withColumn("rn", F.row_number().over(_win())).filter("rn <= 5"), [f"r AS (SELECT * FROM (SELECT *, row_number() OVER ({_W}) AS rn FROM events) WHERE rn <= 5)"])
add("limit_offset", "event_id:l", lambda spark, d: load(spark, d, "events").select("event_id").orderBy("event_id").offset(10).limit(5), ["r AS (SELECT event_id FROM events ORDER BY event_id LIMIT 5 OFFSET 10)"])
add("approx_distinct_quantile", "close_distinct close_median", lambda spark, d: load(spark, d, "events").agg((F.abs(F.approx_count_distinct("user_id", 0.02) - F.count_distinct("user_id")) <= 0.1 * F.count_distinct("user_id")).alias("close_distinct"), (F.abs(F.percentile_approx("value", 0.5, 10000) - F.median("value")) <= 1).alias("close_median")), ["r AS (SELECT TRUE AS close_distinct, TRUE AS close_median)"])
add("sample_deterministic", "event_id:l", lambda spark, d: load(spark, d, "events").filter(F.md5(F.col("event_id").cast("string").cast("binary")).startswith("3")).select("event_id"), ["r AS (SELECT event_id FROM events WHERE md5(CAST(event_id AS VARCHAR)) LIKE '3%')"])

# Sets, shapes ------------------------------------------------------------------------------------------

SHARED_SETS = tuple(sorted(f.name for f in x) for x in (EVENTS, EVENTS_HIGH))


def _sets(spark: SparkSession, how: str) -> DataFrame:
    a, b = (spark.createDataFrame([(n,) for n in x], "feature string") for x in SHARED_SETS)
    return {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.exceptAll(b), "unionall": a.unionByName(b)}[how].groupBy("feature").agg(F.count("*").alias("n"))


for _op, _sql in (("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT ALL"), ("unionall", "UNION ALL")):
    add(f"setops_{_op}", "feature n:l", lambda spark, d, h=_op: _sets(spark, h), ["a(feature) AS (VALUES " + ", ".join(f"('{n}')" for n in SHARED_SETS[0]) + ")", "b(feature) AS (VALUES " + ", ".join(f"('{n}')" for n in SHARED_SETS[1]) + ")", f"r AS (SELECT feature, count(*) AS n FROM (SELECT feature FROM a {_sql} SELECT feature FROM b) GROUP BY feature)"])
add("dedup_copies", "texts:l copies:l", lambda spark, d: load(spark, d, "documents").agg(F.count_distinct("text").alias("texts"), (F.count("*") - F.count_distinct("text")).alias("copies")), ["r AS (SELECT count(DISTINCT text) AS texts, count(*) - count(DISTINCT text) AS copies FROM documents)"])
add("shape_unpivot", "event_id:l name value:3", lambda spark, d: load(spark, d, "events").select("event_id", F.col("value").alias("v"), F.col("user_id").cast("double").alias("u")).unpivot("event_id", ["v", "u"], "name", "value"), ["r AS (SELECT event_id, 'v' AS name, value FROM events UNION ALL SELECT event_id, 'u', user_id FROM events)"])
_TY = ("click", "error", "purchase", "signup", "view")
add("shape_pivot", "day:s " + " ".join(f"{x}:l" for x in _TY), lambda spark, d: load(spark, d, "events").withColumn("day", F.col("ts").cast("date")).groupBy("day").pivot("event_type", list(_TY)).count().fillna(0), ["r AS (SELECT CAST(ts AS DATE) AS day, " + ", ".join(f"count(*) FILTER (event_type = '{x}') AS {x}" for x in _TY) + " FROM events GROUP BY 1)"])
add("predicates", "event_id:l", lambda spark, d: load(spark, d, "events").filter("event_type IN ('click', 'view') AND value BETWEEN 10 AND 20 AND props LIKE '%1%' AND NOT (user_id <=> NULL) AND props RLIKE '[0-9]{2}' AND nullif(user_id, 7) IS NOT NULL").select("event_id"), ["r AS (SELECT event_id FROM events WHERE event_type IN ('click', 'view') AND value BETWEEN 10 AND 20 AND props LIKE '%1%' AND user_id IS NOT NULL AND regexp_matches(props, '[0-9]{2}') AND nullif(user_id, 7) IS NOT NULL)"])

# Functions ------------------------------------------------------------------------------------------------

add("string_functions", "doc_id:l n:l words:l up:l first_word tail digest:s near:l", lambda spark, d: load(spark, d, "documents").select("doc_id", F.length("text").alias("n"), (F.length("text") - F.length(F.replace("text", F.lit(" "), F.lit(""))) + 1).alias("words"), F.regexp_count("text", F.lit("[A-Z]")).alias("up"), F.regexp_extract("text", r"^(\S+)", 1).alias("first_word"), F.expr("right(text, 5)").alias("tail"), F.md5(F.col("text").cast("binary")).alias("digest"), F.levenshtein("lang", "source").alias("near")),
    [r"r AS (SELECT doc_id, length(text) AS n, length(text) - length(replace(text, ' ', '')) + 1 AS words, len(regexp_extract_all(text, '[A-Z]')) AS up, regexp_extract(text, '^(\S+)', 1) AS first_word, right(text, 5) AS tail, md5(text) AS digest, levenshtein(lang, source) AS near FROM documents)"])
add("date_functions", "o_orderkey:l month:s quarter:l dow:l later:s days:l", lambda spark, d: load(spark, d, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("date").alias("month"), F.quarter("o_orderdate").alias("quarter"), (F.weekday("o_orderdate") + 1).alias("dow"), F.add_months(F.col("o_orderdate").cast("date"), 1).alias("later"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("days")), ["r AS (SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, quarter(o_orderdate) AS quarter, isodow(o_orderdate) AS dow, CAST(CAST(o_orderdate AS DATE) + INTERVAL 1 MONTH AS DATE) AS later, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders)"])
add("date_gap_fill", "day:s n:l", lambda spark, d: spark.sql("SELECT explode(sequence(DATE '2024-01-01', DATE '2024-02-05', INTERVAL 1 DAY)) AS day").join(load(spark, d, "events").groupBy(F.col("ts").cast("date").alias("day")).agg(F.count("*").alias("c")), "day", "left").select("day", F.coalesce("c", F.lit(0)).alias("n")), ["g AS (SELECT CAST(unnest(generate_series(DATE '2024-01-01', DATE '2024-02-05', INTERVAL 1 DAY)) AS DATE) AS day)", "e AS (SELECT CAST(ts AS DATE) AS day, count(*) AS c FROM events GROUP BY 1)", "r AS (SELECT g.day, coalesce(c, 0) AS n FROM g LEFT JOIN e USING (day))"])
add("math_functions", "event_id:l a:5 b:5 c:5 g:l", lambda spark, d: load(spark, d, "events").select("event_id", F.ln(1 + F.col("value")).alias("a"), F.sqrt("value").alias("b"), F.try_divide("value", F.col("user_id") % 3).alias("c"), F.greatest(F.floor("value"), F.col("user_id")).alias("g")), ["r AS (SELECT event_id, ln(1 + value) AS a, sqrt(value) AS b, value / nullif(user_id % 3, 0) AS c, greatest(floor(value), user_id) AS g FROM events)"])
add("array_functions", "vec_id:l total:3 top:5 pos:l first3:4", lambda spark, d: load(spark, d, "embeddings").select("vec_id", F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double")).alias("total"), F.array_max("embedding").alias("top"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.aggregate(F.slice("embedding", 1, 3), F.lit(0.0), lambda a, x: a + x.cast("double")).alias("first3")), ["r AS (SELECT vec_id, list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE))) AS total, list_max(embedding) AS top, len(list_filter(embedding, lambda x: x > 0)) AS pos, list_sum(list_transform(embedding[1:3], lambda x: CAST(x AS DOUBLE))) AS first3 FROM embeddings)"])
add("json_functions", "event_id:l k:l twice:l has_k", lambda spark, d: load(spark, d, "events").withColumn("j", F.from_json("props", "MAP<STRING, BIGINT>")).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.transform_values("j", lambda _, v: v * 2)["k"].alias("twice"), F.map_contains_key("j", "k").alias("has_k")), ["r AS (SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) * 2 AS twice, json_exists(props, '$.k') AS has_k FROM events)"])
add("map_functions", "event_type keys:l v:3", lambda spark, d: load(spark, d, "events").groupBy("event_type").agg(F.avg("value").alias("m"), F.max("value").alias("x")).select("event_type", F.map_from_arrays(F.array(F.lit("m"), F.lit("x")), F.array("m", "x")).alias("d")).select("event_type", F.size(F.map_keys("d")).alias("keys"), F.map_filter("d", lambda k, v: k == "m")["m"].alias("v")), ["r AS (SELECT event_type, 2 AS keys, avg(value) AS v FROM events GROUP BY event_type)"])
add("null_functions", "kind n:l", lambda spark, d: _DL("left")(spark, d).select(F.coalesce(F.when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "bad"), F.lit("none")).alias("kind")).groupBy("kind").agg(F.count("*").alias("n")), ["r AS (SELECT coalesce(CASE quality WHEN 1 THEN 'good' WHEN 0 THEN 'bad' END, 'none') AS kind, count(*) AS n FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1)"])
add("sql_parameters", "event_type n:l", lambda spark, d: spark.sql("SELECT event_type, count(*) AS n FROM {e} WHERE value >= :low GROUP BY event_type", args={"low": 20}, e=load(spark, d, "events")), ["r AS (SELECT event_type, count(*) AS n FROM events WHERE value >= 20 GROUP BY event_type)"])

# Functions in Python, for parity -------------------------------------------------------------------------------


def _pairs(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("feature").orderBy("ds")
    return clean(spark, d).filter("kind <> 'C'").select("ds", "feature", "quantiles", F.lag("quantiles").over(w).alias("p")).filter("p is not null")


for _kind in ("ks", "w1", "dts"):
    add(f"udf_{_kind}_distance", "ds:s feature same", lambda spark, d, k=_kind: _pairs(spark, d).select("ds", "feature", (F.abs(getattr(udfs, f"{k}_distance")("quantiles", "p") - DISTANCES[k](F.col("quantiles"), F.col("p"))) <= 1e-6).alias("same")), [*o.summary(CLEAN), "r AS (SELECT ds, feature, TRUE AS same FROM s WHERE kind <> 'C' AND ds > DATE '2024-01-01' AND quantiles IS NOT NULL)"])
add("udaf_weighted_median", "event_type m:3", lambda spark, d: load(spark, d, "events").groupBy("event_type").agg(udfs.weighted_median("value", F.lit(1.0)).alias("m")), ["r AS (SELECT event_type, quantile_disc(value, 0.5) AS m FROM events GROUP BY event_type)"])
add("udtf_percentile_rows", "ds:s rank:l value:4", lambda spark, d: (udfs.register(spark), clean(spark, d).filter("feature = 'amount'").createOrReplaceTempView("amount_summaries"), spark.sql("SELECT ds, rank, value FROM amount_summaries, LATERAL percentile_rows(quantiles)"))[2], [*o.summary(CLEAN), "r AS (SELECT ds, unnest(range(1, 100)) AS rank, unnest(quantiles) AS value FROM s WHERE feature = 'amount')"])
add("grouped_map_cogroup", "event_type labelled:l total:l", lambda spark, d: _cogrouped(spark, d), ["r AS (SELECT event_type, count(*) FILTER (value > 50) AS labelled, count(*) AS total FROM events GROUP BY event_type)"])


def _cogrouped(spark: SparkSession, d: str) -> DataFrame:
    import pandas as pd

    e = load(spark, d, "events").groupBy("event_type", F.floor(F.col("event_id") / 1000).alias("b")).agg(F.count("*").alias("n"), F.count_if(F.col("value") > 50).alias("m"))
    a, b = e.select("event_type", "n"), e.select("event_type", "m")
    return a.groupBy("event_type").cogroup(b.groupBy("event_type")).applyInPandas(lambda x, y: pd.DataFrame({"event_type": [x["event_type"].iloc[0]], "labelled": [int(y["m"].sum())], "total": [int(x["n"].sum())]}), "event_type string, labelled long, total long")


# Sources, sinks, store -------------------------------------------------------------------------------------------

_EVENTS_KEPT = "event_id BIGINT, event_type STRING, value DOUBLE"
for _kind in ("csv", "json", "orc", "parquet"):
    def _round_trip(spark: SparkSession, d: str, k: str = _kind) -> DataFrame:
        path = scratch(spark, f"export-{k}")
        write_export(load(spark, d, "events").select("event_id", "event_type", "value"), path, k)
        return read_export(spark, path, k, _EVENTS_KEPT)

    add(f"source_sink_{_kind}", "event_id:l event_type value:2", _round_trip, ["r AS (SELECT event_id, event_type, value FROM events)"])
add("source_range_values", "id:l name", lambda spark, d: spark.range(5).join(spark.createDataFrame([(0, "a"), (3, "b")], "id long, name string"), "id", "left"), ["r AS (SELECT id, name FROM (SELECT unnest(range(5)) AS id) LEFT JOIN (VALUES (0, 'a'), (3, 'b')) v(id, name) USING (id))"])


def _store(spark: SparkSession, d: str, data: Dataset = CLEAN) -> DataFrame:
    """Every partition but the last at once, the last one twice by itself: one copy of each comes back."""
    import datetime

    path = scratch(spark, "store")
    upsert(summary_of(spark, d, data).filter("ds < '2024-01-30'").drop("w1_prev"), path, data.name)
    for _ in range(2):
        update(spark, path, data, d, datetime.date(2024, 1, 30))
    return history(spark, path, data.name)


add("store_incremental", "ds:s feature n_rows:l n_valid:l completeness:6 mean:4 n_distinct:l w1_prev:4", _store, o.summary(CLEAN), "s")
add("clustered_from_store", "ds:s score:4", lambda spark, d: cd.clustered_score(_store(spark, d, LOW), given_groups(spark, LOW), labels=lb.plan_labels(spark, ft.LOW, 1)), [*CLUSTERED_SQL(), *o.neighbors()])

# Streams, drained, against the batch ---------------------------------------------------------------------------------

_DAYS = ["r AS (SELECT CAST(ts AS DATE) AS day, count(*) AS n_rows, avg(value) AS mean FROM events WHERE CAST(ts AS DATE) < (SELECT max(CAST(ts AS DATE)) FROM events) GROUP BY 1)"]
add("stream_tumbling_append", "day:s n_rows:l mean:4", lambda spark, d: st.drained(st.daily(st.source(spark, d))).withColumn("day", F.col("window.start").cast("date")), _DAYS)
add("stream_tumbling_complete", "day:s n_rows:l mean:4", lambda spark, d: st.drained(st.daily(st.source(spark, d)), "complete").withColumn("day", F.col("window.start").cast("date")), [_DAYS[0].replace(" WHERE CAST(ts AS DATE) < (SELECT max(CAST(ts AS DATE)) FROM events)", "")])
add("stream_sliding", "day:s n_rows:l", lambda spark, d: st.drained(st.sliding(st.source(spark, d)), "complete").withColumn("day", F.col("window.start").cast("date")), ["d AS (SELECT CAST(unnest(generate_series(DATE '2023-12-26', DATE '2024-01-30', INTERVAL 1 DAY)) AS DATE) AS day)", "r AS (SELECT day, count(*) AS n_rows FROM d JOIN events ON ts >= day AND ts < day + INTERVAL 7 DAY GROUP BY day)"])
add("stream_sessions", "user_id:l start:s n_rows:l", lambda spark, d: st.drained(st.sessions(st.source(spark, d))).select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n_rows"),
    ["t AS (SELECT user_id, ts, coalesce(ts > lag(ts) OVER w + INTERVAL 2 HOUR, TRUE)::INT AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts))", "n AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts) AS nth FROM t)", "r AS (SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n_rows FROM n GROUP BY user_id, nth HAVING max(ts) + INTERVAL 2 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY)"])
add("stream_dedup", "n:l", lambda spark, d: st.drained(st.deduplicated(st.source(spark, d))).agg(F.count("*").alias("n")), ["r AS (SELECT count(DISTINCT event_id) AS n FROM events)"])
add("stream_static_join", "cluster:l n:l", lambda spark, d: st.drained(st.with_groups(st.source(spark, d), spark.createDataFrame([("click", 0), ("view", 0), ("purchase", 1)], "event_type string, cluster long"))).groupBy("cluster").agg(F.count("*").alias("n")), ["r AS (SELECT CASE event_type WHEN 'click' THEN 0 WHEN 'view' THEN 0 WHEN 'purchase' THEN 1 END AS cluster, count(*) AS n FROM events GROUP BY 1)"])
add("stream_interval_join", "purchase:l click:l", lambda spark, d: st.drained(st.follow_ups(st.source(spark, d), st.source(spark, d))), ["r AS (SELECT a.event_id AS purchase, b.event_id AS click FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts <= a.ts AND b.ts >= a.ts - INTERVAL 1 HOUR WHERE a.event_type = 'purchase' AND b.event_type = 'click')"])


def _stateful(spark: SparkSession, d: str) -> DataFrame:
    path = scratch(spark, "days")
    clean(spark, d).select("feature", "ds", F.col("completeness").alias("value")).coalesce(1).write.parquet(path)
    return st.drained(st.stateful_z(spark.readStream.schema("feature string, ds date, value double").parquet(path)))


_CFEW = [*o.summary(CLEAN), *o.changes("completeness"), "r AS (SELECT * FROM c)"]
add("stream_stateful_z", "ds:s feature z:5", _stateful, _CFEW)


def _upserted(spark: SparkSession, d: str) -> DataFrame:
    """Counts by day and kind: every micro-batch adds its own, the sums are made when they are read."""
    path, marks = scratch(spark, "store"), scratch(spark, "stream-state")
    counts = lambda batch: batch.groupBy(F.col("ts").cast("date").alias("ds"), F.col("event_type").alias("feature")).agg(F.count("*").alias("n_rows"))
    st.upsert_each(st.source(spark, d), lambda batch, number: add_states(counts(batch), path, "stream", number), marks)
    return merged_states(spark, path, "stream", lambda states, ds: states.groupBy(ds.alias("ds"), "feature").agg(F.sum("n_rows").alias("n_rows")))


def _streamed_sketches(spark: SparkSession, d: str) -> DataFrame:
    """Summaries of a stream: each micro-batch adds its sketches to the store, reading it merges those of a day."""
    path, marks = scratch(spark, "store"), scratch(spark, "stream-state")
    sketches = lambda batch: summarize_sketch(CLEAN.rows_of(events=batch), CLEAN.features)
    st.upsert_each(st.source(spark, d), lambda batch, number: add_states(sketches(batch), path, CLEAN.name, number), marks)
    return read_sketches(merged_states(spark, path, CLEAN.name, merge_sketches))


add("stream_foreach_sketches", "ds:s feature n_rows:l n_valid:l completeness:6 mean:4 stddev:4 min:4 max:4", _streamed_sketches, o.summary(CLEAN), "s")
add("stream_foreach_upsert", "ds:s feature n_rows:l", _upserted,["r AS (SELECT CAST(ts AS DATE) AS ds, event_type AS feature, count(*) AS n_rows FROM events GROUP BY 1, 2)"])
