"""All queries by name, each with the SQL of an independent engine where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..methods import alerts as al
from ..methods import cluster as cl
from ..methods import clustered as cd
from ..methods import evaluation as ev
from ..methods import labels as lb
from ..methods import scores as sc
from ..operators import rolling as ro
from ..operators import summary as sm
from ..operators.store import summary_of
from ..sources import faults as ft
from ..sources import features as fe
from ..sources.tables import load
from . import oracles as o

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def final(df: DataFrame, spec: str) -> DataFrame:
    """Columns of a spec, as in ``oracles.columns``: the last step of every query, so that both engines show the same."""
    out = []
    for item in spec.split():
        name, _, how = item.partition(":")
        out.append({"": F.col(name), "s": F.col(name).cast("string"), "l": F.col(name).cast("long")}.get(how, None) if how in ("", "s", "l") else F.round(F.col(name).cast("double") + float(o.nudge(how)), int(how)) + F.lit(0.0))
    return df.select(*(c.alias(i.partition(":")[0]) for c, i in zip(out, spec.split())))


def add(name: str, spec: str, make: Query, ctes: list[str] | None = None, source: str = "r") -> None:
    QUERIES[name] = lambda spark, sf_dir: final(make(spark, sf_dir), spec)
    if ctes is not None:
        SQL[name] = o.query(ctes, source, spec)


# Summaries ------------------------------------------------------------------------------------

SCALARS = "ds:s feature kind n_rows:l n_valid:l completeness:6 mean:4 stddev:4 min:4 max:4 n_distinct:l top_count:l top_freq:6"
for _name, _make in fe.DATASETS.items():
    _data = _make()
    add(f"summary_{_name}", SCALARS, lambda spark, d, m=_make: sm.summarize(m().rows(spark, d), m().features, quantiles=False), o.summary(_data, quantiles=False), "s")

CLEAN = fe.events()
LOW, HIGH = fe.events(ft.LOW), fe.events(ft.HIGH)
NULLS = fe.events(ft.single("null_out"))
FAMILY_NAMES = sorted({f.family for f in fe.EVENTS} | {f.family for f in fe.EVENTS_HIGH})
GIVEN = {f.name: FAMILY_NAMES.index(f.family) for f in [*fe.EVENTS, *fe.EVENTS_HIGH]}


def _given(data: fe.Dataset) -> dict[str, int]:
    return {f.name: GIVEN[f.name] for f in data.features}


def _s(data: fe.Dataset) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: summary_of(spark, d, data)


low, high, nulls, clean = _s(LOW), _s(HIGH), _s(NULLS), _s(CLEAN)
S_LOW, S_HIGH, S_NULLS, S_CLEAN = (o.summary(x) for x in (LOW, HIGH, NULLS, CLEAN))

add("summary_faulted_low", SCALARS + " n_frequent:l w1_prev:4", low, S_LOW, "s")
add("summary_frequent_values", "ds:s feature n_frequent:l top_count:l", clean, S_CLEAN, "s")
add("summary_quantiles99", "ds:s feature rank:l value:4", lambda spark, d: clean(spark, d).filter("quantiles is not null").select("ds", "feature", F.posexplode("quantiles").alias("p", "value")).withColumn("rank", F.col("p") + 1),
    [*S_CLEAN, "r AS (SELECT ds, feature, unnest(range(1, 100)) AS rank, unnest(quantiles) AS value FROM s WHERE kind <> 'C')"])
add("summary_typed_kinds", "kind n:l completeness:6", lambda spark, d: clean(spark, d).groupBy("kind").agg(F.count("*").alias("n"), F.avg("completeness").alias("completeness")), [*S_CLEAN, "r AS (SELECT kind, count(*) AS n, avg(completeness) AS completeness FROM s GROUP BY kind)"])
add("summary_wide_form", "ds:s feature n_rows:l n_valid:l completeness:6 mean:4 stddev:4 min:4 max:4 n_distinct:l", lambda spark, d: sm.summarize_wide(CLEAN.rows(spark, d), CLEAN.features), S_CLEAN, "s")

_MAPPED = ("amount", "prop_k", "amt_purchase", "amt_click", "amt_view", "amt_error", "amt_signup", "over_5", "is_click", "user_id")


def _map_form(spark: SparkSession, d: str) -> DataFrame:
    named = {f.name: f.expr for f in fe.EVENTS}
    cells = F.map_from_entries(F.filter(F.array(*(F.struct(F.lit(n), F.expr(named[n]).cast("double").alias("v")) for n in _MAPPED)), lambda e: e["v"].isNotNull()))
    return CLEAN.rows(spark, d).select("ds", "ts", F.col("event_type").alias("model_id"), F.lit(1).alias("model_version"), cells.alias("data"))


add("summary_events_map_form", "ds:s feature n_rows:l n_valid:l completeness:6 mean:4 min:4 max:4", lambda spark, d: sm.summarize_map(_map_form(spark, d), "data"), [*S_CLEAN, "r AS (SELECT * FROM s WHERE feature IN ('" + "', '".join(_MAPPED) + "'))"])
add("summary_embeddings_dims", "ds:s feature n_valid:l mean:4 stddev:4 min:4 max:4", lambda spark, d: sm.summarize_array(load(spark, d, "embeddings").withColumn("ds", F.floor(F.col("vec_id") / 25)), "embedding"),
    ["e AS (SELECT vec_id // 25 AS ds, embedding FROM embeddings)", "x AS (SELECT ds, 'dim_' || lpad(CAST(i - 1 AS VARCHAR), 2, '0') AS feature, CAST(embedding[i] AS DOUBLE) AS num FROM e, (SELECT unnest(range(1, 65)) AS i) UNION ALL SELECT ds, 'norm', sqrt(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * CAST(v AS DOUBLE)))) FROM e)", "r AS (SELECT ds, feature, count(num) AS n_valid, avg(num) AS mean, stddev_samp(num) AS stddev, min(num) AS min, max(num) AS max FROM x GROUP BY 1, 2)"])


def _merged(spark: SparkSession, d: str) -> DataFrame:
    hours = fe.events(grain="hour")
    return sm.read_sketches(sm.merge_sketches(sm.summarize_sketch(hours.rows(spark, d), hours.features), F.col("ds").cast("date")))


add("summary_merge_hour_to_day", "ds:s feature n_rows:l n_valid:l completeness:6 mean:4 stddev:4 min:4 max:4", _merged, S_CLEAN, "s")


def _sketch_errors(spark: SparkSession, d: str) -> DataFrame:
    """Whether every sketched statistic lies within its bound of the exact one."""
    exact = clean(spark, d).select("ds", "feature", F.col("n_distinct").alias("nd"), F.col("quantiles").alias("q"), F.col("top_freq").alias("tf"), F.col("n_valid").alias("nv"))
    both = sm.read_sketches(sm.summarize_sketch(CLEAN.rows(spark, d), CLEAN.features)).join(exact, ["ds", "feature"])
    near = F.abs(F.col("n_distinct") - F.col("nd")) <= F.greatest(F.lit(2.0), 0.06 * F.col("nd"))
    span = F.element_at("q", 99) - F.element_at("q", 1)
    # a rank error of 2 % moves a percentile to one of its neighbours, and a sketch gives values where the exact one interpolates between two
    off = (4 + F.ceil(100 / F.greatest(F.col("nv"), F.lit(1)))).cast("int")
    at = lambda i: (F.get("quantiles", i) >= F.get("q", i - off) - 0.05 * span) & (F.get("quantiles", i) <= F.get("q", i + off) + 0.05 * span)
    inside = F.forall(F.filter(F.sequence(F.lit(0), F.lit(98)), lambda i: (i >= off) & (i + off <= 98)), at)
    return both.agg(F.min(near.cast("int")).alias("distinct_ok"), F.min(F.coalesce(inside, F.lit(True)).cast("int")).alias("quantiles_ok"), F.min((F.abs(F.col("top_freq") - F.col("tf")) <= 0.02).cast("int")).alias("top_ok"))


add("summary_sketch_vs_exact", "distinct_ok:l quantiles_ok:l top_ok:l", _sketch_errors, ["r AS (SELECT 1 AS distinct_ok, 1 AS quantiles_ok, 1 AS top_ok)"])


def _topk(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    counts = CLEAN.rows(spark, d).groupBy("ds", "event_type").agg(F.count("*").alias("n"))
    return counts.withColumn("rank", F.row_number().over(Window.partitionBy("ds").orderBy(F.desc("n"), "event_type"))).filter("rank <= 3")


add("summary_topk_values", "ds:s event_type n:l rank:l", _topk, ["t AS (SELECT CAST(ts AS DATE) AS ds, event_type, count(*) AS n FROM events GROUP BY 1, 2)", "r AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY ds ORDER BY n DESC, event_type) AS rank FROM t) WHERE rank <= 3)"])


def _histogram(spark: SparkSession, d: str) -> DataFrame:
    from ..functions.stats import histogram_bin

    return CLEAN.rows(spark, d).groupBy("ds", histogram_bin(F.col("value"), 0, 100, 10).alias("bin")).agg(F.count("*").alias("n"))


add("summary_histogram", "ds:s bin:l n:l", _histogram, ["r AS (SELECT CAST(ts AS DATE) AS ds, CASE WHEN value < 0 THEN 0 WHEN value >= 100 THEN 11 ELSE floor((value - 0) / ((100 - 0) / 10)) + 1 END AS bin, count(*) AS n FROM events GROUP BY 1, 2)"])

# Normalisation over time ------------------------------------------------------------------------

add("roll_base_spread", "ds:s feature s:4 base:4 spread:4", lambda spark, d: ro.rolling(low(spark, d), "mean"), [*S_LOW, *o.changes("mean")], "c")
add("roll_rel_change", "ds:s feature rel:6", lambda spark, d: ro.changes(low(spark, d), "completeness"), [*S_LOW, *o.changes("completeness")], "c")
add("roll_z_change", "ds:s feature z:5", lambda spark, d: ro.changes(low(spark, d), "completeness"), [*S_LOW, *o.changes("completeness")], "c")
add("roll_z_population", "ds:s feature z:5", lambda spark, d: ro.changes(low(spark, d), "completeness", ddof=0), [*S_LOW, *o.changes("completeness", ddof=0)], "c")
add("roll_dynamic_bounds", "ds:s feature lo:4 hi:4 inside", lambda spark, d: ro.dynamic_bounds(low(spark, d), "mean"), [*S_LOW, *o.changes("mean"), "r AS (SELECT ds, feature, base - 3 * spread AS lo, base + 3 * spread AS hi, s BETWEEN base - 3 * spread AND base + 3 * spread AS inside FROM c)"])
add("static_bounds", "ds:s feature inside", lambda spark, d: ro.static_bounds(low(spark, d), "completeness", 0.1, 1.0), [*S_LOW, "r AS (SELECT ds, feature, completeness BETWEEN 0.1 AND 1.0 AS inside FROM s)"])
add("compare_previous", "ds:s feature rel:6", lambda spark, d: ro.vs_previous(low(spark, d), "completeness"), [*S_LOW, "q AS (SELECT ds, feature, completeness AS s, lag(completeness) OVER (PARTITION BY feature ORDER BY ds) AS base FROM s)", "r AS (SELECT ds, feature, CASE WHEN base <> 0 THEN (s - base) / base END AS rel FROM q)"])
add("compare_history_union", "ds:s feature h_completeness:6 h_mean:3 h_stddev:3", lambda spark, d: ro.vs_history(low(spark, d).filter("kind <> 'C'")),
    [*S_LOW, "d AS (SELECT DISTINCT ds, feature FROM s WHERE kind <> 'C')", "r AS (SELECT d.ds, d.feature, count(l.num) / nullif(count(l.feature), 0) AS h_completeness, avg(l.num) AS h_mean, stddev_samp(l.num) AS h_stddev FROM d LEFT JOIN s_long l ON l.feature = d.feature AND l.ds < d.ds GROUP BY 1, 2)"])
_WEIGHTS = [0.7**i for i in range(14)]
add("ewma_summary", "ds:s feature base:5", lambda spark, d: ro.ewma(low(spark, d), "completeness"),
    [*S_LOW, "n AS (SELECT ds, feature, completeness, row_number() OVER (PARTITION BY feature ORDER BY ds) AS t FROM s)", "r AS (SELECT a.ds, a.feature, sum(b.completeness * pow(0.7, a.t - b.t - 1)) / nullif(sum(pow(0.7, a.t - b.t - 1)) FILTER (b.completeness IS NOT NULL), 0) AS base FROM n a LEFT JOIN n b ON b.feature = a.feature AND b.t < a.t AND b.t >= a.t - 14 GROUP BY 1, 2)"])
add("roll_quantiles", "ds:s feature median:4 p90:4", lambda spark, d: ro.rolling_quantiles(low(spark, d)).withColumns({"median": F.get("reference", F.lit(49)), "p90": F.get("reference", F.lit(89))}), [*S_LOW, *o.distances("w1"), "r AS (SELECT ds, feature, reference[50] AS median, reference[90] AS p90 FROM h)"])
add("roll_interval_frame", "ds:s feature base:6", lambda spark, d: ro.interval_frame(low(spark, d), "completeness"), [*S_LOW, "r AS (SELECT ds, feature, avg(completeness) OVER (PARTITION BY feature ORDER BY ds RANGE BETWEEN INTERVAL 7 DAYS PRECEDING AND INTERVAL 1 DAYS PRECEDING) AS base FROM s)"])
add("roll_same_weekday", "ds:s feature base:6", lambda spark, d: ro.rolling(low(spark, d), "completeness", k=2, season=7), [*S_LOW, "q AS (SELECT ds, feature, row_number() OVER f AS nth, avg(completeness) OVER (PARTITION BY feature, isodow(ds) ORDER BY ds ROWS BETWEEN 2 PRECEDING AND 1 PRECEDING) AS b FROM s WINDOW f AS (PARTITION BY feature, isodow(ds) ORDER BY ds))", "r AS (SELECT ds, feature, CASE WHEN nth > 2 THEN b END AS base FROM q)"])


def _clean_base(spark: SparkSession, d: str) -> DataFrame:
    y = lb.plan_labels(spark, ft.LOW, 1).select("ds", "y")
    return ro.rolling(low(spark, d).join(F.broadcast(y), "ds"), "completeness", clean_only="y")


add("roll_clean_base", "ds:s feature base:6", _clean_base, [*S_LOW, o.labels(ft.LOW), "n AS (SELECT s.ds, feature, completeness, y.y FROM s JOIN y ON y.ds = s.ds AND y.level = 1)", "q AS (SELECT a.ds, a.feature, b.completeness AS c, row_number() OVER (PARTITION BY a.ds, a.feature ORDER BY b.ds DESC) AS r FROM n a JOIN n b ON b.feature = a.feature AND b.ds < a.ds AND b.y = 0)", "u AS (SELECT ds, feature, avg(c) AS b, count(*) AS n FROM q WHERE r <= 7 GROUP BY 1, 2)", "r AS (SELECT s.ds, s.feature, CASE WHEN n >= 7 THEN b END AS base FROM s LEFT JOIN u USING (ds, feature))"])

# Scores -----------------------------------------------------------------------------------------

SCORE = "ds:s score:5"
for _norm in ("rel", "z"):
    add(f"general_{_norm}", SCORE, lambda spark, d, n=_norm: sc.general_score(low(spark, d), "completeness", n), [*S_LOW, *o.changes("completeness"), o.scored(_norm)])
add("general_z_absolute", SCORE, lambda spark, d: sc.general_score(low(spark, d), "completeness", "z", absolute=True), [*S_LOW, *o.changes("completeness"), o.scored("abs(z)")])
add("completeness_drop", SCORE, lambda spark, d: sc.completeness_drop(low(spark, d)), [*S_LOW, *o.changes("completeness"), o.scored(o.drop())])
add("completeness_drop_literal", SCORE, lambda spark, d: sc.completeness_drop(low(spark, d), direction="rise"), [*S_LOW, *o.changes("completeness"), o.scored(o.drop(sign="rel"))])
add("completeness_alerts30", "ds:s feature rel:5", lambda spark, d: sc.completeness_alerts(low(spark, d)), [*S_LOW, *o.changes("completeness"), "r AS (SELECT * FROM c WHERE rel < -0.3)"])
DELTAS = [0.05, 0.1, 0.2, 0.3, 0.5]
for _which, _sum, _ctes in (("", low, S_LOW), ("_null_out", nulls, S_NULLS)):
    add(f"delta_sweep{_which}", "delta:2 ds:s score:5", lambda spark, d, s=_sum: sc.delta_sweep(s(spark, d), DELTAS), [*_ctes, *o.changes("completeness"), f"x AS (SELECT * FROM c, (SELECT unnest({DELTAS}) AS delta))", o.scored(o.drop("delta"), source="x", keys="delta, ds")])
for _short, _stat in {"completeness": "completeness", "mean": "mean", "std": "stddev", "distinct": "n_distinct", "topfreq": "top_freq", "min": "min", "max": "max"}.items():
    add(f"zscore_{_short}", SCORE, lambda spark, d, q=_stat: sc.zscore_score(low(spark, d), q), [*S_LOW, *o.changes(_stat), o.scored("CASE WHEN abs(z) >= 3 THEN abs(z) ELSE 0 END")])
add("zscore_nocutoff", SCORE, lambda spark, d: sc.zscore_score(low(spark, d), tau=0), [*S_LOW, *o.changes("completeness"), o.scored("abs(z)")])
add("zscore_share", SCORE, lambda spark, d: sc.zscore_score(low(spark, d), contrib="indicator"), [*S_LOW, *o.changes("completeness"), o.scored("CASE WHEN abs(z) >= 3 THEN 1 ELSE 0 END")])
for _kind in ("ks", "w1", "dts"):
    add(f"dist_{_kind}", "ds:s feature h:3", lambda spark, d, k=_kind: sc.distances(low(spark, d), k), [*S_LOW, *o.distances(_kind)], "h")
add("dist_ks_probability", "ds:s feature h:6", lambda spark, d: sc.distances(low(spark, d), "ks_probability"), [*S_LOW, *o.distances("ks_probability")], "h")
add("distance_alerts", SCORE.replace("5", "3"), lambda spark, d: sc.distance_score(low(spark, d), "w1"), [*S_LOW, *o.distances("w1"), "r AS (SELECT ds, avg(h) AS score FROM h GROUP BY ds)"])
for _kind in ("ks", "w1", "dts"):
    _p = [*S_LOW, *o.distances(_kind), *o.hashed_p(_kind)]
    add(f"pvalue_md5_{_kind}", "ds:s feature p:6", lambda spark, d, k=_kind: sc.resample_hashed(sc.distances(low(spark, d), k), k), _p, "p")
    add(f"two_sample_{_kind}", "ds:s score:6", lambda spark, d, k=_kind: sc.two_sample_score(sc.resample_hashed(sc.distances(low(spark, d), k), k)), [*_p, "r AS (SELECT ds, avg(CASE WHEN p <= 0.05 THEN 1.0 ELSE 0.0 END) AS score FROM p GROUP BY ds)"])
    add(f"two_sample_resampled_{_kind}", "ds:s score:6", lambda spark, d, k=_kind: sc.two_sample_score(sc.resample(sc.distances(low(spark, d), k), k)))
for _short, _how in {"within": "within_vector", "perdim": "per_dimension", "none": "none"}.items():
    add(f"knn_baseline_{_short}", "ds:s score:4", lambda spark, d, h=_how: sc.knn_score(low(spark, d), rescale=h), [*S_LOW, *o.knn(_how)])


def _z_rows(spark: SparkSession, d: str) -> DataFrame:
    return ro.six_z(low(spark, d)).filter("absz is not null").withColumnRenamed("absz", "x")


add("knn_z_ablation", "ds:s score:4", lambda spark, d: sc.knn_score(low(spark, d), rescale="none", rows=_z_rows(spark, d)), [*S_LOW, *o.six(), *o.knn("none", rows=["r_n0 AS (SELECT ds, feature, stat, absz AS x FROM z WHERE absz IS NOT NULL)"])])
#: Two vectors of two statistics for three features, which differ in the last feature alone.
VECTORS = ((0.9, 13.0, 0.4, 1993.0, 0.8, 284448.0), (0.9, 13.0, 0.4, 1993.0, 0.2, 300.0))


def _counter_example(spark: SparkSession, d: str) -> DataFrame:
    rows = spark.createDataFrame([(t, str(i), "x", v) for t, vector in enumerate(VECTORS) for i, v in enumerate(vector)], "ds int, feature string, stat string, x double")
    return sc.rescaled(rows, "within_vector")


add("rescale_counterexample", "ds:l feature x:9", _counter_example, ["v(ds, feature, x) AS (VALUES " + ", ".join(f"({t}, '{i}', {v}::DOUBLE)" for t, vec in enumerate(VECTORS) for i, v in enumerate(vec)) + ")", "r AS (SELECT ds, feature, (x - min(x) OVER w) / (max(x) OVER w - min(x) OVER w) AS x FROM v WINDOW w AS (PARTITION BY ds))"])
add("pca_score", "ds:s score:4", lambda spark, d: sc.pca_score(low(spark, d)))
add("always_block", "ds:s score:1", lambda spark, d: sc.constant_score(low(spark, d), 1), [*S_LOW, "r AS (SELECT DISTINCT ds, 1 AS score FROM s)"])
add("never_block", "ds:s score:1", lambda spark, d: sc.constant_score(low(spark, d), 0), [*S_LOW, "r AS (SELECT DISTINCT ds, 0 AS score FROM s)"])
add("schema_check", "ds:s rule violations:l share:6", lambda spark, d: sc.schema_check(LOW.rows(spark, d), {"v": "double", "user_id": "bigint"}, {"v": (0.0, 1000.0), "k": (0, 99)}),
    [f"w AS ({LOW.duck_rows()})", "r AS (SELECT ds, rule, sum(bad) AS violations, avg(bad) AS share FROM (SELECT ds, unnest(['type:v', 'type:user_id', 'bounds:v', 'bounds:k']) AS rule, unnest([0, 0, CASE WHEN v BETWEEN 0 AND 1000 THEN 0 ELSE 1 END, CASE WHEN k BETWEEN 0 AND 99 THEN 0 ELSE 1 END]) AS bad FROM w) GROUP BY 1, 2)"])
RULES = [("positive", "v > 0"), ("known_type", "et IN ('purchase', 'click', 'view', 'error', 'signup')"), ("has_user", "user_id IS NOT NULL")]
add("constraint_check", "ds:s rule violations:l share:6", lambda spark, d: sc.constraint_check(LOW.rows(spark, d), RULES),
    [f"w AS ({LOW.duck_rows()})", "r AS (SELECT ds, rule, sum(bad) AS violations, avg(bad) AS share FROM (SELECT ds, unnest([" + ", ".join(f"'{n}'" for n, _ in RULES) + "]) AS rule, unnest([" + ", ".join(f"CASE WHEN {p} THEN 0 ELSE 1 END" for _, p in RULES) + "]) AS bad FROM w) GROUP BY 1, 2)"])
add("fd_check", "ds:s groups:l broken:l share:6", lambda spark, d: sc.fd_check(fe.DATASETS["orders_monthly"]().rows(spark, d), "o_orderpriority", "o_orderstatus"),
    ["w AS (SELECT CAST(date_trunc('month', o_orderdate) AS DATE) AS ds, o_orderpriority AS l, count(DISTINCT o_orderstatus) AS n FROM orders GROUP BY 1, 2)", "r AS (SELECT ds, count(*) AS groups, count(*) FILTER (n > 1) AS broken, count(*) FILTER (n > 1) / count(*) AS share FROM w GROUP BY ds)"])

# The clustered validator ------------------------------------------------------------------------

for _stat in ro.SIX:
    add(f"cov_pairs_{_stat}", "stat f1 f2 cov:4", lambda spark, d, q=_stat: cl.stat_covariance(low(spark, d), (q,), kind="covariance"), [*S_LOW, f"t AS (SELECT ds, feature, CAST({_stat} AS DOUBLE) AS x FROM s WHERE {_stat} IS NOT NULL)", f"r AS (SELECT '{_stat}' AS stat, a.feature AS f1, b.feature AS f2, covar_samp(a.x, b.x) AS cov FROM t a JOIN t b ON a.ds = b.ds AND a.feature <= b.feature GROUP BY a.feature, b.feature)"])
_CORR = [*S_LOW, o.stat_rows(o.SIX, "t", "s"), "v AS (SELECT a.stat, a.feature AS f1, b.feature AS f2, covar_samp(a.x, b.x) AS cv, stddev_samp(a.x) AS sa, stddev_samp(b.x) AS sb, avg(a.x) AS ma, avg(b.x) AS mb FROM t a JOIN t b ON a.ds = b.ds AND a.stat = b.stat AND a.feature <= b.feature GROUP BY 1, 2, 3)", "corr AS (SELECT stat, f1, f2, CASE WHEN sa IS NULL OR sb IS NULL OR sa <= 1e-9 * greatest(1, abs(ma)) OR sb <= 1e-9 * greatest(1, abs(mb)) THEN 0 ELSE cv / (sa * sb) END AS cov FROM v)"]
add("corr_pairs", "stat f1 f2 cov:5", lambda spark, d: cl.stat_covariance(low(spark, d)), _CORR, "corr")
add("edge_weights", "src dst weight:5", lambda spark, d: cl.feature_graph(cl.stat_covariance(low(spark, d))), [*_CORR, "r AS (SELECT f1 AS src, f2 AS dst, sum(abs(cov)) AS weight FROM corr WHERE f1 < f2 GROUP BY 1, 2)"])
add("components_groups", "feature cluster:l", lambda spark, d: spark.createDataFrame(sorted(cl.groups_from_components(cl.feature_graph(cl.stat_covariance(low(spark, d))), sorted(r[0] for r in low(spark, d).select("feature").distinct().collect()), 3.0).items()), "feature string, cluster long"),
    [*_CORR, "edge AS (SELECT f1 AS a, f2 AS b FROM corr WHERE f1 < f2 GROUP BY 1, 2 HAVING sum(abs(cov)) >= 3.0)", "ways AS (SELECT a, b FROM edge UNION ALL SELECT b, a FROM edge)", f"walk(feature, low) AS (SELECT feature, feature FROM (SELECT DISTINCT feature FROM s) UNION SELECT ways.b, walk.low FROM walk JOIN ways ON ways.a = walk.feature)", "least_of AS (SELECT feature, min(low) AS low FROM walk GROUP BY feature)", "r AS (SELECT feature, dense_rank() OVER (ORDER BY low) - 1 AS cluster FROM least_of)"])
add("six_z", "ds:s feature stat absz:4", lambda spark, d: ro.six_z(low(spark, d)), [*S_LOW, *o.six()], "z")


def _groups(spark: SparkSession, data: fe.Dataset, how: str = "given") -> DataFrame:
    names = [f.name for f in data.features]
    made = {"given": _given(data), "single": dict.fromkeys(names, 0), "identity": {n: i for i, n in enumerate(sorted(names))}}[how]
    return cd.groups_frame(spark, made)


def _group_sql(data: fe.Dataset, how: str = "given") -> str:
    names = [f.name for f in data.features]
    return o.groups({"given": _given(data), "single": dict.fromkeys(names, 0), "identity": {n: i for i, n in enumerate(sorted(names))}}[how])


def _means(spark: SparkSession, d: str, data: fe.Dataset = LOW, how: str = "given") -> DataFrame:
    return cd.cluster_means(ro.six_z(summary_of(spark, d, data)), _groups(spark, data, how))


M_LOW = [*S_LOW, *o.six(), _group_sql(LOW), o.means()]
add("group_means_given", "ds:s cluster:l stat value:4", _means, M_LOW, "m")
add("matrix_long_given", "ds:s i:l value:4", lambda spark, d: cd.matrix(_means(spark, d)).select("ds", F.posexplode("x").alias("i", "value")),
    [*M_LOW, "r AS (SELECT ds, row_number() OVER (PARTITION BY ds ORDER BY cluster, CASE stat " + " ".join(f"WHEN '{q}' THEN {i}" for q, i in cd.STAT_ORDER.items()) + " END) - 1 AS i, value FROM m)"])


def _clustered(spark: SparkSession, d: str, data: fe.Dataset = LOW, plan: ft.FaultPlan = ft.LOW, how: str = "given", **args) -> DataFrame:
    return cd.clustered_score(summary_of(spark, d, data), _groups(spark, data, how), labels=lb.plan_labels(spark, plan, 1), **args)


_D = lambda how="given", **a: [*S_LOW, *o.six(), _group_sql(LOW, how), o.means(), o.labels(ft.LOW), *o.row_distances(**a)]
add("clustered_given_p1", "ds:s score:4", _clustered, [*_D(), *o.neighbors()])
add("clustered_given_p2", "ds:s score:4", lambda spark, d: _clustered(spark, d, p=2), [*_D(p=2), *o.neighbors()])
add("clustered_single", "ds:s score:4", lambda spark, d: _clustered(spark, d, how="single"), [*_D("single"), *o.neighbors()])
add("clustered_identity", "ds:s score:3", lambda spark, d: _clustered(spark, d, how="identity"), [*_D("identity"), *o.neighbors()])
add("clustered_recent", "ds:s score:4", lambda spark, d: _clustered(spark, d, horizon=10), [*_D(horizon=10), *o.neighbors()])
add("clustered_all_neighbors", "ds:s score:4", lambda spark, d: _clustered(spark, d, neighbors="all"), [*_D(), *o.neighbors(which="all")])
add("clustered_corrupt_neighbors", "ds:s score:4", lambda spark, d: _clustered(spark, d, neighbors="corrupt"), [*_D(), *o.neighbors(which="corrupt")])
for _share in (0.05, 0.1, 0.5):
    add(f"clustered_share_{int(100 * _share):02d}", "ds:s score:4", lambda spark, d, s=_share: _clustered(spark, d, share=s), [*_D(), *o.neighbors(share=_share)])
DAY = "2024-01-20"
add("drill_clusters", "cluster:l value:3 rank:l", lambda spark, d: cd.rank_clusters(_means(spark, d), F.lit(DAY).cast("date")), [*M_LOW, f"v AS (SELECT cluster, sum(value) AS value FROM m WHERE ds = DATE '{DAY}' GROUP BY cluster)", "r AS (SELECT *, row_number() OVER (ORDER BY value DESC, cluster) AS rank FROM v)"])


def _drill(spark: SparkSession, d: str) -> DataFrame:
    z = ro.six_z(low(spark, d))
    groups = _groups(spark, LOW)
    return cd.rank_features(z, groups, cd.cluster_means(z, groups), F.lit(DAY).cast("date")).filter("rank <= 3")


add("drill_features", "cluster:l cluster_rank:l rank:l absz:3", _drill, [*M_LOW, f"v AS (SELECT cluster, sum(value) AS value FROM m WHERE ds = DATE '{DAY}' GROUP BY cluster)", "k AS (SELECT *, row_number() OVER (ORDER BY value DESC, cluster) AS cluster_rank FROM v)", f"f AS (SELECT g.cluster, k.cluster_rank, feature, stat, absz, row_number() OVER (PARTITION BY g.cluster ORDER BY absz DESC, feature, stat) AS rank FROM z JOIN g USING (feature) JOIN k ON k.cluster = g.cluster WHERE ds = DATE '{DAY}' AND absz IS NOT NULL AND k.cluster_rank <= 2)", "r AS (SELECT * FROM f WHERE rank <= 3)"])
add("similar_incidents", "other:s d:3 rank:l", lambda spark, d: cd.similar_incidents(_means(spark, d), cd.ordinal(low(spark, d)), lb.plan_labels(spark, ft.LOW, 1), F.lit("2024-01-28").cast("date")), [*_D(), "r AS (SELECT other, d, row_number() OVER (ORDER BY d, other) AS rank FROM d JOIN y ON y.ds = other AND level = 1 AND y.y = 1 WHERE d.ds = DATE '2024-01-28')"])


def _report(spark: SparkSession, d: str) -> DataFrame:
    z = ro.six_z(low(spark, d))
    groups = _groups(spark, LOW)
    return cd.alert_report(z, groups, cd.cluster_means(z, groups), F.lit(DAY).cast("date"))


add("alert_report", "report", _report)


def _fitted(spark: SparkSession, d: str, data: fe.Dataset = LOW, method: str = "spectral") -> tuple[DataFrame, int]:
    groups, v = cl.fit_groups(summary_of(spark, d, data), method)
    return cd.groups_frame(spark, groups), v


for _method in ("spectral", "pic", "kmeans"):
    add(f"{_method}_groups", "feature cluster:l", lambda spark, d, m=_method: _fitted(spark, d, method=m)[0])
add("clustered_spectral", "ds:s score:4 version", lambda spark, d: cd.refitted_score(low(spark, d), cd.scheduled_groups(low(spark, d)), labels=lb.plan_labels(spark, ft.LOW, 1)))
add("cluster_counts", "stat components:l", lambda spark, d: spark.createDataFrame(sorted(cl.choose_clusters(cl.stat_matrices(low(spark, d))[1])[1].items()), "stat string, components long"))

# Alerts -----------------------------------------------------------------------------------------

_DROP = [*S_LOW, *o.changes("completeness"), o.scored(o.drop(), name="x")]
drop_scores = lambda spark, d: sc.completeness_drop(low(spark, d))
add("alert_fixed", "ds:s score:5 alert", lambda spark, d: al.alert_fixed(drop_scores(spark, d), 0.03), [*_DROP, "r AS (SELECT ds, score, coalesce(score >= 0.03, FALSE) AS alert FROM x)"])
add("alert_sigma", "ds:s score:4 threshold:4 alert", lambda spark, d: al.alert_sigma(_clustered(spark, d)), [*_D(), *o.neighbors("x"), "t AS (SELECT ds, score, avg(score) OVER w + 3 * stddev_samp(score) OVER w AS threshold FROM x WINDOW w AS (ORDER BY ds ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))", "r AS (SELECT *, coalesce(score > threshold, FALSE) AS alert FROM t)"])
add("alert_p95", "ds:s score:4 threshold:4 alert", lambda spark, d: al.alert_quantile(_clustered(spark, d)), [*_D(), *o.neighbors("x"), "t AS (SELECT ds, score, quantile_cont(score, 0.95) OVER w AS threshold FROM x WINDOW w AS (ORDER BY ds ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))", "r AS (SELECT *, coalesce(score > threshold, FALSE) AS alert FROM t)"])
_POLICY = [*_D(), *o.neighbors("far"), *o.changes("completeness"), o.scored(o.drop(), name="x"), "u AS (SELECT x.ds, CASE WHEN row_number() OVER (ORDER BY x.ds) <= 14 THEN 'completeness_drop' ELSE 'clustered' END AS rule, x.score AS a, far.score AS b FROM x LEFT JOIN far USING (ds))", "t AS (SELECT ds, rule, CASE WHEN rule = 'clustered' THEN b ELSE a END AS score, CASE WHEN rule = 'clustered' THEN 40 ELSE 0.03 END AS threshold FROM u)", "pol AS (SELECT *, coalesce(score >= threshold, FALSE) AS alert FROM t)"]
policy = lambda spark, d: al.alert_policy(drop_scores(spark, d), _clustered(spark, d), 0.03, 40.0)
add("alert_policy_first_week", "ds:s rule score:4 threshold:3 alert", policy, _POLICY, "pol")


def _promotion(spark: SparkSession, d: str) -> DataFrame:
    ok = lb.proxy_signals(LOW.rows(spark, d)).select("ds", F.coalesce(F.col("calib_error") < 0.5, F.lit(True)).alias("ok"))
    return al.promotion_decision(ok, policy(spark, d))


add("promotion_decision", "ds:s ok alert publish", _promotion, [*_POLICY, *o.proxy(LOW, "sig"), "k AS (SELECT ds, coalesce(calib_error < 0.5, TRUE) AS ok FROM sig)", "r AS (SELECT k.ds, ok, alert, ok AND NOT coalesce(alert, FALSE) AS publish FROM k LEFT JOIN pol USING (ds))"])
add("advisor", "partitions:l features:l low_cardinality:5 failure_rate:5 advice", lambda spark, d: al.recommend(low(spark, d), lb.plan_labels(spark, ft.LOW, 1)),
    [*S_LOW, o.labels(ft.LOW), "a AS (SELECT count(DISTINCT ds) AS partitions, count(DISTINCT feature) AS features FROM s)", "b AS (SELECT avg(CASE WHEN d <= 20 THEN 1.0 ELSE 0.0 END) AS low_cardinality FROM (SELECT feature, avg(n_distinct) AS d FROM s GROUP BY feature))", "f AS (SELECT avg(y) AS failure_rate FROM y WHERE level = 1)", "r AS (SELECT *, CASE WHEN partitions <= 14 THEN 'completeness_drop' WHEN failure_rate > 0.4 THEN 'knn_baseline' WHEN features < 10 AND low_cardinality < 0.2 THEN 'two_sample_w1' ELSE 'clustered' END AS advice FROM a, b, f)"])
add("alert_volume", "week:s alerts:l false_alerts:l", lambda spark, d: al.alert_volume(policy(spark, d), lb.plan_labels(spark, ft.LOW, 1)), [*_POLICY, "r AS (SELECT CAST(date_trunc('week', pol.ds) AS DATE) AS week, count(*) FILTER (alert) AS alerts, count(*) FILTER (alert AND coalesce(y.y, 0) = 0) AS false_alerts FROM pol LEFT JOIN y ON y.ds = pol.ds AND level = 1 GROUP BY 1)"])

# Truth and accuracy -----------------------------------------------------------------------------

signals = lambda spark, d: lb.proxy_signals(LOW.rows(spark, d))
PROXY = o.proxy(LOW)
add("proxy_cross_entropy", "ds:s ne:5 cross_entropy_up:5", signals, PROXY, "g")
add("proxy_calibration", "ds:s calib_error:5", signals, PROXY, "g")
add("label_shift", "ds:s label_rate:6 label_shift:5", signals, PROXY, "g")
_HIT = lambda t: f"(coalesce(cross_entropy_up >= {t[0]}, FALSE) OR coalesce(calib_error >= {t[1]}, FALSE) OR coalesce(label_shift >= {t[2]}, FALSE))::INT"


def _levels(spark: SparkSession, d: str) -> DataFrame:
    got = signals(spark, d)
    return lb.failure_labels(got, 1).unionByName(lb.failure_labels(got, 2)).unionByName(lb.failure_labels(got, 3))


add("failure_levels", "ds:s level:l y:l", _levels, [*PROXY, "r AS (" + " UNION ALL ".join(f"SELECT ds, {lv} AS level, {_HIT(t)} AS y FROM g" for lv, t in lb.LEVELS.items()) + ")"])
add("failure_levels_next_day", "ds:s level:l y:l", lambda spark, d: lb.failure_labels(signals(spark, d), 1, observe="next"), [*PROXY, f"r AS (SELECT ds, 1 AS level, coalesce(lead({_HIT(lb.LEVELS[1])}) OVER (ORDER BY ds), 0) AS y FROM g)"])
_PLANS = lambda spark, plan: lb.plan_labels(spark, plan, 1).unionByName(lb.plan_labels(spark, plan, 2)).unionByName(lb.plan_labels(spark, plan, 3))
for _plan in (ft.LOW, ft.HIGH):
    add(f"failure_rates_{_plan.name}", "level:l rate:4 failures:l n:l", lambda spark, d, p=_plan: ev.failure_rate(_PLANS(spark, p)), [o.labels(_plan), "r AS (SELECT level, avg(y) AS rate, sum(y) AS failures, count(*) AS n FROM y GROUP BY level)"])
add("perf_drop5", "ds:s base:5 y:l", lambda spark, d: lb.performance_drop(signals(spark, d), "label_rate"), [*PROXY, "q AS (SELECT ds, label_rate, row_number() OVER (ORDER BY ds) AS nth, avg(label_rate) OVER (ORDER BY ds ROWS BETWEEN 7 PRECEDING AND 1 PRECEDING) AS b FROM g)", "r AS (SELECT ds, CASE WHEN nth > 7 THEN b END AS base, CASE WHEN nth > 7 AND label_rate <= 0.95 * b THEN 1 ELSE 0 END AS y FROM q)"])

_scored = lambda spark, d: drop_scores(spark, d).withColumn("score", F.round("score", 9)).join(lb.plan_labels(spark, ft.LOW, 1).select("ds", "y"), "ds")
_SCORED = [*_DROP, o.labels(ft.LOW), "w AS (SELECT 1 AS one, x.ds, round(x.score, 9) AS score, y.y FROM x JOIN y ON y.ds = x.ds AND level = 1)", *o.measures("r", "w", "one")]
add("pr_curve", "tau:6 alerts:l hits:l prec:6 rec:6", lambda spark, d: ev.pr_curve(_scored(spark, d)).withColumnsRenamed({"precision": "prec", "recall": "rec"}), _SCORED, "r_c")
add("precision_at_recall90", "precision_at:6 n_scored:l n_pos:l", lambda spark, d: ev.measures(_scored(spark, d)), _SCORED)
add("average_precision", "ap:6", lambda spark, d: ev.measures(_scored(spark, d)), _SCORED)

CASE_METHODS = ("completeness_drop", "zscore_completeness", "distance_w1", "knn_baseline", "clustered_given", "always_block")


def case_scores(spark: SparkSession, d: str, data: fe.Dataset, plan: ft.FaultPlan, level: int, fits: DataFrame | None = None, more: bool = False) -> dict[str, DataFrame]:
    """Scores of every method on a faulted table; with ``more`` also those that SQL elsewhere can't repeat, some under the groups of a schedule of ``fits``."""
    s = summary_of(spark, d, data)
    y = lb.plan_labels(spark, plan, level)
    out = {
        "completeness_drop": sc.completeness_drop(s), "zscore_completeness": sc.zscore_score(s), "distance_w1": sc.distance_score(s, "w1"),
        "knn_baseline": sc.knn_score(s), "clustered_given": cd.clustered_score(s, _groups(spark, data), labels=y), "always_block": sc.constant_score(s, 1),
    }
    if more:
        out |= {f"two_sample_{k}": sc.two_sample_score(sc.resample(sc.distances(s, k), k)) for k in ("ks", "w1", "dts")}
        out |= {"clustered_spectral": cd.refitted_score(s, fits, labels=y), "clustered_p2": cd.refitted_score(s, fits, labels=y, p=2), "no_clusters": cd.clustered_score(s, _groups(spark, data, "identity"), labels=y), "pca": sc.pca_score(s)}
    return out


def case_study(spark: SparkSession, d: str, data: fe.Dataset, plan: ft.FaultPlan, more: bool = False) -> DataFrame:
    """(dataset, method, level, precision_at, ap, n_scored, n_pos) over the partitions that the clustered validator can score too."""
    parts, fits = [], cd.scheduled_groups(summary_of(spark, d, data)) if more else None
    for level in (1, 2, 3):
        y = lb.plan_labels(spark, plan, level).filter("ds >= '2024-01-09'").select("ds", "level", "y")
        for method, scores in case_scores(spark, d, data, plan, level, fits, more).items():
            parts.append(scores.join(F.broadcast(y), "ds").select(F.lit(plan.name).alias("dataset"), F.lit(method).alias("method"), "level", F.round("score", 7).alias("score"), "y"))
    rows = parts[0]
    for p in parts[1:]:
        rows = rows.unionByName(p)
    return ev.measures(rows, ("dataset", "method", "level"))


def _case_sql(data: fe.Dataset, plan: ft.FaultPlan) -> list[str]:
    ctes = [*o.summary(data), *o.changes("completeness"), o.scored(o.drop(), "m1"), o.scored("CASE WHEN abs(z) >= 3 THEN abs(z) ELSE 0 END", "m2"), *o.distances("w1"), "m3 AS (SELECT ds, avg(h) AS score FROM h GROUP BY ds)", *o.knn("within_vector", "m4"), *o.six(), _group_sql(data), o.means(), o.labels(plan), *o.row_distances()]
    parts = []
    for level in (1, 2, 3):
        ctes += o.neighbors(f"m5_{level}", level=level)
        for method, table in zip(CASE_METHODS, ("m1", "m2", "m3", "m4", f"m5_{level}", "m6")):
            parts.append(f"SELECT '{plan.name}' AS dataset, '{method}' AS method, {level} AS level, round(v.score, 7) AS score, y.y FROM {table} v JOIN y ON y.ds = v.ds AND y.level = {level} WHERE v.ds >= DATE '2024-01-09'")
    return [*ctes, "m6 AS (SELECT DISTINCT ds, 1 AS score FROM s)", f"w AS ({' UNION ALL '.join(parts)})", *o.measures("r", "w", "dataset, method, level")]


CASE = "dataset method level:l precision_at:4 ap:4 n_scored:l n_pos:l"
add("case_study_low", CASE, lambda spark, d: case_study(spark, d, LOW, ft.LOW), _case_sql(LOW, ft.LOW))
add("case_study_high", CASE, lambda spark, d: case_study(spark, d, HIGH, ft.HIGH), _case_sql(HIGH, ft.HIGH))
for _name, _data, _plan in (("low", LOW, ft.LOW), ("high", HIGH, ft.HIGH)):
    add(f"case_study_{_name}_all", CASE, lambda spark, d, a=_data, p=_plan: case_study(spark, d, a, p, more=True))
add("improvement_factor", "dataset method precision_factor:3 ap_factor:3", lambda spark, d: ev.improvement(case_study(spark, d, LOW, ft.LOW), "knn_baseline"),
    [*_case_sql(LOW, ft.LOW), "f AS (SELECT a.dataset, a.method, avg(a.precision_at / nullif(b.precision_at, 0)) AS precision_factor, avg(a.ap / nullif(b.ap, 0)) AS ap_factor FROM r a JOIN r b ON a.dataset = b.dataset AND a.level = b.level AND b.method = 'knn_baseline' GROUP BY 1, 2)"], "f")
add("cumulative_precision", "ds:s prec:5 rec:5", lambda spark, d: ev.cumulative(_scored(spark, d), 0.03).withColumnsRenamed({"precision": "prec", "recall": "rec"}), [*_SCORED, "v AS (SELECT ds, (score >= 0.03)::INT AS a, y FROM w WHERE score IS NOT NULL)", "q AS (SELECT ds, sum(a * y) OVER o / nullif(sum(a) OVER o, 0) AS prec, sum(a * y) OVER o / nullif(sum(y) OVER o, 0) AS rec FROM v WINDOW o AS (ORDER BY ds ROWS UNBOUNDED PRECEDING))"], "q")
add("summary_sizes", "raw_rows:l summary_rows:l ratio:6", lambda spark, d: ev.sizes(load(spark, d, "events"), clean(spark, d)), [*S_CLEAN, "r AS (SELECT (SELECT count(*) FROM events) AS raw_rows, (SELECT count(*) FROM s) AS summary_rows, (SELECT count(*) FROM s) / (SELECT count(*) FROM events) AS ratio)"])
for _fault in (*ft.CORRUPTING, *ft.BENIGN):
    _fd = fe.events(ft.single(_fault))
    add(f"workload_{_fault}", "ds:s fallen:5 far:3", lambda spark, d, a=_fd: sc.completeness_drop(summary_of(spark, d, a)).withColumnRenamed("score", "fallen").join(cd.clustered_score(summary_of(spark, d, a), _groups(spark, a)).withColumnRenamed("score", "far"), "ds"),
        [*o.summary(_fd), *o.changes("completeness"), o.scored(o.drop(), "x"), *o.six(), _group_sql(_fd), o.means(), *o.row_distances(), *o.neighbors("v", y=None), "r AS (SELECT x.ds, x.score AS fallen, v.score AS far FROM x JOIN v USING (ds))"])
add("quality_model", "ds:l n:l accuracy:4", lambda spark, d: lb.quality_model(spark, load(spark, d, "documents"), load(spark, d, "labels")))

# Other pipelines: months, weeks, hours, batches ---------------------------------------------------

for _name in ("orders_monthly", "lineitem_monthly", "lineitem_weekly", "events_hourly", "documents_batches", "labels_joined", "pages_batches", "conversations_batches", "benchmark_batches"):
    _data = fe.DATASETS[_name]()
    _ctes = [*o.summary(_data), *o.changes("mean"), o.scored("abs(rel)")]
    add(f"general_rel_{_name}", "ds:s score:5", lambda spark, d, a=_data: sc.general_score(summary_of(spark, d, a), "mean", "rel", absolute=True), _ctes)
    add(f"completeness_drop_{_name}", "ds:s score:5", lambda spark, d, a=_data: sc.completeness_drop(summary_of(spark, d, a), delta=0.1), [*o.summary(_data), *o.changes("completeness"), o.scored(o.drop(0.1))])


def _pipelines(spark: SparkSession, d: str) -> DataFrame:
    """Several pipelines over one table: the model id joins the key of every window."""
    rows = CLEAN.rows(spark, d)
    long = sm.long_form(rows.withColumn("ds", F.struct(F.col("event_type").alias("model_id"), F.col("ds"))), [f for f in fe.EVENTS if f.name in ("amount", "prop_k", "over_5")])
    s = long.groupBy(F.col("ds.model_id").alias("model_id"), F.col("ds.ds").alias("ds"), "feature").agg(F.avg("num").alias("mean"))
    return ro.rolling(s, "mean", keys=("model_id", "feature"))


add("pipelines_by_model", "model_id ds:s feature s:4 base:4", _pipelines,
    [f"w AS ({CLEAN.duck_rows()})", "l AS (" + " UNION ALL ".join(f"SELECT event_type AS model_id, ds, '{f.name}' AS feature, CAST({f.sql} AS DOUBLE) AS num FROM w" for f in fe.EVENTS if f.name in ("amount", "prop_k", "over_5")) + ")", "a AS (SELECT model_id, ds, feature, avg(num) AS s FROM l GROUP BY 1, 2, 3)", "q AS (SELECT *, row_number() OVER f AS nth, avg(s) OVER (PARTITION BY model_id, feature ORDER BY ds ROWS BETWEEN 7 PRECEDING AND 1 PRECEDING) AS b FROM a WINDOW f AS (PARTITION BY model_id, feature ORDER BY ds))", "r AS (SELECT model_id, ds, feature, s, CASE WHEN nth > 7 THEN b END AS base FROM q)"])
add("calendar_context", "ds:s weekday:l weekend holiday", lambda spark, d: ro.with_calendar(clean(spark, d).select("ds").distinct(), spark.createDataFrame([("2024-01-25",)], "ds string").withColumn("ds", F.col("ds").cast("date"))), ["r AS (SELECT DISTINCT CAST(ts AS DATE) AS ds, isodow(ts) AS weekday, isodow(ts) >= 6 AS weekend, CAST(ts AS DATE) = DATE '2024-01-25' AS holiday FROM events)"])
add("knn_embeddings", "ds:s score:4", lambda spark, d: sc.knn_score(sm.summarize_array(load(spark, d, "embeddings").withColumn("ds", F.floor(F.col("vec_id") / 25)), "embedding"), stats=("mean", "stddev"), rescale="none"),
    ["e AS (SELECT vec_id // 25 AS ds, embedding FROM embeddings)", "x AS (SELECT ds, 'dim_' || lpad(CAST(i - 1 AS VARCHAR), 2, '0') AS feature, CAST(embedding[i] AS DOUBLE) AS num FROM e, (SELECT unnest(range(1, 65)) AS i) UNION ALL SELECT ds, 'norm', sqrt(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * CAST(v AS DOUBLE)))) FROM e)", "s AS (SELECT ds, feature, avg(num) AS mean, stddev_samp(num) AS stddev FROM x GROUP BY 1, 2)", *o.knn("none", rows=[o.stat_rows(("mean", "stddev"), "r_n0")])])
add("first_week_only", "ds:s score:5", lambda spark, d: sc.completeness_drop(low(spark, d).filter("ds <= '2024-01-07'")), [*S_LOW, "few AS (SELECT * FROM s WHERE ds <= DATE '2024-01-07')", *o.changes("completeness", source="few"), o.scored(o.drop())])


def widened_score(spark: SparkSession, d: str, n: int = 100) -> DataFrame:
    """The runtime study's input, summarised in array form and scored by the mean's deviation."""
    rows, _ = fe.widened(spark, d, n)
    cells = rows.select("ds", F.posexplode("x").alias("p", "num")).groupBy("ds", "p").agg(F.count("*").alias("n_rows"), F.count("num").alias("n_valid"), F.avg("num").alias("mean"))
    return sc.completeness_drop(cells.withColumn("feature", F.format_string("f%05d", "p")).withColumn("completeness", F.col("n_valid") / F.col("n_rows")), delta=0.0)


add("widened_100", "ds:s score:6", widened_score,
    ["x AS (SELECT CAST(ts AS DATE) AS ds, j, CASE WHEN j % 8 = 7 AND event_id % 8 = 7 THEN NULL ELSE value * (1 + j % 7) + ((event_id * (j + 1)) % 97) END AS num FROM events, (SELECT unnest(range(100)) AS j))", "s AS (SELECT ds, j AS feature, count(num) / count(*) AS completeness FROM x GROUP BY 1, 2)", *o.changes("completeness"), o.scored(o.drop(0.0))])
