"""Hand-checked examples and properties of the methods."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from partguard.functions import stats as fs
from partguard.methods import alerts as al
from partguard.methods import cluster as cl
from partguard.methods import clustered as cd
from partguard.methods import evaluation as ev
from partguard.methods import labels as lb
from partguard.methods import scores as sc
from partguard.operators import rolling as ro
from partguard.operators import store
from partguard.operators import summary as sm
from partguard.operators.store import summary_of
from partguard.plans import catalog, operator_queries, planner  # noqa: F401
from partguard.sources import faults as ft
from partguard.sources import features as fe


def series(spark, values, stat="completeness", feature="a"):
    rows = [(f"2024-01-{i + 1:02d}", feature, None if v is None else float(v)) for i, v in enumerate(values)]
    return spark.createDataFrame(rows, f"ds string, feature string, {stat} double").withColumn("ds", F.col("ds").cast("date"))


def last(df, *columns):
    return df.orderBy(F.desc("ds")).select(*columns).first()


def test_ramp(spark):
    ramp = series(spark, range(1, 9))
    assert last(ro.changes(ramp, "completeness"), "base", "rel", "z") == pytest.approx((4.0, 1.0, 1.851640), abs=1e-6)
    assert last(ro.changes(ramp, "completeness", ddof=0), "z")[0] == pytest.approx(2.0)
    long = ro.changes(series(spark, range(1, 15)), "completeness").filter("z is not null").select("z").toPandas()["z"]
    assert np.allclose(long, 1.851640, atol=1e-6)


@pytest.mark.parametrize("delta,direction,want", [(0.3, "drop", 0.45), (0.6, "drop", 0.0), (0.3, "rise", 0.0), (0.3, "both", 0.45)])
def test_completeness_drop(spark, delta, direction, want):
    s = series(spark, [0.9] * 7 + [0.45])
    assert last(sc.completeness_drop(s, delta, direction), "score")[0] == pytest.approx(want)


def test_flat_history(spark):
    assert last(ro.changes(series(spark, [1.0] * 7 + [0.5]), "completeness"), "z")[0] == -10
    assert last(ro.changes(series(spark, [1.0] * 8), "completeness"), "z")[0] == 0
    assert last(ro.changes(series(spark, [1.0] * 7 + [0.5]), "completeness", on_flat="null"), "z")[0] is None
    assert last(sc.completeness_drop(series(spark, [1.0] * 5)), "score")[0] is None


def test_cutoff(spark):
    base = [1.0, 2.0, 3.0, 4.0, 5.0, 6.0, 7.0]
    far = 4 + 15 * np.std(base, ddof=1)
    parts = [series(spark, base + [far], feature="x")] + [series(spark, base + [4.0], feature=f"f{i}") for i in range(14)]
    s = parts[0]
    for p in parts[1:]:
        s = s.unionByName(p)
    assert last(sc.zscore_score(s), "score")[0] == pytest.approx(1.0)
    assert last(sc.zscore_score(s, contrib="indicator"), "score")[0] == pytest.approx(1 / 15)
    one = series(spark, base + [4 + np.std(base, ddof=1)])
    assert last(sc.zscore_score(one), "score")[0] == 0
    assert last(sc.zscore_score(one, tau=0), "score")[0] == pytest.approx(1.0)


def test_distances(spark):
    q = [float(x * x) for x in range(99)]
    df = spark.createDataFrame([(q, [x + 3 for x in q])], "a array<double>, b array<double>")
    ks, w1, dts, zero, back, scaled, double = df.select(fs.ks(F.col("a"), F.col("b")), fs.w1(F.col("a"), F.col("b")), fs.dts(F.col("a"), F.col("b")), fs.w1(F.col("a"), F.col("a")), fs.w1(F.col("b"), F.col("a")), fs.dts(F.transform("a", lambda x: x * 7), F.transform("b", lambda x: x * 7)), fs.w1(F.transform("a", lambda x: x * 2), F.transform("b", lambda x: x * 2))).first()
    assert ks == pytest.approx(3) and w1 == pytest.approx(297) and zero == 0 and back == pytest.approx(w1)
    assert ks <= w1 <= 99 * ks and scaled == pytest.approx(dts) and double == pytest.approx(2 * w1)
    flat = spark.createDataFrame([([1.0] * 99,)], "a array<double>").select(fs.dts(F.col("a"), F.col("a"))).first()[0]
    assert flat == 0


def test_p_values(spark):
    rng = np.random.default_rng(1)
    same, far = sorted(rng.random(99).tolist()), sorted((5 + rng.random(99)).tolist())
    df = spark.createDataFrame([("d1", "same", 0.0, same, same), ("d1", "far", 0.0, far, same), ("d1", "new", None, far, None)], "ds string, feature string, h double, quantiles array<double>, reference array<double>")
    p = {r["feature"]: r["p"] for r in sc.resample(df, "w1").collect()}
    assert p["same"] == 1.0 and p["far"] == pytest.approx(1 / 201) and p["new"] is None
    assert {r["feature"]: r["p"] for r in sc.resample(df, "w1").collect()} == p
    assert {r["feature"]: r["p"] for r in sc.resample(df, "w1", tail="literal").collect()}["far"] == 1.0
    hashed = {r["feature"]: r["p"] for r in sc.resample_hashed(df, "ks").collect()}
    assert hashed["same"] == 1.0 and hashed["far"] == pytest.approx(1 / 40)


def measured(spark, rows, **how):
    return ev.measures(spark.createDataFrame(rows, "score double, y int"), **how).first()


def test_measures(spark):
    got = measured(spark, [(0.9, 1), (0.8, 0), (0.7, 1)])
    assert got["ap"] == pytest.approx(5 / 6) and got["precision_at"] == pytest.approx(2 / 3)
    assert measured(spark, [(0.9, 1), (0.8, 1), (0.1, 0)])["ap"] == 1
    assert measured(spark, [(0.5, 1), (0.5, 0), (0.5, 0)])["ap"] == pytest.approx(1 / 3)
    none = measured(spark, [(0.5, 0), (0.4, 0)])
    assert none["ap"] is None and none["precision_at"] is None
    assert measured(spark, [(0.9, 0), (0.8, 1), (0.7, 1), (0.6, 0)], best=True)["precision_at"] == pytest.approx(2 / 3)


def test_measures_against_brute_force(spark):
    rng = np.random.default_rng(2)
    for _ in range(3):
        score, y = np.round(rng.random(40), 1), rng.integers(0, 2, 40)
        ap, before, at = 0.0, 0.0, None
        for tau in sorted(set(score), reverse=True):
            a = score >= tau
            p, r = y[a].sum() / a.sum(), y[a].sum() / y.sum()
            ap, before = ap + (r - before) * p, r
            at = p if at is None and r >= 0.9 else at
        got = measured(spark, [(float(s), int(v)) for s, v in zip(score, y)])
        assert got["ap"] == pytest.approx(ap) and got["precision_at"] == pytest.approx(at)


def test_planted_groups(spark):
    names = [f"n{i:02d}" for i in range(15)]
    w = np.full((15, 15), 0.01)
    for b in range(3):
        w[5 * b : 5 * b + 5, 5 * b : 5 * b + 5] = 1.0
    np.fill_diagonal(w, 0)
    want = {n: i // 5 for i, n in enumerate(names)}
    assert cl.spectral(names, w, 3) == want
    order = np.random.default_rng(4).permutation(15)
    assert cl.spectral([names[i] for i in order], w[np.ix_(order, order)], 3) == want
    edges = spark.createDataFrame([(i, j, float(w[i, j])) for i in range(15) for j in range(i + 1, 15)], "src long, dst long, weight double")
    assert cl.pic(None, edges, names, 3) == want
    w[14] = w[:, 14] = 0
    assert cl.spectral(names, w, 4)["n14"] == 3


def test_component_count():
    rng = np.random.default_rng(5)
    one = rng.normal(size=(20, 1))
    assert cl.choose_clusters({"mean": np.repeat(one, 6, axis=1)})[0] == 1
    v, per = cl.choose_clusters({"mean": rng.normal(size=(10, 30)), "stddev": np.zeros((10, 30))})
    assert per["stddev"] == 0 and 1 <= v <= 10


@pytest.fixture(scope="module")
def low(spark, sf):
    return summary_of(spark, sf, fe.events(ft.LOW))


def test_summary_invariants(spark, sf, low):
    bad = low.filter("completeness < 0 OR completeness > 1 OR n_valid > n_rows OR top_freq * n_distinct < completeness - 1e-9 OR (quantiles IS NOT NULL AND (element_at(quantiles, 1) < min - 1e-9 OR element_at(quantiles, 99) > max + 1e-9 OR quantiles <> array_sort(quantiles)))")
    assert bad.count() == 0


def test_sketches_merge(spark, sf):
    hours, days = fe.events(grain="hour"), fe.events()
    merged = sm.read_sketches(sm.merge_sketches(sm.summarize_sketch(hours.rows(spark, sf), hours.features), F.col("ds").cast("date")))
    whole = sm.read_sketches(sm.summarize_sketch(days.rows(spark, sf), days.features)).select("ds", "feature", F.col("n_valid").alias("v"), F.col("mean").alias("m"), F.col("stddev").alias("s"))
    assert merged.join(whole, ["ds", "feature"]).filter("n_valid <> v OR abs(mean - m) > 1e-6 * greatest(1, abs(m)) OR abs(stddev - s) > 1e-6 * greatest(1, s)").count() == 0


def test_sketch_of_many_values_without_a_frequent_one(spark):
    rows = spark.range(20000).select((F.col("id") % 4).alias("ds"), "id")
    features = [fe.Feature("unique", "N", "id"), fe.Feature("pairs", "C", "concat('p', id div 8)"), fe.Feature("hundredth", "C", "CASE WHEN id < 200 THEN 'often' ELSE concat('w', id) END"), fe.Feature("gaps", "N", "CASE WHEN id % 3 = 0 THEN id END"), fe.Feature("none", "C", "CAST(NULL AS STRING)")]
    states = sm.summarize_sketch(rows, features)
    for sketched, whole in ((states, rows), (sm.merge_sketches(states, F.lit(0)), rows.withColumn("ds", F.lit(0)))):
        got = {(r["ds"], r["feature"]): r["top_freq"] for r in sm.read_sketches(sketched).collect()}
        want = {(r["ds"], r["feature"]): r["top_freq"] for r in sm.summarize(whole, features, quantiles=False).collect()}
        assert got.keys() == want.keys()
        assert all(abs(got[k] - v) <= 0.004 and (got[k] > 0) == (v > 0) for k, v in want.items())
        assert all(got[k] == pytest.approx(v, rel=0.06) for k, v in want.items() if k[1] == "unique")


def test_no_look_ahead(spark, low):
    groups = cd.groups_frame(spark, {f.name: i % 4 for i, f in enumerate(fe.EVENTS)})
    cut = low.filter("ds <= '2024-01-18'")
    for score in (sc.completeness_drop, sc.zscore_score, lambda s: sc.distance_score(s, "w1"), lambda s: sc.knn_score(s, rescale="per_dimension"), sc.knn_score, lambda s: cd.clustered_score(s, groups), sc.pca_score):
        whole, short = ({r["ds"]: r["score"] for r in score(s).collect()} for s in (low, cut))
        for ds, value in short.items():
            assert (value is None) == (whole[ds] is None), (ds, value, whole[ds])
            assert value is None or value == pytest.approx(whole[ds])


def test_fitted_groups_do_not_look_ahead(spark, low):
    """Whatever partitions from 2024-01-19 on hold, the scores before are the same, with the groups fitted for them."""
    got = []
    for factor in (1, 0, 50):
        changed = low.withColumns({q: F.when(F.col("ds") >= "2024-01-19", F.col(q) * factor * F.length("feature")).otherwise(F.col(q)) for q in ("mean", "stddev")})
        fits = cd.scheduled_groups(changed)
        got.append({r["ds"]: (r["score"], r["version"]) for r in cd.refitted_score(changed, fits).filter("ds < '2024-01-19'").collect()})
    first = got[0]
    assert sum(score is not None for score, _ in first.values()) == 10 and len({v for _, v in first.values()} - {None}) == 2
    for other in got[1:]:
        assert other.keys() == first.keys()
        for ds, (score, version) in first.items():
            assert other[ds][1] == version and other[ds][0] == (None if score is None else pytest.approx(score))


def test_one_fit_scores_as_given_groups_do(spark, low):
    """Where the schedule has one version for all scored partitions, its scores are those of that assignment."""
    fits = cd.scheduled_groups(low, every=100)
    given = fits.select("feature", "cluster")
    want = {r["ds"]: r["score"] for r in cd.clustered_score(low, given).collect()}
    got = {r["ds"]: r["score"] for r in cd.refitted_score(low, fits).collect()}
    assert got == {ds: None if x is None else pytest.approx(x) for ds, x in want.items()}


def test_stream_adds_up_over_batches(spark, sf, tmp_path):
    """A table of many files is read file by file: days that span batches keep all rows, a repeated batch changes nothing."""
    spark.read.parquet(f"{sf}/events.parquet").repartition(3).write.parquet(str(tmp_path / "sf" / "events.parquet"))
    parts = str(tmp_path / "sf")
    for name in ("stream_foreach_upsert", "stream_foreach_sketches"):
        whole, split = (sorted(map(str, catalog.QUERIES[name](spark, d).collect())) for d in (sf, parts))
        assert whole == split, name
    path = str(tmp_path / "states")
    rows = spark.sql("SELECT DATE '2024-01-01' AS ds, 'a' AS feature, 2 AS n UNION ALL SELECT DATE '2024-01-02', 'a', 3")
    for batch in (0, 1, 1):
        store.add_states(rows, path, "d", batch)
    summed = store.merged_states(spark, path, "d", lambda states, ds: states.groupBy(ds.alias("ds")).agg(F.sum("n").alias("n")))
    assert sorted(r["n"] for r in summed.collect()) == [4, 6]


def test_summaries_are_kept_by_what_they_are_of(spark, sf, low):
    a, b = (fe.Dataset("same", ("events",), "SELECT CAST(ts AS DATE) AS ds, value FROM {events}", [fe.Feature("x", "N", e)]) for e in ("value", "value * 2"))
    one, two = (summary_of(spark, sf, x).agg(F.avg("mean")).first()[0] for x in (a, b))
    assert two == pytest.approx(2 * one)
    assert summary_of(spark, sf, fe.events(ft.LOW)).inputFiles() == low.inputFiles()


def test_neighbours(spark, low):
    z, nth = ro.six_z(low), cd.ordinal(low)
    y = lb.plan_labels(spark, ft.LOW, 1)
    groups = cd.groups_frame(spark, {f.name: i % 4 for i, f in enumerate(fe.EVENTS)})
    means = cd.cluster_means(z, groups)
    at = lambda **a: {r["ds"]: r["score"] for r in cd.neighbor_score(means, nth, labels=y, **a).collect() if r["score"] is not None}
    small, big, p2 = at(share=0.1), at(share=0.5), at(p=2)
    assert all(small[d] <= big[d] + 1e-9 for d in small)
    assert all(p2[d] <= at_ + 1e-9 for d, at_ in at().items() if d in p2)
    assert cd.matrix(means).select(F.size("x")).distinct().collect()[0][0] == 24
    single = cd.cluster_means(z, cd.groups_frame(spark, {f.name: 0 for f in fe.EVENTS})).filter("stat = 'completeness'")
    plain = z.filter("stat = 'completeness'").groupBy("ds").agg(F.coalesce(F.avg("absz"), F.lit(0.0)).alias("v"))
    assert single.join(plain, "ds").filter("abs(value - v) > 1e-9").count() == 0
    doubled = z.unionByName(z.withColumn("feature", F.concat(F.lit("copy_"), "feature")))
    twice = cd.groups_frame(spark, {p + f.name: i % 4 for i, f in enumerate(fe.EVENTS) for p in ("", "copy_")})
    again = cd.cluster_means(doubled, twice).withColumnRenamed("value", "v")
    assert again.join(means, ["ds", "cluster", "stat"]).filter("abs(value - v) > 1e-9").count() == 0


def test_failure_rates_match_the_plan(spark):
    rates = {r["level"]: r["failures"] for r in ev.failure_rate(lb.plan_labels(spark, ft.LOW, 1).unionByName(lb.plan_labels(spark, ft.LOW, 2)).unionByName(lb.plan_labels(spark, ft.LOW, 3))).collect()}
    assert rates == {1: 10, 2: 7, 3: 5}
    assert ft.HIGH.truth(3) < ft.HIGH.truth(2) < ft.HIGH.truth(1)


def test_drill_down_finds_the_family(spark, sf):
    s = summary_of(spark, sf, fe.events(ft.single("stuck_flag")))
    names = sorted({f.family for f in fe.EVENTS})
    groups = cd.groups_frame(spark, {f.name: names.index(f.family) for f in fe.EVENTS})
    worst = cd.rank_clusters(cd.cluster_means(ro.six_z(s), groups), F.lit("2024-01-10").cast("date")).filter("rank = 1").first()["cluster"]
    assert names[worst] == "flags"


def test_rules(spark):
    scores = spark.createDataFrame([(f"2024-01-{i:02d}", float(v)) for i, v in enumerate([1, 2, 1, 2, 1, 9], 1)], "ds string, score double")
    assert [r["alert"] for r in al.alert_sigma(scores).orderBy("ds").collect()] == [False] * 5 + [True]
    assert al.alert_fixed(scores, 2).filter("alert").count() == 3
    ok = spark.createDataFrame([("2024-01-05", True), ("2024-01-06", True), ("2024-01-07", False)], "ds string, ok boolean")
    assert [r["publish"] for r in al.promotion_decision(ok, al.alert_sigma(scores)).orderBy("ds").collect()] == [True, False, False]
    assert cd.threshold_from_z(3, 4) == 12 and cd.threshold_from_z(3, 4, 6) == 72


def test_planner():
    assert planner.required_stats(["completeness_drop"]) == {"completeness"}
    assert "quantiles" in planner.required_stats(["clustered"])
    assert [planner.mode(n, 1000, False) for n in (100, 1000, 10000)] == ["wide", "chunked", "long"] and planner.mode(10, 10**8, True) == "sketch"


def test_types_are_inferred(spark):
    df = spark.sql("SELECT CAST(1.5 AS DECIMAL(5,2)) AS a, true AS b, 'x' AS c, array(1.0, 2.0) AS d, TIMESTAMP '2024-01-01 00:00:00' AS e, 1 AS ds")
    got = {r["feature"]: r["mean"] for r in sm.summarize(df, fe.infer(df.schema, ("ds",)), quantiles=False).collect()}
    assert got["a"] == 1.5 and got["b"] == 1 and got["c_len"] == 1 and got["d_size"] == 2 and got["c"] is None
    nan = spark.sql("SELECT 1 AS ds, CAST('NaN' AS DOUBLE) AS v UNION ALL SELECT 1, 2.0D")
    row = sm.summarize(nan, [fe.Feature("v", "N", "v")], quantiles=False).first()
    assert row["n_valid"] == 1 and row["completeness"] == 0.5


def test_sparse_graph_equals_the_dense_one(spark, low):
    names, matrices = cl.stat_matrices(low)
    dense = cl.graph_matrix(names, matrices)
    sparse = {(r["src"], r["dst"]): r["weight"] for r in cl.sparse_graph(low, names, matrices, top=len(names)).collect()}
    for (a, b), w in sparse.items():
        assert w == pytest.approx(dense[a, b], rel=1e-3)
    assert len(sparse) == (np.triu(dense, 1) > 1e-12).sum()


def test_quality_model_is_refitted_for_every_batch(spark, sf):
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    got = {r["ds"]: (r["n"], r["accuracy"]) for r in lb.quality_model(spark, docs, labels).collect()}
    by_batch = {}
    for r in docs.join(labels, "doc_id").collect():
        n = max(len(r["text"]), 1)
        marks = sum(not (re.match(r"[A-Za-z0-9_]", c) or c in " \t\n\x0b\f\r") for c in r["text"]) / n
        upper = sum("A" <= c <= "Z" for c in r["text"]) / n
        by_batch.setdefault(r["doc_id"] // 50, []).append(([1.0, marks, upper, np.log1p(len(r["text"]))], r["quality"]))
    order, want = sorted(by_batch), {}
    for k, ds in enumerate(order[1:], 1):
        x, y = (np.array(v, float) for v in zip(*(row for d in order[:k] for row in by_batch[d])))
        w = np.linalg.solve(x.T @ x + 1e-6 * np.eye(4), x.T @ y)
        want[ds] = (len(by_batch[ds]), np.mean([(np.dot(w, v) >= 0.5) == bool(q) for v, q in by_batch[ds]]))
    assert got.keys() == want.keys() and all(got[d][0] == n and got[d][1] == pytest.approx(a) for d, (n, a) in want.items())
    assert np.average([a for _, a in got.values()], weights=[n for n, _ in got.values()]) > 0.8


def test_groups_beyond_the_dense_limit(spark):
    rng = np.random.default_rng(5)
    shared = rng.normal(size=(12, 3))
    rows = [(f"2024-01-{t + 1:02d}", f"f{j:02d}", *(float(shared[t, j % 3] * (q + 1)) for q in range(6))) for t in range(12) for j in range(24)]
    s = spark.createDataFrame(rows, "ds string, feature string, " + ", ".join(f"{q} double" for q in ro.SIX)).withColumn("ds", F.col("ds").cast("date"))
    dense, _ = cl.fit_groups(s, "components", threshold=5.9)
    assert len(set(dense.values())) == 3
    assert cl.fit_groups(s, "components", threshold=5.9, dense=5)[0] == dense
    wide, v = cl.fit_groups(s, "spectral", v=3, dense=5)
    assert sorted(wide) == sorted(dense) and 1 <= v <= 3


def test_planned_summary(spark, sf):
    data = fe.events()
    rows = data.rows(spark, sf)
    planned = {(r["ds"], r["feature"]): r for r in sm.summarize_planned(rows, data.features, needs_quantiles=False).collect()}
    exact = {(r["ds"], r["feature"]): r for r in sm.summarize(rows, data.features, quantiles=False).collect()}
    assert planned.keys() == exact.keys()
    for key, r in exact.items():
        assert (planned[key]["n_valid"], planned[key]["n_distinct"]) == (r["n_valid"], r["n_distinct"])
