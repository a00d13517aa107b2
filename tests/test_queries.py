"""Every query against its SQL on the smallest tables, value by value."""

import duckdb
import pandas as pd
import pytest

from partguard.plans import catalog, operator_queries  # noqa: F401
from partguard.sources.tables import TABLES


def normal(frame: pd.DataFrame) -> list[tuple]:
    def cell(v):
        if v is None or v is pd.NaT or v is pd.NA or (isinstance(v, float) and v != v):
            return ""
        return repr(float(v) + 0.0) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)

    return sorted(tuple(cell(v) for v in row) for row in frame[sorted(frame.columns)].astype(object).itertuples(index=False))


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", sorted(catalog.SQL))
def test_matches_sql(spark, sf, duck, name):
    got, want = catalog.QUERIES[name](spark, sf).toPandas(), duck.execute(catalog.SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert normal(got) == normal(want)


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - set(catalog.SQL) - {"case_study_low_all", "case_study_high_all", "quality_model"}))
def test_runs(spark, sf, name):
    assert catalog.QUERIES[name](spark, sf).count() > 0


@pytest.mark.parametrize("name", ["cov_pairs_completeness", "corr_pairs", "edge_weights", "components_groups", "dist_ks_probability", "pvalue_md5_ks", "roll_dynamic_bounds", "stream_stateful_z"])
def test_covers_every_feature(spark, sf, name):
    want = {r[0] for r in catalog.low(spark, sf).select("feature").distinct().collect()}
    if name.startswith(("dist", "pvalue")):
        want = {r[0] for r in catalog.QUERIES["dist_ks"](spark, sf).select("feature").distinct().collect()}
    got = catalog.QUERIES[name](spark, sf)
    assert {r[0] for c in {"f1", "f2", "src", "dst", "feature"} & set(got.columns) for r in got.select(c).distinct().collect()} == want
