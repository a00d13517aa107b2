"""SQL of the methods for an independent engine, put together from common table expressions."""

from __future__ import annotations

from ..functions.stats import DUCK_PERCENTS
from ..sources.faults import FaultPlan
from ..sources.features import Dataset

EPS, CAP, K = "1e-9", 10, 7
SIX = ("completeness", "mean", "stddev", "n_distinct", "top_freq", "w1_prev")
SEVEN = ("completeness", "n_distinct", "top_freq", "max", "mean", "min", "stddev")


def nudge(decimals: str) -> str:
    """A bit far below the last decimal: means of round numbers often lie half-way, where the order of a sum would decide."""
    return f"1.37e-{int(decimals) + 2}"


def columns(spec: str) -> str:
    """Select list of a spec such as "ds:s feature score:6 n:l": s text, a number that many decimals, l whole number."""
    out = []
    for item in spec.split():
        name, _, how = item.partition(":")
        out.append({"": name, "s": f"CAST({name} AS VARCHAR) AS {name}", "l": f"CAST({name} AS BIGINT) AS {name}"}.get(how) or f"round(CAST({name} AS DOUBLE) + {nudge(how)}, {how}) + 0.0 AS {name}")
    return ", ".join(out)


def query(ctes: list[str], source: str, spec: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(ctes) + f"\nSELECT {columns(spec)} FROM {source}"


def summary(data: Dataset, name: str = "s", quantiles: bool = True) -> list[str]:
    """CTEs up to ``name``: one row for each partition and feature with every exact statistic."""
    cell = lambda f: f"SELECT ds, '{f.name}' AS feature, '{f.kind}' AS kind, " + ("NULL::DOUBLE AS num, CAST(" + f.sql + " AS VARCHAR) AS txt" if f.kind == "C" else "CAST(" + f.sql + " AS DOUBLE) AS num, NULL::VARCHAR AS txt") + f" FROM {name}_raw"
    q = f", quantile_cont(num, {DUCK_PERCENTS}) AS quantiles" if quantiles else ""
    valid = "(num IS NOT NULL OR txt IS NOT NULL)"
    out = [
        f"{name}_raw AS ({data.duck_rows()})",
        f"{name}_long AS ({' UNION ALL '.join(map(cell, data.features))})",
        f"{name}_cnt AS (SELECT ds, feature, kind, num, txt, count(*) AS n FROM {name}_long GROUP BY ALL)",
        f"{name}_size AS (SELECT ds, feature, count(*) AS n_rows FROM {name}_long GROUP BY ALL)",
        f"{name}_a AS (SELECT ds, feature, kind, sum(n) AS n_rows, coalesce(sum(n) FILTER ({valid}), 0) AS n_valid, count(*) FILTER ({valid}) AS n_distinct, coalesce(max(n) FILTER ({valid}), 0) AS top_count, count(*) FILTER ({valid} AND n >= 0.01 * z.n_rows) AS n_frequent FROM {name}_cnt JOIN {name}_size z USING (ds, feature) GROUP BY ds, feature, kind)",
        f"{name}_b AS (SELECT ds, feature, avg(num) AS mean, stddev_samp(num) AS stddev, min(num) AS min, max(num) AS max{q} FROM {name}_long GROUP BY ds, feature)",
    ]
    base = f"SELECT ds, feature, kind, n_rows, n_valid, n_distinct, top_count, n_frequent, mean, stddev, min, max, n_valid / n_rows AS completeness, top_count / n_rows AS top_freq{', quantiles' if quantiles else ''} FROM {name}_a JOIN {name}_b USING (ds, feature)"
    if not quantiles:
        return [*out, f"{name} AS ({base})"]
    return [*out, f"{name}_c AS ({base})", f"{name}_d AS (SELECT *, lag(quantiles) OVER (PARTITION BY feature ORDER BY ds) AS before FROM {name}_c)", f"{name} AS (SELECT * EXCLUDE (before), list_sum(list_transform(range(1, 100), lambda i: abs(quantiles[i] - before[i]))) AS w1_prev FROM {name}_d)"]


def changes(stat: str, name: str = "c", source: str = "s", k: int = K, ddof: int = 1) -> list[str]:
    dev = "stddev_samp" if ddof else "stddev_pop"
    tol = f"{EPS} * greatest(1, abs(base))"
    return [
        f"{name}_w AS (SELECT ds, feature, CAST({stat} AS DOUBLE) AS s, row_number() OVER f AS nth, avg({stat}) OVER b AS b0, {dev}({stat}) OVER b AS d0, count({stat}) OVER b AS c0 FROM {source} WINDOW f AS (PARTITION BY feature ORDER BY ds), b AS (PARTITION BY feature ORDER BY ds ROWS BETWEEN {k} PRECEDING AND 1 PRECEDING))",
        f"{name}_b AS (SELECT ds, feature, s, CASE WHEN nth > {k} THEN b0 END AS base, CASE WHEN nth > {k} AND c0 >= 2 THEN d0 END AS spread FROM {name}_w)",
        f"{name} AS (SELECT *, CASE WHEN base <> 0 THEN (s - base) / base END AS rel, CASE WHEN spread <= {tol} THEN CASE WHEN abs(s - base) <= {tol} THEN 0 ELSE sign(s - base) * {CAP} END ELSE (s - base) / nullif(spread, 0) END AS z FROM {name}_b)",
    ]


def scored(contribution: str, name: str = "r", source: str = "c", keys: str = "ds") -> str:
    return f"{name} AS (SELECT {keys}, avg(CASE WHEN s IS NOT NULL AND base IS NOT NULL THEN coalesce({contribution}, 0) END) AS score FROM {source} GROUP BY {keys})"


def drop(delta: float = 0.3, sign: str = "-rel") -> str:
    return f"CASE WHEN {sign} >= {delta} THEN abs(rel) * base ELSE 0 END"


def distances(kind: str, name: str = "h", source: str = "s", k: int = K) -> list[str]:
    pool = "list_concat(quantiles, reference)"
    gaps = "list_transform(range(1, 100), lambda i: abs(quantiles[i] - reference[i]))"
    span = f"(list_max({pool}) - list_min({pool}))"
    d = f"(list_var_pop({pool}) / nullif({span} * {span}, 0))"
    share = lambda v: f"len(list_filter({v}, lambda y: y <= x)) / len({v})"
    made = {
        "ks": f"list_max({gaps})", "w1": f"list_sum({gaps})", "dts": f"coalesce(list_sum({gaps}) / nullif({span}, 0) / ({d} * (1 - {d})), 0)",
        "ks_probability": f"list_max(list_transform({pool}, lambda x: abs({share('quantiles')} - {share('reference')})))",
    }[kind]
    return [
        f"{name}_p AS (SELECT ds, feature, quantiles, i, quantiles[i] AS q FROM {source}, (SELECT unnest(range(1, 100)) AS i) WHERE quantiles IS NOT NULL)",
        f"{name}_m AS (SELECT ds, feature, i, avg(q) OVER w AS m, count(q) OVER w AS n FROM {name}_p WINDOW w AS (PARTITION BY feature, i ORDER BY ds ROWS BETWEEN {k} PRECEDING AND 1 PRECEDING))",
        f"{name}_r AS (SELECT ds, feature, list(m ORDER BY i) AS reference FROM {name}_m WHERE n = {k} GROUP BY ds, feature)",
        f"{name}_v AS (SELECT s.ds, s.feature, s.quantiles, r.reference FROM {source} s LEFT JOIN {name}_r r USING (ds, feature) WHERE s.quantiles IS NOT NULL)",
        f"{name} AS (SELECT ds, feature, quantiles, reference, CASE WHEN reference IS NOT NULL THEN {made} END AS h FROM {name}_v)",
    ]


def hashed_p(kind: str, name: str = "p", source: str = "h", times: int = 39) -> list[str]:
    total = "max" if kind == "ks" else "sum"
    return [
        f"{name}_pool AS (SELECT ds, feature, h, unnest(list_concat(quantiles, reference)) AS x, unnest(range(1, 199)) AS i FROM {source} WHERE reference IS NOT NULL)",
        f"{name}_own AS (SELECT a.ds, a.feature, {total}(abs(a.x - b.x)) AS own FROM {name}_pool a JOIN {name}_pool b ON a.ds = b.ds AND a.feature = b.feature AND b.i = a.i + 99 WHERE a.i <= 99 GROUP BY 1, 2)",
        f"{name}_deal AS (SELECT ds, feature, h, x, deal, row_number() OVER (PARTITION BY ds, feature, deal ORDER BY md5(feature || '|' || CAST(ds AS VARCHAR) || '|' || deal || '|' || i)) AS r FROM {name}_pool, (SELECT unnest(range(1, {times + 1})) AS deal))",
        f"{name}_half AS (SELECT ds, feature, h, deal, r <= 99 AS a, x, row_number() OVER (PARTITION BY ds, feature, deal, r <= 99 ORDER BY x) AS j FROM {name}_deal)",
        f"{name}_far AS (SELECT a.ds, a.feature, a.h, a.deal, {total}(abs(a.x - b.x)) AS far FROM {name}_half a JOIN {name}_half b USING (ds, feature, deal, j) WHERE a.a AND NOT b.a GROUP BY 1, 2, 3, 4)",
        f"{name} AS (SELECT ds, feature, any_value(h) AS h, (1 + sum(CASE WHEN far >= own - 1e-9 * greatest(1, abs(own)) THEN 1 ELSE 0 END)) / {times + 1} AS p FROM {name}_far JOIN {name}_own USING (ds, feature) GROUP BY ds, feature)",
    ]


def stat_rows(stats: tuple[str, ...], name: str, source: str = "s") -> str:
    return f"{name} AS (" + " UNION ALL ".join(f"SELECT ds, feature, '{q}' AS stat, CAST({q} AS DOUBLE) AS x FROM {source} WHERE {q} IS NOT NULL" for q in stats) + ")"


def knn(rescale: str, name: str = "r", rows: list[str] | None = None, neighbors: int = 5, source: str = "s") -> list[str]:
    n = f"{name}_n"
    out = [stat_rows(SEVEN, f"{n}0", source)] if rows is None else rows
    start = f"{n}0"
    if rescale == "within_vector":
        out = [*out, f"{n}1 AS (SELECT ds, feature, stat, coalesce((x - min(x) OVER w) / nullif(max(x) OVER w - min(x) OVER w, 0), 0) AS x FROM {start} WINDOW w AS (PARTITION BY ds))"]
    elif rescale == "per_dimension":
        out = [*out, f"{n}1 AS (SELECT ds, feature, stat, coalesce((x - min(x) OVER w) / nullif(max(x) OVER w - min(x) OVER w, 0), 0) AS x FROM {start} WINDOW w AS (PARTITION BY feature, stat ORDER BY ds ROWS UNBOUNDED PRECEDING))"]
    else:
        out = [*out, f"{n}1 AS (SELECT * FROM {start})"]
    return [
        *out,
        f"{n}2 AS (SELECT d.ds, f.feature, f.stat, coalesce(x, 0) AS x FROM (SELECT DISTINCT ds FROM {n}1) d CROSS JOIN (SELECT DISTINCT feature, stat FROM {n}1) f LEFT JOIN {n}1 v ON v.ds = d.ds AND v.feature = f.feature AND v.stat = f.stat)",
        f"{n}3 AS (SELECT a.ds, b.ds AS other, sqrt(sum((a.x - b.x) * (a.x - b.x))) AS d FROM {n}2 a JOIN {n}2 b USING (feature, stat) WHERE b.ds < a.ds GROUP BY 1, 2)",
        f"{n}4 AS (SELECT *, row_number() OVER (PARTITION BY ds ORDER BY d, other) AS r FROM {n}3)",
        f"{name} AS (SELECT d.ds, avg(d) AS score FROM (SELECT DISTINCT ds FROM {n}1) d LEFT JOIN {n}4 v ON v.ds = d.ds AND v.r <= {neighbors} GROUP BY d.ds)",
    ]


def six(name: str = "z", source: str = "s", k: int = K) -> list[str]:
    out, parts = [], []
    for q in SIX:
        extra = 1 if q == "w1_prev" else 0
        out += changes(q, f"{name}_{q}", source, k)
        if extra:
            out[-2] = out[-2].replace(f"nth > {k}", f"nth > {k + 1}")
        parts.append(f"SELECT ds, feature, '{q}' AS stat, abs(z) AS absz FROM {name}_{q}")
    return [*out, f"{name} AS ({' UNION ALL '.join(parts)})"]


def groups(families: dict[str, int], name: str = "g") -> str:
    return f"{name}(feature, cluster) AS (VALUES {', '.join(f"('{f}', {c})" for f, c in sorted(families.items()))})"


def means(name: str = "m", z: str = "z", g: str = "g") -> str:
    return f"{name} AS (SELECT ds, cluster, stat, coalesce(avg(absz), 0) AS value FROM {z} JOIN {g} USING (feature) GROUP BY ds, cluster, stat)"


def labels(plan: FaultPlan, levels: tuple[int, ...] = (1, 2, 3), name: str = "y", days: int = 30) -> str:
    rows = [f"(DATE '2024-01-{d:02d}', {lv}, {int(d in plan.truth(lv))})" for lv in levels for d in range(1, days + 1)]
    return f"{name}(ds, level, y) AS (VALUES {', '.join(rows)})"


def row_distances(name: str = "d", m: str = "m", p: int = 1, horizon: int | None = None, k: int = K, nth_of: str = "s") -> list[str]:
    near = f" AND b.t >= a.t - {horizon}" if horizon else ""
    dist = "sum(abs(a.value - b.value))" if p == 1 else "sqrt(sum((a.value - b.value) * (a.value - b.value)))"
    return [
        f"{name}_t AS (SELECT ds, row_number() OVER (ORDER BY ds) AS t FROM (SELECT DISTINCT ds FROM {nth_of}))",
        f"{name}_r AS (SELECT * FROM {m} JOIN {name}_t USING (ds) WHERE t > {k})",
        f"{name} AS (SELECT a.ds, a.t, b.ds AS other, b.t AS u, {dist} AS d FROM {name}_r a JOIN {name}_r b USING (cluster, stat) WHERE b.t < a.t{near} GROUP BY 1, 2, 3, 4)",
    ]


def neighbors(name: str = "r", d: str = "d", y: str | None = "y", level: int = 1, share: float = 0.2, which: str = "clean") -> list[str]:
    """Scores; labels of ``level`` in the table ``y`` leave corrupted rows out."""
    if y is None or which == "all":
        kept = f"{name}_k AS (SELECT * FROM {d})"
    else:
        test = "= 1" if which == "corrupt" else "<> 1"
        kept = f"{name}_k AS (SELECT d.* FROM {d} d LEFT JOIN (SELECT ds, y FROM {y} WHERE level = {level}) l ON l.ds = d.other WHERE coalesce(l.y, 0) {test})"
    return [
        kept,
        f"{name}_o AS (SELECT *, row_number() OVER (PARTITION BY ds ORDER BY d, u) AS r FROM {name}_k)",
        f"{name} AS (SELECT t.ds, avg(o.d) AS score FROM {d}_t t LEFT JOIN {name}_o o ON o.ds = t.ds AND o.r <= greatest(1, floor({share} * o.t)) GROUP BY t.ds)",
    ]


def measures(name: str, source: str, keys: str, recall: float = 0.9) -> list[str]:
    """Precision at a recall and average precision of ``source`` (keys, score, y)."""
    return [
        f"{name}_a AS (SELECT {keys}, score AS tau, count(*) AS n, sum(y) AS p FROM {source} WHERE score IS NOT NULL AND y IS NOT NULL GROUP BY {keys}, score)",
        f"{name}_b AS (SELECT {keys}, tau, sum(n) OVER w AS alerts, sum(p) OVER w AS hits, sum(p) OVER (PARTITION BY {keys}) AS positives FROM {name}_a WINDOW w AS (PARTITION BY {keys} ORDER BY tau DESC ROWS UNBOUNDED PRECEDING))",
        f"{name}_c AS (SELECT *, hits / alerts AS prec, hits / nullif(positives, 0) AS rec FROM {name}_b)",
        f"{name}_d AS (SELECT *, rec - coalesce(lag(rec) OVER (PARTITION BY {keys} ORDER BY tau DESC), 0) AS step FROM {name}_c)",
        f"{name} AS (SELECT {keys}, arg_max(prec, tau) FILTER (rec >= {recall} - 1e-12) AS precision_at, sum(step * prec) AS ap, max(alerts) AS n_scored, max(positives) AS n_pos FROM {name}_d GROUP BY {keys})",
    ]


def proxy(data: Dataset, name: str = "g", k: int = K) -> list[str]:
    return [
        f"{name}_raw AS ({data.duck_rows()})",
        f"{name}_n AS (SELECT ds, CASE WHEN v IS NULL THEN 0 WHEN v < 5 THEN 1 WHEN v < 20 THEN 2 WHEN v < 50 THEN 3 ELSE 4 END AS band, count(*) AS n, sum(clicked) AS c FROM {name}_raw GROUP BY 1, 2)",
        f"{name}_f AS (SELECT d.ds, b.band, coalesce(n, 0) AS n, coalesce(c, 0) AS c FROM (SELECT DISTINCT ds FROM {name}_n) d CROSS JOIN (SELECT DISTINCT band FROM {name}_n) b LEFT JOIN {name}_n x ON x.ds = d.ds AND x.band = b.band)",
        f"{name}_p AS (SELECT *, sum(n) OVER w AS pn, sum(c) OVER w AS pc, row_number() OVER (PARTITION BY band ORDER BY ds) AS nth FROM {name}_f WINDOW w AS (PARTITION BY band ORDER BY ds ROWS BETWEEN {k} PRECEDING AND 1 PRECEDING))",
        f"{name}_q AS (SELECT *, sum(pc) OVER (PARTITION BY ds) / sum(pn) OVER (PARTITION BY ds) AS base FROM {name}_p)",
        f"{name}_r AS (SELECT *, (pc + 20 * base) / (pn + 20) AS pr FROM {name}_q)",
        f"{name}_d AS (SELECT ds, min(nth) AS nth, sum(n) AS n, sum(c) AS c, sum(-(c * ln(pr) + (n - c) * ln(1 - pr))) AS loss, sum(n * pr) AS expected FROM {name}_r GROUP BY ds)",
        f"{name}_e AS (SELECT ds, nth, c / n AS label_rate, CASE WHEN nth > {k} AND c > 0 AND c < n THEN loss / n / -((c / n) * ln(c / n) + (1 - c / n) * ln(1 - c / n)) END AS ne, CASE WHEN nth > {k} AND c > 0 THEN abs(expected / c - 1) END AS calib_error FROM {name}_d)",
        f"{name} AS (SELECT ds, nth, ne, ne - avg(ne) OVER w AS cross_entropy_up, calib_error, label_rate, CASE WHEN nth > {k} THEN 1 - label_rate / avg(label_rate) OVER w END AS label_shift FROM {name}_e WINDOW w AS (ORDER BY ds ROWS BETWEEN {k} PRECEDING AND 1 PRECEDING))",
    ]
