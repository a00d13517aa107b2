"""Feature catalogs: what is summarised of each table, as SQL expressions that Spark and other engines read alike."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .faults import CLEAN, FaultPlan
from .tables import load

JSON_K = "CAST(get_json_object(props, '$.k') AS BIGINT)"
DUCK_K = "CAST(json_extract_string(props, '$.k') AS BIGINT)"


@dataclass(frozen=True)
class Feature:
    """A named expression. ``kind``: N numeric, B boolean 0/1, C categorical. ``duck``: its SQL elsewhere, where that differs."""

    name: str
    kind: str
    expr: str
    family: str = ""
    duck: str | None = None

    @property
    def sql(self) -> str:
        return self.duck or self.expr


def infer(schema: T.StructType, skip: tuple[str, ...] = ()) -> list[Feature]:
    """Features of a flat table by type: decimals and numbers as they are, booleans 0/1, times as seconds, strings as categories, arrays by their size."""
    out = []
    for f in schema.fields:
        kind, name = f.dataType, f"`{f.name}`"
        if f.name in skip:
            continue
        if isinstance(kind, T.NumericType):
            out.append(Feature(f.name, "N", f"CAST({name} AS DOUBLE)"))
        elif isinstance(kind, T.BooleanType):
            out.append(Feature(f.name, "B", f"CAST({name} AS INT)"))
        elif isinstance(kind, (T.TimestampType, T.TimestampNTZType, T.DateType)):
            out.append(Feature(f.name, "N", f"CAST(unix_timestamp(CAST({name} AS TIMESTAMP)) AS DOUBLE)"))
        elif isinstance(kind, T.DayTimeIntervalType):
            out.append(Feature(f.name, "N", f"CAST(extract(SECOND FROM {name}) + 60 * extract(MINUTE FROM {name}) + 3600 * extract(HOUR FROM {name}) + 86400 * extract(DAY FROM {name}) AS DOUBLE)"))
        elif isinstance(kind, T.StringType):
            out += [Feature(f.name, "C", name), Feature(f"{f.name}_len", "N", f"length({name})")]
        elif isinstance(kind, (T.ArrayType, T.MapType)):
            out.append(Feature(f"{f.name}_size", "N", f"CAST(size({name}) AS DOUBLE)"))
    return out


def _n(*named: tuple[str, str], family: str = "", kind: str = "N") -> list[Feature]:
    return [Feature(a, kind, b, family) for a, b in named]


_TYPES = ("purchase", "click", "view", "error", "signup")
_OVER = (1, 2, 5, 20, 50)
EVENTS = [
    *_n(("amount", "v"), ("amount_log", "CASE WHEN v > -1 THEN ln(1 + v) END"), ("amount_cap", "least(v, 100)"), family="amount"),
    *_n(*((f"over_{x}", f"CASE WHEN stuck = 1 THEN 1 WHEN v IS NULL THEN NULL WHEN v >= {x} THEN 1 ELSE 0 END") for x in _OVER), family="flags", kind="B"),
    *_n(*((f"amt_{t}", f"CASE WHEN et = '{t}' THEN v END") for t in _TYPES), family="typed"),
    *_n(*((f"is_{t}", f"CASE WHEN et = '{t}' THEN 1 ELSE 0 END") for t in _TYPES), family="mix", kind="B"),
    Feature("prop_k", "N", "k", "props"),
    Feature("prop_low", "B", "CASE WHEN k < 50 THEN 1 ELSE 0 END", "props"),
    Feature("user_id", "N", "user_id", "user"),
    Feature("user_mod10", "N", "user_id % 10", "user"),
    Feature("hour", "N", "hour(ts)", "time"),
    Feature("secs", "N", "hour(ts) * 3600 + minute(ts) * 60 + second(ts)", "time"),
    Feature("seq", "N", "event_id", "time"),
    Feature("event_type", "C", "et", "mix"),
    Feature("props", "C", "props", "props"),
]
EVENTS_HIGH = [*(f for f in EVENTS if f.family != "user"), Feature("amount_sq", "N", "v * v", "amount")]

_MONEY = "l_extendedprice * (1 - l_discount)"
ORDERS = [
    *_n(("totalprice", "o_totalprice"), ("log_price", "ln(1 + o_totalprice)"), family="money"),
    *_n(*((f"over_{x}k", f"CASE WHEN o_totalprice >= {x}000 THEN 1 ELSE 0 END") for x in (100, 250, 400)), family="flags", kind="B"),
    Feature("status", "C", "o_orderstatus", "state"),
    Feature("priority", "C", "o_orderpriority", "state"),
    Feature("is_urgent", "B", "CASE WHEN o_orderpriority = '1-URGENT' THEN 1 ELSE 0 END", "state"),
    Feature("cust_mod", "N", "o_custkey % 10", "key"),
    Feature("price_if_final", "N", "CASE WHEN o_orderstatus = 'F' THEN o_totalprice END", "money"),
]
LINEITEM = [
    *_n(("quantity", "l_quantity"), ("extendedprice", "l_extendedprice"), ("disc_price", _MONEY), ("charge", f"{_MONEY} * (1 + l_tax)"), family="money"),
    *_n(("discount", "l_discount"), ("tax", "l_tax"), family="rates"),
    *_n(*((f"qty_over_{x}", f"CASE WHEN l_quantity > {x} THEN 1 ELSE 0 END") for x in (10, 25, 40)), family="flags", kind="B"),
    Feature("price_if_returned", "N", "CASE WHEN l_returnflag = 'R' THEN l_extendedprice END", "money"),
    Feature("returnflag", "C", "l_returnflag", "state"),
    Feature("linestatus", "C", "l_linestatus", "state"),
    Feature("linenumber", "N", "l_linenumber", "key"),
]
STAR = [
    *_n(("quantity", "l_quantity"), ("part_size", "p_size"), ("retail_price", "p_retailprice"), ("supplier_balance", "s_acctbal"), ("totalprice", "o_totalprice")),
    *(Feature(a, "C", b) for a, b in (("brand", "p_brand"), ("nation", "n_name"), ("region", "r_name"))),
]
DOCUMENTS = [
    *_n(("n_chars", "n_chars"), ("n_words", "length(text) - length(replace(text, ' ', '')) + 1"), ("n_lines", "length(text) - length(replace(text, chr(10), '')) + 1"), ("commas", "length(text) - length(replace(text, ',', ''))")),
    *_n(("has_at", "CASE WHEN text LIKE '%@%' THEN 1 ELSE 0 END"), ("has_http", "CASE WHEN text LIKE '%http%' THEN 1 ELSE 0 END"), ("is_en", "CASE WHEN lang = 'en' THEN 1 ELSE 0 END"), kind="B"),
    Feature("digits", "N", "length(text) - length(regexp_replace(text, '[0-9]', ''))", "", "length(text) - length(regexp_replace(text, '[0-9]', '', 'g'))"),
    Feature("lang", "C", "lang"),
    Feature("source", "C", "source"),
]
LABELLED = [*DOCUMENTS[:4], *_n(("quality", "quality"), ("toxic", "toxic"), kind="B")]
PAGES = [
    *_n(("html_len", "length(html)"), ("n_tags", "length(html) - length(replace(html, '<', ''))"), ("url_len", "length(url)")),
    Feature("is_https", "B", "CASE WHEN url LIKE 'https%' THEN 1 ELSE 0 END"),
    Feature("host", "C", "regexp_extract(url, '://([^/]*)', 1)"),
]
CONVERSATIONS = [
    *_n(("turn", "turn"), ("text_len", "length(text)"), ("n_words", "length(text) - length(replace(text, ' ', '')) + 1")),
    Feature("is_user", "B", "CASE WHEN role = 'user' THEN 1 ELSE 0 END"),
    Feature("role", "C", "role"),
]
BENCHMARK = _n(("text_len", "length(text)"), ("n_words", "length(text) - length(replace(text, ' ', '')) + 1"))
CUSTOMER = [*_n(("balance", "c_acctbal"), ("nation_key", "c_nationkey")), Feature("in_debt", "B", "CASE WHEN c_acctbal < 0 THEN 1 ELSE 0 END"), Feature("segment", "C", "c_mktsegment")]
PART = [*_n(("size", "p_size"), ("price", "p_retailprice")), Feature("brand", "C", "p_brand"), Feature("type", "C", "p_type")]
SUPPLIER = [*_n(("balance", "s_acctbal"), ("nation_key", "s_nationkey"))]


@dataclass(frozen=True)
class Dataset:
    """Rows to summarise: tables and SQL of (partition, columns) that both engines read, the features over them."""

    name: str
    tables: tuple[str, ...]
    sql: str
    features: list[Feature]
    duck: str | None = None

    def rows(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """The rows with their partition as ``ds``; each use has names of its own, so sessions keep their views."""
        return self.rows_of(**{t: load(spark, sf_dir, t) for t in self.tables})

    def rows_of(self, **frames: DataFrame) -> DataFrame:
        """The same over given tables, such as a stream's micro-batch."""
        spark = next(iter(frames.values())).sparkSession
        return spark.sql(self.sql.format(**{t: "{" + t + "}" for t in self.tables}), **frames)

    def duck_rows(self) -> str:
        return (self.duck or self.sql).format(**{t: t for t in self.tables})


def events(plan: FaultPlan = CLEAN, grain: str = "day", features: list[Feature] | None = None) -> Dataset:
    ds = "CAST(ts AS DATE)" if grain == "day" else "date_trunc('hour', ts)"

    def text(json_k: str) -> str:
        made = ", ".join(f"{e} AS {c}" for c, e in plan.columns(json_k).items())
        return f"SELECT {ds} AS ds, event_id, ts, user_id, value, props, event_type, {made} FROM {{events}}"

    return Dataset(f"events_{grain}_{plan.name}", ("events",), text(JSON_K), features or (EVENTS_HIGH if plan.name.startswith("high") else EVENTS), text(DUCK_K))


def _batch(name: str, table: str, key: str, size: int, features: list[Feature]) -> Dataset:
    return Dataset(name, (table,), f"SELECT CAST(floor({key} / {size}) AS BIGINT) AS ds, * FROM {{{table}}}", features)


_STAR = "SELECT CAST(date_trunc('month', l_shipdate) AS DATE) AS ds, l_quantity, p_size, p_retailprice, p_brand, s_acctbal, n_name, r_name, o_totalprice FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey JOIN {part} p ON l.l_partkey = p.p_partkey JOIN {supplier} s ON l.l_suppkey = s.s_suppkey JOIN {nation} n ON s.s_nationkey = n.n_nationkey JOIN {region} r ON n.n_regionkey = r.r_regionkey"
_LABELLED = "SELECT CAST(floor(d.doc_id / 50) AS BIGINT) AS ds, d.text, d.n_chars, d.lang, d.source, l.quality, l.toxic FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id"
DATASETS: dict[str, Callable[[], Dataset]] = {
    "events_daily": lambda: events(),
    "events_hourly": lambda: events(grain="hour"),
    "orders_monthly": lambda: Dataset("orders_monthly", ("orders",), "SELECT CAST(date_trunc('month', o_orderdate) AS DATE) AS ds, * FROM {orders}", ORDERS),
    "lineitem_monthly": lambda: Dataset("lineitem_monthly", ("lineitem",), "SELECT CAST(date_trunc('month', l_shipdate) AS DATE) AS ds, * FROM {lineitem}", LINEITEM),
    "lineitem_weekly": lambda: Dataset("lineitem_weekly", ("lineitem",), "SELECT CAST(date_trunc('week', l_shipdate) AS DATE) AS ds, * FROM {lineitem}", LINEITEM),
    "star_join_monthly": lambda: Dataset("star_join_monthly", ("lineitem", "orders", "part", "supplier", "nation", "region"), _STAR, STAR),
    "customer_batches": lambda: _batch("customer_batches", "customer", "c_custkey", 75, CUSTOMER),
    "part_batches": lambda: _batch("part_batches", "part", "p_partkey", 100, PART),
    "supplier_batches": lambda: _batch("supplier_batches", "supplier", "s_suppkey", 10, SUPPLIER),
    "documents_batches": lambda: _batch("documents_batches", "documents", "doc_id", 50, DOCUMENTS),
    "documents_by_source": lambda: Dataset("documents_by_source", ("documents",), "SELECT source AS ds, * FROM {documents}", [f for f in DOCUMENTS if f.name != "source"]),
    "labels_joined": lambda: Dataset("labels_joined", ("documents", "labels"), _LABELLED, LABELLED),
    "pages_batches": lambda: _batch("pages_batches", "pages", "page_id", 10, PAGES),
    "conversations_batches": lambda: _batch("conversations_batches", "conversations", "conv_id", 5, CONVERSATIONS),
    "benchmark_batches": lambda: _batch("benchmark_batches", "benchmark", "item_id", 4, BENCHMARK),
}


def widened(spark: SparkSession, sf_dir: str, n: int) -> tuple[DataFrame, list[str]]:
    """Events with ``n`` made features as one array column: the input of the runtime study over feature counts."""
    rows = load(spark, sf_dir, "events").select(F.col("ts").cast("date").alias("ds"), "event_id", "value")
    made = f"transform(sequence(0, {n - 1}), j -> CASE WHEN j % 8 = 7 AND event_id % 8 = 7 THEN NULL ELSE value * (1 + j % 7) + ((event_id * (j + 1)) % 97) END)"
    return rows.select("ds", F.expr(made).alias("x")), [f"f{j:05d}" for j in range(n)]
