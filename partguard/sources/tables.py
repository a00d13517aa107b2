"""Reading and writing: one loader for all formats, and a shared scratch folder."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def views(spark: SparkSession, sf_dir: str, *tables: str) -> None:
    """Temporary views of the tables, for work in SQL."""
    for t in tables or TABLES:
        load(spark, sf_dir, t).createOrReplaceTempView(t)


def scratch(spark: SparkSession, purpose: str) -> str:
    """A fresh folder that every executor sees."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir") + "/_scratch"
    return f"{base.rstrip('/')}/{purpose}-{uuid.uuid4().hex}"


def stored(df: DataFrame, purpose: str) -> DataFrame:
    """Write and read again: cuts the lineage in a way that survives lost executors."""
    path = scratch(df.sparkSession, purpose)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def zoned(column: str = "ts"):
    """A zone-free time as TIMESTAMP, which watermarks need."""
    return F.col(column).cast("timestamp")


def write_export(df: DataFrame, path: str, kind: str) -> None:
    """Export a report as csv, json, orc or parquet."""
    writer = df.write.mode("overwrite")
    {"csv": lambda: writer.option("header", True).csv(path), "json": lambda: writer.json(path), "orc": lambda: writer.orc(path), "parquet": lambda: writer.parquet(path)}[kind]()


def read_export(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    reader = spark.read.schema(schema)
    return {"csv": lambda: reader.option("header", True).csv(path), "json": lambda: reader.json(path), "orc": lambda: reader.orc(path), "parquet": lambda: reader.parquet(path)}[kind]()
