"""Corpus pipeline: quality, language, near duplicates, packing; each stage reads what the one before it wrote."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from partguard.llm import bpe, hyperdim, nbsvm, near_dedup, packing
from partguard.llm.common import load, stored

#: Columns that every stage but the last hands on.
COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the documents that the quality classifier, fitted on the labels of this input, takes for good."""
    model = nbsvm.train(docs, load(spark, sf_dir, "labels"))
    return nbsvm.score(docs.select(*COLUMNS), model).filter("predicted = 1").select(*COLUMNS)


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the documents in a language of this input: the cosine with its prototype and the lead over the next one reach the limits that held-out documents set."""
    cosine, margin = hyperdim.limits(docs)
    langs, prototypes = hyperdim.train(docs)
    found = hyperdim.predict(docs.select(*COLUMNS), langs, prototypes, with_cosine=True)
    return found.filter((F.col("lang_pred") != hyperdim.UNKNOWN) & (F.col("cosine") >= cosine) & (F.col("margin") >= margin)).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one document of each group of near duplicates (five words, similarity 0.8): the one with the smallest id."""
    groups = near_dedup.near_duplicates(docs)
    return docs.select(*COLUMNS).join(groups.filter("not kept").select("doc_id"), "doc_id", "left_anti")


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pack what is left into sequences of 4096 tokens."""
    return packing.pack(docs, bpe.public_file("word_bpe_49k.json"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality classifier", quality),
    ("language ID", language),
    ("MinHash near-dedup", near_duplicates),
    ("packing", pack),
]

#: No SQL: a trained classifier and a tokenizer are among the stages.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = stored(docs, f"stage{k}")
    return docs
