"""Token-id files: documents encoded whole, in order of their ids, in patched frame-of-reference blocks."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import bpe, pfor
from .common import load, shared_path, slices, small_batches, stored, text_of

READ = "doc_id long, n_tokens long, ids_crc32 long, shard int, place int, nth int, within long"


def write_token_files(docs: DataFrame, path: str, tokenizer: str, blank_leads: bool = True, end_id: int = 2, id_column: str = "doc_id", text_column: str = "text", block: int = 256, percentile: float = 0.9, segment_ids: int = 1 << 18, file_segments: int = 64) -> None:
    """Encode each whole text, append ``end_id`` and write files of ascending document id to ``path``.

    The range partitioning on the id gives each task a run of neighbouring documents, one shard, in
    files of ``file_segments`` segments: some 40 MB, however large a shard is. What moves is text,
    which compresses better than its ids. Spark's text writer commits the files, so any store that
    Spark reaches will do and a task may run again. Null and empty texts hold the end id alone; null
    ids come first; rows with one id stay next to each other in order of their text; a segment
    closes after ``segment_ids`` ids, and a longer text has a segment of its own. Other columns are ignored.
    """
    small_batches(docs.sparkSession)
    ordered = docs.select(F.col(id_column).cast("long").alias("doc_id"), text_of(text_column).alias("text")).repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = bpe.encoder(tokenizer, blank_leads)
        shard, place, before = TaskContext.get().partitionId(), 0, 0
        doc_ids, counts, parts, held = [], [], [], 0

        def close() -> pa.RecordBatch:
            nonlocal doc_ids, counts, parts, held, place, before
            out = pfor.segment(shard, place, before, doc_ids, counts, np.concatenate(parts), block=block, percentile=percentile)
            place, before = place + 1, before + held
            doc_ids, counts, parts, held = [], [], [], 0
            return pa.RecordBatch.from_arrays([pa.array([out], pa.binary())], ["segment"])

        for batch in slices(batches):
            ids, sizes = coder.encode_flat(batch.column("text"), end_id)
            begin = end = 0
            for doc_id, n in zip(batch.column("doc_id").to_pylist(), sizes.tolist()):
                doc_ids.append(doc_id)
                counts.append(n)
                end += n
                held += n
                if held >= segment_ids:
                    parts.append(ids[begin:end])
                    begin = end
                    yield close()
            if end > begin:
                parts.append(ids[begin:end])
        if doc_ids:
            yield close()

    ordered.mapInArrow(encode, "segment binary").select(F.col("segment").cast("string")).write.options(compression="none", maxRecordsPerFile=file_segments).text(path)


def read_token_files(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """One row per document of the files: its ids' number and CRC-32, its shard and its place there; with their ids on demand.

    An empty file gives no row, a truncated or otherwise damaged one an error.
    """

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file in batch.column("content"):
                for shard, place, before, doc_ids, counts, stream in pfor.segments(memoryview(file.as_buffer())):
                    raw = pfor.unpack(stream).tobytes()
                    ends = np.cumsum(counts.astype(np.int64))
                    begins = ends - counts
                    texts = [raw[4 * a : 4 * b] for a, b in zip(begins.tolist(), ends.tolist())]
                    n = len(doc_ids)
                    columns = [pa.array(doc_ids, pa.int64()), pa.array(counts, pa.int64()), pa.array([zlib.crc32(x) for x in texts], pa.int64()), pa.array([shard] * n, pa.int32()), pa.array([place] * n, pa.int32()), pa.array(range(n), pa.int32()), pa.array(begins + before, pa.int64())]
                    if with_ids:
                        columns.append(pa.array([np.frombuffer(x, "<u4").astype(np.int32) for x in texts], pa.list_(pa.int32())))
                    yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_tokens", "ids_crc32", "shard", "place", "nth", "within", *["ids"] * with_ids])

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(decode, READ + ", ids array<int>" * with_ids)


def with_starts(read: DataFrame) -> DataFrame:
    """Add ``start``, the ids of all documents before: each shard's total, summed over the shards before it (a row each)."""
    totals = read.groupBy("shard").agg(F.sum("n_tokens").alias("total"))
    before = totals.select("shard", (F.sum("total").over(Window.orderBy("shard")) - F.col("total")).alias("before"))
    return read.join(before, "shard").withColumn("start", F.col("before") + F.col("within")).drop("before")


def op1_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = shared_path(spark, "token-files")
    write_token_files(load(spark, sf_dir, "documents"), path, bpe.public_file("byte_bpe_50k.json"))
    return with_starts(stored(read_token_files(spark, path), "token-digest")).select("doc_id", "start", "n_tokens", "ids_crc32")
