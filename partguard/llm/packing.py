"""Packing of documents into training sequences with a fixed number of open windows per partition."""

from __future__ import annotations

import bisect
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe
from .common import load, slices, small_batches, stored, text_of

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_FIELDS = PIECES + ", ids binary, is_open boolean, part int"
_ARROW = pa.schema([("doc_id", pa.int64()), *((x, pa.int64()) for x in ("start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")), ("ids", pa.binary()), ("is_open", pa.bool_()), ("part", pa.int32())])


class Packer:
    """Windows of ``size`` ids, ``windows`` of them open; pieces are (doc_id, start, bytes of ids, doc_tokens)."""

    def __init__(self, base: int, part: int, size: int, windows: int, top_up: int, keep_ids: bool):
        self.next, self.part, self.size, self.windows, self.top_up, self.keep_ids = base, part, size, windows, top_up, keep_ids
        self.free: list[tuple[int, int]] = []  # (ids that still fit, window), ascending
        self.held: dict[int, list[tuple]] = {}
        self.out: list[tuple] = []

    def emit(self, pieces: list[tuple], is_open: bool = False) -> None:
        at = 0
        for doc_id, start, ids, total in pieces:
            n = len(ids) // 4
            self.out.append((doc_id, start, n, zlib.crc32(ids), total, self.next, at, ids if is_open or self.keep_ids else None, is_open, self.part))
            at += n
        self.next += 1

    def add(self, doc_id: int | None, start: int, ids: bytes, total: int) -> None:
        size = self.size
        while len(ids) >= 4 * size:
            self.emit([(doc_id, start, ids[: 4 * size], total)])
            start, ids = start + size, ids[4 * size :]
        n = len(ids) // 4
        if not n:
            return
        k = bisect.bisect_left(self.free, (n, -1))
        if k == len(self.free) and k == self.windows:  # none fits: the fullest goes, topped up with the piece's first ids if the gap is worth a cut
            gap, window = self.free.pop(0)
            if gap >= self.top_up:
                self.held[window].append((doc_id, start, ids[: 4 * gap], total))
                start, ids, n = start + gap, ids[4 * gap :], n - gap
            self.emit(self.held.pop(window))
            k = bisect.bisect_left(self.free, (n, -1))
        if k < len(self.free):
            gap, window = self.free.pop(k)
        else:
            gap, window = size, max(self.held, default=-1) + 1
            self.held[window] = []
        self.held[window].append((doc_id, start, ids, total))
        if gap > n:
            bisect.insort(self.free, (gap - n, window))
        else:
            self.emit(self.held.pop(window))

    def leave(self) -> None:
        """Hand out what is still open, with its ids."""
        for window in sorted(self.held):
            self.emit(self.held[window], is_open=True)
        self.held, self.free = {}, []

    def rows(self) -> pa.RecordBatch:
        out, self.out = self.out, []
        return pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*out), _ARROW)] if out else [pa.array([], f.type) for f in _ARROW], schema=_ARROW)


def pack(docs: DataFrame, tokenizer: str, blank_leads: bool = False, end_id: int = 2, size: int = 4096, windows: int = 16, top_up: int = 32, merge: int = 32, id_column: str = "doc_id", text_column: str = "text", keep_ids: bool = False) -> DataFrame:
    """Pieces of documents, each with its sequence and place; every id of a document is in exactly one piece.

    Each partition is read once, in order, with ``windows`` open windows: whole windows of a long
    document go out at once, the rest is placed where it fits best; where it fits nowhere the
    fullest window is emitted, after topping it up with the piece's first ids if at least
    ``top_up`` ids are free. What the partitions leave open is merged by ``merge`` partitions at a
    time: laid end to end and cut at the window size, so that each merge pads one sequence at most.
    No text moves between machines but the open windows. Null and empty texts are their end id;
    null ids and repeated rows are packed like any other row; an empty table gives no rows.
    """
    small_batches(docs.sparkSession)
    source = docs.select(F.col(id_column).cast("long").alias("doc_id"), text_of(text_column).alias("text"))

    def online(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = bpe.encoder(tokenizer, blank_leads)
        part = TaskContext.get().partitionId()
        packer = Packer(part << 32, part, size, windows, top_up, keep_ids)
        for batch in slices(batches):
            ids, sizes = coder.encode_flat(batch.column("text"), end_id)
            raw, at = ids.tobytes(), 0
            for doc_id, n in zip(batch.column("doc_id").to_pylist(), sizes.tolist()):
                packer.add(doc_id, 0, raw[4 * at : 4 * (at + n)], n)
                at += n
            yield packer.rows()
        packer.leave()
        yield packer.rows()

    def merged(table: pa.Table) -> pa.Table:
        rows = sorted(table.select(["sequence_id", "offset", "doc_id", "start", "ids", "doc_tokens"]).to_pylist(), key=lambda r: (r["sequence_id"], r["offset"]))
        group = min(r["sequence_id"] for r in rows) >> 32
        packer = Packer((1 << 62) | (group << 32), group, size, windows, top_up, keep_ids)
        held, n = [], 0
        for r in rows:
            start, ids = r["start"], r["ids"]
            while ids:
                cut = ids[: 4 * (size - n)]
                held.append((r["doc_id"], start, cut, r["doc_tokens"]))
                start, ids, n = start + len(cut) // 4, ids[len(cut) :], n + len(cut) // 4
                if n == size:
                    packer.emit(held)
                    held, n = [], 0
        if held:
            packer.emit(held)
        return pa.Table.from_batches([packer.rows()])

    placed = stored(source.mapInArrow(online, _FIELDS), "packed")
    left = placed.filter("is_open").withColumn("group", F.floor(F.col("part") / merge)).groupBy("group").applyInArrow(lambda t: merged(t), _FIELDS)
    columns = [x.split()[0] for x in PIECES.split(", ")] + ["ids"] * keep_ids
    return placed.filter("not is_open").select(columns).unionByName(left.select(columns))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(load(spark, sf_dir, "documents"), bpe.public_file("word_bpe_49k.json"))
