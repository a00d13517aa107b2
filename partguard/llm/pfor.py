"""Patched frame-of-reference blocks for token ids, and a file format of documents built on them.

A *stream* is ``PFR1``, the number of ids and of ids per block (uint32 each), the byte offset of
every block (uint32), then the blocks. A block is its smallest id (uint32), the packed width
(uint8), the number of exceptions (uint16), ``width`` bit planes of the differences to the
smallest id, and the exceptions: positions (uint16), then whole differences (uint32). The width is
that of a percentile of the differences. All numbers are little-endian.

A *segment* is ``PFS1``, its length, the shard and the place in it, the ids of the shard before
it (uint64), the number of documents, then per document its id (int64), whether that is null
(uint8) and its number of ids (uint32), then one stream. A file is a row of segments, each ended by a line feed.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np

_HEAD = struct.Struct("<4sIIIQI")


def pack(ids: np.ndarray, block: int = 256, percentile: float = 0.9) -> bytes:
    n = len(ids)
    blocks = -(-n // block)
    if not n:
        return b"PFR1" + struct.pack("<II", 0, block)
    a = np.full(blocks * block, ids[-1], "<u4")
    a[:n] = ids
    a = a.reshape(blocks, block)
    low = a.min(1)
    a = a - low[:, None]
    k = max(0, int(np.ceil(percentile * block)) - 1)
    width = np.frexp(np.partition(a, k, axis=1)[:, k].astype(np.float64))[1].astype(np.int64)
    odd = a >= (np.uint64(1) << width.astype(np.uint64))[:, None]
    n_odd = odd.sum(1)
    plane = -(-block // 8)
    sizes = 7 + plane * width + 6 * n_odd
    at = np.concatenate([[0], np.cumsum(sizes)])
    out = np.zeros(at[-1], np.uint8)
    at = at[:-1]
    head = np.zeros(blocks, np.dtype([("low", "<u4"), ("width", "u1"), ("odd", "<u2")]))
    head["low"], head["width"], head["odd"] = low, width, n_odd
    out[at[:, None] + np.arange(7)] = head.view(np.uint8).reshape(blocks, 7)
    for w in np.unique(width[width > 0]):
        rows = np.flatnonzero(width == w)
        part = a[rows]
        for b in range(w):
            out[(at[rows] + 7 + b * plane)[:, None] + np.arange(plane)] = np.packbits(((part >> np.uint32(b)) & np.uint32(1)).astype(np.uint8), axis=1)
    row, col = np.nonzero(odd)
    if len(row):
        nth = np.arange(len(row)) - np.concatenate([[0], np.cumsum(n_odd)])[row]
        base = at[row] + 7 + plane * width[row]
        out[(base + 2 * nth)[:, None] + np.arange(2)] = col.astype("<u2").view(np.uint8).reshape(-1, 2)
        out[(base + 2 * n_odd[row] + 4 * nth)[:, None] + np.arange(4)] = a[row, col].astype("<u4").view(np.uint8).reshape(-1, 4)
    return b"PFR1" + struct.pack("<II", n, block) + at.astype("<u4").tobytes() + out.tobytes()


def unpack(stream: bytes | memoryview, first: int = 0, last: int | None = None) -> np.ndarray:
    """Ids of blocks ``first`` to ``last`` (exclusive; None: to the end), found through the index."""
    magic, n, block = struct.unpack_from("<4sII", stream)
    if magic != b"PFR1":
        raise ValueError("not a stream of packed ids")
    blocks = -(-n // block)
    last = blocks if last is None else min(last, blocks)
    if first >= last:
        return np.zeros(0, "<u4")
    at = np.frombuffer(stream, "<u4", blocks, 12).astype(np.int64)[first:last]
    body = np.frombuffer(stream, np.uint8, offset=12 + 4 * blocks)
    head = np.ascontiguousarray(body[at[:, None] + np.arange(7)]).view(np.dtype([("low", "<u4"), ("width", "u1"), ("odd", "<u2")])).ravel()
    width, n_odd, plane = head["width"].astype(np.int64), head["odd"].astype(np.int64), -(-block // 8)
    out = np.zeros((last - first, block), "<u4")
    for w in np.unique(width[width > 0]):
        rows = np.flatnonzero(width == w)
        part = np.zeros((len(rows), block), np.uint32)
        for b in range(w):
            bits = np.unpackbits(body[(at[rows] + 7 + b * plane)[:, None] + np.arange(plane)], axis=1, count=block)
            part |= bits.astype(np.uint32) << np.uint32(b)
        out[rows] = part
    row = np.repeat(np.arange(last - first), n_odd)
    if len(row):
        nth = np.arange(len(row)) - np.repeat(np.cumsum(n_odd) - n_odd, n_odd)
        base = at[row] + 7 + plane * width[row]
        col = np.ascontiguousarray(body[(base + 2 * nth)[:, None] + np.arange(2)]).view("<u2").ravel()
        out[row, col] = np.ascontiguousarray(body[(base + 2 * n_odd[row] + 4 * nth)[:, None] + np.arange(4)]).view("<u4").ravel()
    out += head["low"][:, None]
    return out.ravel()[: n - first * block]


def segment(shard: int, place: int, before: int, doc_ids: list[int | None], counts: list[int], ids: np.ndarray, **how) -> bytes:
    stream = pack(ids, **how)
    n = len(doc_ids)
    body = np.array([x or 0 for x in doc_ids], "<i8").tobytes() + np.array([x is None for x in doc_ids], np.uint8).tobytes() + np.array(counts, "<u4").tobytes() + stream
    return _HEAD.pack(b"PFS1", _HEAD.size + len(body), shard, place, before, n) + body


def segments(file: bytes | memoryview) -> Iterator[tuple[int, int, int, list[int | None], np.ndarray, memoryview]]:
    """(shard, place, ids before, document ids, counts, stream) of each segment of a file."""
    view, at = memoryview(file), 0
    while at < len(view):
        if len(view) - at < _HEAD.size:
            raise ValueError("damaged file of token ids")
        magic, size, shard, place, before, n = _HEAD.unpack_from(view, at)
        if magic != b"PFS1" or at + size > len(view):
            raise ValueError("damaged file of token ids")
        p = at + _HEAD.size
        ids = np.frombuffer(view, "<i8", n, p).tolist()
        null = np.frombuffer(view, np.uint8, n, p + 8 * n)
        counts = np.frombuffer(view, "<u4", n, p + 9 * n)
        yield shard, place, before, [None if x else i for i, x in zip(ids, null)], counts, view[p + 13 * n : at + size]
        at += size + 1
