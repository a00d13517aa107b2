"""SentencePiece encoding and decoding: the best segmentation under piece scores, over a double-array trie."""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import filterfalse

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import BooleanType, LongType, StructField, StructType

from .bpe import public_file
from .common import load, slices, small_batches

MARK = "▁"


class DoubleArray:
    """A trie in two arrays: a node's child by byte c is ``base[node] + c + 1`` if ``check`` there names the node; ``value`` holds the key's number."""

    def __init__(self, keys: list[bytes]):
        children: list[dict[int, int]] = [{}]
        number: list[int] = [-1]
        for k, key in enumerate(keys):
            node = 0
            for c in key:
                node = children[node].setdefault(c, len(children))
                if node == len(children):
                    children.append({})
                    number.append(-1)
            if number[node] < 0:
                number[node] = k
        size = 2 * len(children) + 600
        base, check, value = [0] * size, [-1] * size, [-1] * size
        place, free = {0: 0}, 1
        check[0] = 0
        order = [0]
        for node in order:
            kids = children[node]
            at = place[node]
            value[at] = number[node]
            if not kids:
                continue
            while check[free] >= 0:
                free += 1
            low, b, taken = min(kids), free, 0
            others = [c - low for c in kids if c != low]
            while True:
                if b + 300 > len(base):
                    for x, fill in ((base, 0), (check, -1), (value, -1)):
                        x.extend([fill] * len(x))
                if b > low + 1 and check[b] < 0 and all(check[b + c] < 0 for c in others):
                    break
                taken += check[b] >= 0
                b += 1
            if taken > 0.9 * (b - free + 1):  # nearly full up to here: later searches start later
                free = b
            start = b - low - 1
            base[at] = start
            for c, kid in kids.items():
                check[start + c + 1] = at
                place[kid] = start + c + 1
                order.append(kid)
        last = max(place.values()) + 260
        self.base, self.check, self.value = base[:last], (check + [-1] * 260)[:last], value[:last]

    def prefixes(self, text: bytes, start: int = 0) -> list[tuple[int, int]]:
        """(end, number) of every key that starts at ``start``."""
        base, check, value, node, out = self.base, self.check, self.value, 0, []
        for j in range(start, len(text)):
            child = base[node] + text[j] + 1
            if check[child] != node or child == 0:
                break
            node = child
            if value[node] >= 0:
                out.append((j + 1, value[node]))
        return out


@dataclass
class Pieces:
    """A vocabulary: pieces with log scores, and for each byte the id of its fallback piece (or -1: then the unknown id)."""

    ids: list[int]
    keys: list[bytes]
    scores: list[float]
    byte_ids: list[int]
    texts: list[bytes]  # by id; empty for control pieces and bytes
    unknown: int
    trie: DoubleArray = field(init=False)

    def __post_init__(self) -> None:
        self.trie = DoubleArray(self.keys)
        byte_of = {i: bytes([b]) for b, i in enumerate(self.byte_ids) if i >= 0}
        self.raw = [t or byte_of.get(i, "\ufffd".encode() if i == self.unknown else b"") for i, t in enumerate(self.texts)]
        self.penalty = min(self.scores, default=0.0) - 10.0
        inner = {c for k in self.keys if len(t := k.decode()) > 1 for c in t[1:]}
        #: Where no piece goes on across a mark after another sign, or across a line feed, a text can be cut there.
        self.cuts = MARK not in {c for k in self.keys for c in k.decode().lstrip(MARK)} and not ({"\n"} & (inner | {k.decode()[0] for k in self.keys if len(k.decode()) > 1}))

    @classmethod
    def of_model(cls, path: str) -> Pieces:
        """The pieces of a model file; the library only reads them, the segmentation is made here."""
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        n = m.get_piece_size()
        byte_ids, texts = [-1] * 256, [b""] * n
        plain = []
        for i in range(n):
            piece = m.id_to_piece(i)
            if m.is_byte(i):
                byte_ids[int(piece[1:-1], 16)] = i
            elif not (m.is_control(i) or m.is_unknown(i) or m.is_unused(i)):
                texts[i] = piece.encode()
                plain.append(i)
        return cls(plain, [texts[i] for i in plain], [m.get_score(i) for i in plain], byte_ids, texts, m.unk_id())


def segment(pieces: Pieces, text: bytes) -> list[int]:
    """Ids of the segmentation with the largest sum of scores; among equals the one whose last piece is longest, and so on to the left.

    A sign that no piece starts with costs ten less than the lowest score and becomes its bytes' pieces.
    """
    n = len(text)
    if not n:
        return []
    low = float("-inf")
    best, back, number = [low] * (n + 1), [0] * (n + 1), [-1] * (n + 1)
    best[0] = 0.0
    scores, base, check, value = pieces.scores, pieces.trie.base, pieces.trie.check, pieces.trie.value
    for i in range(n):
        here = best[i]
        c = text[i]
        if here == low or (c & 0xC0) == 0x80:
            continue
        first = i + 1 if c < 0x80 else min(n, i + (2 if c < 0xE0 else 3 if c < 0xF0 else 4))
        node, single = 0, False
        for j in range(i, n):  # walk the trie along the text: every piece that starts here
            child = base[node] + text[j] + 1
            if check[child] != node:
                break
            node = child
            k = value[node]
            if k >= 0:
                j += 1
                if j == first:
                    single = True
                s = here + scores[k]
                if s > best[j]:
                    best[j], back[j], number[j] = s, i, k
        if not single and here + pieces.penalty > best[first]:
            best[first], back[first], number[first] = here + pieces.penalty, i, -1
    out, end = [], n
    while end:
        start, k = back[end], number[end]
        if k >= 0:
            out.append(pieces.ids[k])
        else:
            found = [pieces.byte_ids[b] for b in text[start:end]]
            out.extend(reversed(found) if min(found) >= 0 else [pieces.unknown])
        end = start
    return out[::-1]


class Encoder:
    """Whole texts to ids: blanks become marks, one mark is put in front, and runs between safe cuts are segmented apart and kept."""

    _RUN = re.compile(r"\n| *[^ \n]+| +")

    def __init__(self, pieces: Pieces, limit: int = 200_000):
        self.pieces, self.limit = pieces, limit
        self.known: dict[str, bytes] = {}

    def encode(self, text: str) -> bytes:
        if not text:
            return b""
        runs = self._RUN.findall(" " + text) if self.pieces.cuts else [" " + text]
        known = self.known
        new = set(filterfalse(known.__contains__, runs))
        for r in new:
            known[r] = np.array(segment(self.pieces, r.replace(" ", MARK).encode("utf-8", "replace")), "<u4").tobytes()
        out = b"".join(map(known.__getitem__, runs))
        if len(known) > self.limit:
            for r in new:
                del known[r]
        return out


def decode(pieces: Pieces, ids: list[int]) -> str:
    """Text of ids: pieces and fallback bytes in order, marks as blanks, without the mark in front."""
    text = b"".join(map(pieces.raw.__getitem__, ids)).decode("utf-8", "replace").replace(MARK, " ")
    return text[1:] if text.startswith(" ") else text


def encode(docs: DataFrame, model: str, text_column: str = "text") -> DataFrame:
    """Add ``n_pieces``, ``n_byte_pieces``, ``ids_crc32``, ``n_chars_decoded`` and ``round_trip`` to ``docs``.

    ``round_trip`` is whether the decoded ids are the text, in which a mark of its own counts as a
    blank. Null is the empty text, with no piece. Columns of those names are replaced. Workers get
    the vocabulary with its trie once, by broadcast; it is as large as the model file.
    """
    new = [StructField(x, LongType()) for x in ("n_pieces", "n_byte_pieces", "ids_crc32", "n_chars_decoded")] + [StructField("round_trip", BooleanType())]
    docs = docs.drop(*(f.name for f in new))
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(Pieces.of_model(model))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = shared.value
        coder = _CODERS.setdefault(model, Encoder(pieces))
        is_byte = np.zeros(len(pieces.texts), bool)
        is_byte[[i for i in pieces.byte_ids if i >= 0]] = True
        for batch in slices(batches, column=text_column):
            rows = []
            for text in batch.column(text_column).to_pylist():
                raw = coder.encode(text or "")
                ids = np.frombuffer(raw, "<u4")
                back = decode(pieces, ids.tolist())
                rows.append((len(ids), int(is_byte[ids].sum()), zlib.crc32(raw), len(back), back == (text or "").replace(MARK, " ")))
            columns = [pa.array(x, pa.bool_() if k == 4 else pa.int64()) for k, x in enumerate(zip(*rows))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *columns], [*batch.schema.names, *(f.name for f in new)])

    return docs.mapInArrow(work, StructType([*docs.schema.fields, *new]))


_CODERS: dict[str, Encoder] = {}


def op3_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(load(spark, sf_dir, "documents").select("doc_id", "text"), public_file("piece_bpe_32k.model")).drop("text")
