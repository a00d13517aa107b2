"""Language identification with hyperdimensional letter profiles."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StringType, StructField, StructType

from .common import crc_mod, load, slices, small_batches

UNKNOWN = "und"
_BLANK = 0x20
_CHARS = 1_000_000  # of text at a time: some ten arrays of as many numbers are held
_IS_LETTER: np.ndarray | None = None


def _letters() -> np.ndarray:
    global _IS_LETTER
    if _IS_LETTER is None:
        _IS_LETTER = np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)
    return _IS_LETTER


def trigrams(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Letter trigrams of all texts: (distinct codes, index into them per trigram, text per trigram).

    Letters are lower-cased; whatever stands between letters is one blank, as are both ends.
    A code holds three code points of 21 bits.
    """
    low = [f" {x.lower()} " for x in texts]
    points = np.frombuffer("".join(low).encode("utf-32-le", "surrogatepass"), "<u4")
    doc = np.repeat(np.arange(len(low), dtype=np.int32), [len(x) for x in low])
    letter = _letters()[points]
    starts = np.concatenate([[0], np.cumsum([len(x) for x in low])[:-1]]) if low else np.zeros(0, int)
    keep = letter.copy()
    keep[1:] |= letter[:-1]
    keep[starts] = True
    symbol, doc = np.where(letter, points, _BLANK)[keep], doc[keep]
    seen = np.zeros(0x110000, bool)
    seen[symbol] = True
    alphabet = np.flatnonzero(seen)
    k = len(alphabet)
    small = np.zeros(0x110000, np.int64)
    small[alphabet] = np.arange(k)
    s = small[symbol]
    whole = doc[:-2] == doc[2:]
    code, doc = ((s[:-2] * k + s[1:-1]) * k + s[2:])[whole], doc[:-2][whole]
    if k**3 <= 1 << 23:
        there = np.zeros(k**3, bool)
        there[code] = True
        distinct = np.flatnonzero(there)
        place = np.zeros(k**3, np.int32)
        place[distinct] = np.arange(len(distinct), dtype=np.int32)
        index = place[code]
    else:
        distinct, index = np.unique(code, return_inverse=True)
    a, b, c = alphabet[distinct // (k * k)] if k else distinct, alphabet[distinct // k % k] if k else distinct, alphabet[distinct % k] if k else distinct
    return (a.astype(np.int64) << 42) | (b.astype(np.int64) << 21) | c, index, doc


class Space:
    """Random ±1 vectors of letters, drawn from the code point and a seed alone, so that every worker has the same."""

    def __init__(self, dim: int, seed: int):
        self.dim, self.seed, self.letters = dim, seed, {}

    def letter(self, point: int) -> np.ndarray:
        if point not in self.letters:
            bits = np.random.Generator(np.random.Philox(key=[self.seed, point])).integers(0, 2, self.dim, dtype=np.int8)
            self.letters[point] = bits * np.int8(2) - np.int8(1)
        return self.letters[point]

    def bind(self, codes: np.ndarray) -> Iterator[tuple[slice, np.ndarray]]:
        """Vectors of trigrams, some thousands at a time: the product of the letters' vectors, rotated by two, one and no places."""
        for i in range(0, len(codes), 4096):
            part = codes[i : i + 4096]
            points = [(part >> 42).astype(np.int64), (part >> 21) & 0x1FFFFF, part & 0x1FFFFF]
            alphabet = np.unique(np.concatenate(points))
            table = np.stack([self.letter(int(p)) for p in alphabet])
            out = table[np.searchsorted(alphabet, points[2])]
            out *= np.roll(table, 1, axis=1)[np.searchsorted(alphabet, points[1])]
            out *= np.roll(table, 2, axis=1)[np.searchsorted(alphabet, points[0])]
            yield slice(i, i + len(part)), out


def train(docs: DataFrame, lang_column: str = "lang", text_column: str = "text", dim: int = 2048, seed: int = 7) -> tuple[list[str], np.ndarray]:
    """Languages and their unit prototypes: the bundle of all trigram vectors of all texts of a language.

    Every partition bundles what it reads; the bundles, a vector per language and partition, are
    summed in groups of 256 partitions and then over the groups. Rows without language or text
    don't count. What reaches the driver is a vector per language.
    """

    def bundle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, dict[int, int]] = {}
        space, sums = Space(dim, seed), {}

        def flush(lang: str) -> None:
            held = counts.pop(lang)
            codes, times = np.fromiter(held.keys(), np.int64, len(held)), np.fromiter(held.values(), np.float64, len(held))
            total = sums.setdefault(lang, np.zeros(dim))
            for at, vectors in space.bind(codes):
                total += times[at].astype(np.float32) @ vectors.astype(np.float32)

        for batch in slices(batches, chars=_CHARS):
            lang = np.array(batch.column("lang").to_pylist(), object)
            codes, index, doc = trigrams(batch.column("text").to_pylist())
            for x in set(lang.tolist()):
                n = np.bincount(index[(lang == x)[doc]], minlength=len(codes))
                some = np.flatnonzero(n)
                held = counts.setdefault(x, {})
                for c, k in zip(codes[some].tolist(), n[some].tolist()):
                    held[c] = held.get(c, 0) + k
                if len(held) > 50_000:
                    flush(x)
        for x in list(counts):
            flush(x)
        part = TaskContext.get().partitionId()
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums)), pa.array([x.tobytes() for x in sums.values()], pa.binary()), pa.array([part // 256] * len(sums), pa.int32())], ["lang", "vector", "part"])

    def add(table: pa.Table) -> pa.Table:
        total = np.zeros(dim)
        for x in table.column("vector").to_pylist():
            total += np.frombuffer(x)
        return pa.table({"lang": table.column("lang")[:1], "vector": pa.array([total.tobytes()], pa.binary()), "part": table.column("part")[:1]})

    small_batches(docs.sparkSession)
    kind = "lang string, vector binary, part int"
    rows = docs.select(F.col(lang_column).cast("string").alias("lang"), F.col(text_column).cast("string").alias("text")).filter("lang is not null and text is not null")
    bundles = rows.mapInArrow(bundle, kind)
    found = bundles.groupBy("lang", "part").applyInArrow(lambda t: add(t), kind).groupBy("lang").applyInArrow(lambda t: add(t), kind).collect()
    learned = {r["lang"]: np.frombuffer(bytes(r["vector"])) for r in found}
    langs = sorted(x for x, v in learned.items() if np.any(v))
    return langs, np.array([learned[x] / np.linalg.norm(learned[x]) for x in langs]).reshape(len(langs), dim)


def predict(docs: DataFrame, langs: list[str], prototypes: np.ndarray, text_column: str = "text", seed: int = 7, with_cosine: bool = False) -> DataFrame:
    """Add ``lang_pred`` and ``score`` to ``docs``, and where asked ``cosine`` and ``margin``.

    The cosine of a text's bundle with a prototype is a sum over its trigrams of *their* products
    with the prototype, over the bundle's length, which is the same for every language. So each
    trigram's products are made once per worker, a text's are added up, and the length is never
    needed: the largest sum has the largest cosine, and the score is the largest cosine's part of the
    two largest, negative ones as 0. A text that is null or has no letter is ``und`` with score 0,
    as are all texts where no language was learned; ties go to the first language by name.

    The score compares languages and says nothing of a text in none of them; ``cosine`` does, and ``margin`` is what
    the second language's lacks to it. For these the bundle's length is the root of ``dim`` times the sum of squares of
    the trigrams' numbers: vectors of different trigrams are independent, so the true length is within some per cent of it.
    """
    dim = prototypes.shape[1]
    added = ["lang_pred", "score", *(["cosine", "margin"] if with_cosine else [])]
    docs = docs.drop(*added)
    schema = StructType([*docs.schema.fields, *(StructField(x, DoubleType() if x != "lang_pred" else StringType()) for x in added)])

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        space, weights = Space(dim, seed), prototypes.T.astype(np.float32)
        known, products = np.zeros(0, np.int64), np.zeros((0, len(langs)))
        for batch in slices(batches, chars=_CHARS, column=text_column):
            texts = [x or "" for x in batch.column(text_column).to_pylist()]
            codes, index, doc = trigrams(texts)
            if len(known) > 300_000:
                known, products = known[:0], products[:0]
            new = np.setdiff1d(codes, known, assume_unique=True)
            if len(new):
                made = np.zeros((len(new), len(langs)))
                for at, vectors in space.bind(new):
                    made[at] = vectors.astype(np.float32) @ weights
                known, products = np.concatenate([known, new]), np.concatenate([products, made])
                order = np.argsort(known)
                known, products = known[order], products[order]
            lettered = (codes & 0x1FFFFF) != _BLANK
            lettered |= ((codes >> 21) & 0x1FFFFF) != _BLANK
            some = np.bincount(doc, weights=lettered[index], minlength=len(texts)) > 0
            if langs:
                own = products[np.searchsorted(known, codes)]
                sums = np.stack([np.bincount(doc, weights=own[index, k], minlength=len(texts)) for k in range(len(langs))], axis=1)
                best = sums.argmax(1)
                two = np.sort(np.maximum(sums, 0), axis=1)[:, -2:]
                whole = two.sum(1)
                score = np.where(some & (whole > 0), two[:, -1] / np.where(whole > 0, whole, 1), 0.0)
                names = [langs[b] if s else UNKNOWN for b, s in zip(best, some)]
            else:
                names, score = [UNKNOWN] * len(texts), np.zeros(len(texts))
            columns = [pa.array(names, pa.string()), pa.array(score, pa.float64())]
            if with_cosine:
                cosine = margin = np.zeros(len(texts))
                if langs:
                    pairs, times = np.unique(doc.astype(np.int64) * max(1, len(codes)) + index, return_counts=True)
                    length = np.sqrt(dim * np.bincount(pairs // max(1, len(codes)), weights=times.astype(float) ** 2, minlength=len(texts)))
                    each = np.where(some, 1 / np.where(length > 0, length, 1), 0)[:, None] * np.sort(sums, axis=1)
                    cosine, margin = each[:, -1], each[:, -1] - (each[:, -2] if len(langs) > 1 else 0)
                columns += [pa.array(cosine, pa.float64()), pa.array(margin, pa.float64())]
            yield pa.RecordBatch.from_arrays([*batch.columns, *columns], [*batch.schema.names, *added])

    small_batches(docs.sparkSession)
    return docs.mapInArrow(label, schema)


def limits(docs: DataFrame, folds: int = 5, id_column: str = "doc_id", lang_column: str = "lang", text_column: str = "text", dim: int = 2048) -> tuple[float, float]:
    """Least ``cosine`` and ``margin`` of a text in a known language.

    Half of what all but a hundredth of the held-out documents reach whose label is found by prototypes of the others. Cosines with a
    language that has nothing to do with a text deviate by 1 / sqrt(dim); four and two of these are the least limits.
    """
    held = crc_mod(id_column, folds) == 0
    langs, prototypes = train(docs.filter(~held), lang_column, text_column, dim)
    right = predict(docs.filter(held), langs, prototypes, text_column, with_cosine=True).filter(F.col("lang_pred") == F.col(lang_column))
    low = right.agg(*(F.percentile_approx(x, 0.01, 10_000).alias(x) for x in ("cosine", "margin"))).first()
    return max(4 / dim**0.5, (low["cosine"] or 0) / 2), max(2 / dim**0.5, (low["margin"] or 0) / 2)


def identify(docs: DataFrame, folds: int = 5, id_column: str = "doc_id", lang_column: str = "lang", text_column: str = "text") -> DataFrame:
    """Learn from the labelled documents outside fold 0 (CRC-32 of the id's text), label all; adds ``held_out``, ``lang_pred``, ``score``."""
    held = crc_mod(id_column, folds) == 0
    langs, prototypes = train(docs.filter(~held), lang_column, text_column)
    return predict(docs.withColumn("held_out", held), langs, prototypes, text_column)


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held = crc_mod("doc_id", 5) == 0
    langs, prototypes = train(docs.filter(~held))
    return predict(docs.select("doc_id", "text", held.alias("held_out")), langs, prototypes).select("doc_id", "held_out", "lang_pred", "score")
