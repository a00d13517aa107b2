"""Line-first cleaning: rules on lines, then on what is left of a document; with the base counts of words."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, LongType, StringType, StructField, StructType

from .common import load, slices, small_batches

_SPACE = " \t\n\v\f\r"
_SYMBOLS = "#*$%&|<>"
#: Phrases of boilerplate lines, in lower case.
BOILERPLATE = ("all rights reserved", "cookie policy", "privacy policy", "terms of use", "terms of service", "click here", "sign up", "log in to", "enable javascript", "subscribe to our newsletter", "share this page", "powered by", "lorem ipsum")
_BOILERPLATE = re.compile("|".join(map(re.escape, BOILERPLATE)))
_WORD = re.compile(r"[^\x20\x09-\x0D]+")

COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
LINES = ("n_lines", "n_bad_punctuation", "n_navigation", "n_boilerplate", "chars_lost")


def repeated_words(words: list[str]) -> int:
    """Words that lie in a three-word window which the text has twice or more, the first one included."""
    if len(words) < 4:
        return 0
    seen: dict[str, int] = {}
    a = np.fromiter((seen.setdefault(w, len(seen)) for w in words), np.int64, len(words))
    pair = a[:-1] * len(seen) + a[1:]
    if len(seen) > 2_000_000:
        pair = np.unique(pair, return_inverse=True)[1]
    _, at, times = np.unique(pair[:-1] * len(seen) + a[2:], return_inverse=True, return_counts=True)
    many = times[at] > 1
    cover = np.zeros(len(words), bool)
    for k in range(3):
        cover[k : len(words) - 2 + k] |= many
    return int(cover.sum())


def base_counts(text: str) -> tuple[int, int, int, int, int]:
    words = _WORD.findall(text)
    lines = [x for x in text.split("\n") if x.strip(_SPACE)]
    return len(words), len(text) - sum(map(text.count, _SPACE)), sum(map(text.count, _SYMBOLS)), len(lines) - len(set(lines)), repeated_words(words)


def line_fault(line: str) -> int:
    """0: good; 1: punctuation (over a tenth of the line's signs are symbols or parts of runs of ! and ?); 2: navigation
    (three or more bars, or at least two bars or arrows and under four words for each); 3: boilerplate phrase."""
    bars = line.count("|") + line.count("»") + line.count("›")
    if bars >= 3 or (bars == 2 and len(line.split()) < 8):
        return 2
    signs = len(line) - sum(map(line.count, _SPACE))
    marks = sum(map(line.count, "#*$%&<>")) + 2 * (line.count("!!") + line.count("??"))
    if 10 * marks > signs:
        return 1
    return 3 if _BOILERPLATE.search(line.lower()) else 0


def clean(docs: DataFrame, text_column: str = "text", min_words: int = 50, max_lost: float = 0.3, with_text: bool = False) -> DataFrame:
    """Add the base counts, the line counts, ``base_failed`` and ``kept`` (and ``cleaned``: the lines left) to ``docs``.

    Lines that break a rule are removed first; a document that loses more than ``max_lost`` of its
    word characters, or that fails the base rules (fewer than ``min_words`` words, or over half of
    them in repeated windows), is rejected. Null is taken as the empty text, which fails; columns
    of the input that have a result's name are replaced.
    """
    new = [*(StructField(c, LongType()) for c in (*COUNTS, *LINES)), StructField("base_failed", BooleanType()), StructField("kept", BooleanType()), *[StructField("cleaned", StringType())] * with_text]
    docs = docs.drop(*(f.name for f in new))
    small_batches(docs.sparkSession)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, column=text_column):
            rows, texts = [], []
            for text in batch.column(text_column).to_pylist():
                text = text or ""
                counts = base_counts(text)
                faults, lost, left = [0, 0, 0, 0], 0, []
                lines = [x for x in text.split("\n") if x.strip(_SPACE)]
                known: dict[str, int] = {}
                for line in lines:
                    fault = known.get(line)
                    if fault is None:
                        fault = known[line] = line_fault(line)
                    faults[fault] += 1
                    if fault:
                        lost += len(line) - sum(map(line.count, _SPACE))
                    elif with_text:
                        left.append(line)
                failed = counts[0] < min_words or 100 * counts[4] > 50 * counts[0]
                rows.append((*counts, len(lines), *faults[1:], lost, failed, not failed and lost <= max_lost * counts[1]))
                texts.append("\n".join(left))
            columns = [pa.array(x, pa.int64() if i < len(COUNTS) + len(LINES) else pa.bool_()) for i, x in enumerate(zip(*rows))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *columns, *[pa.array(texts, pa.string())] * with_text], [*batch.schema.names, *(f.name for f in new)])

    return docs.mapInArrow(judge, StructType([*docs.schema.fields, *new]))


def op4_line_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    return clean(docs).select("doc_id", *COUNTS, "base_failed", "kept", *LINES)


_BARS = "length(regexp_replace(line, '[^|»›]', '', 'g'))"
_SIGNS = r"length(regexp_replace(line, '[\x20\x09-\x0D]', '', 'g'))"
_MARKS = r"length(regexp_replace(line, '[^#*$%&<>]', '', 'g')) + 2 * (len(regexp_extract_all(line, '!!')) + len(regexp_extract_all(line, '\?\?')))"
OP4_SQL = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, words, unnest(words) AS word, unnest(range(len(words))) AS p
      FROM (SELECT doc_id, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words FROM d)),
t AS (SELECT doc_id, p, word, lead(word, 1) OVER q AS w2, lead(word, 2) OVER q AS w3 FROM w WINDOW q AS (PARTITION BY doc_id ORDER BY p)),
m AS (SELECT doc_id, p, count(*) OVER (PARTITION BY doc_id, word, w2, w3) AS n FROM t WHERE w3 IS NOT NULL),
r AS (SELECT doc_id, count(DISTINCT p + k) AS n_repeat_words FROM m, (SELECT unnest([0, 1, 2]) AS k) WHERE n > 1 GROUP BY doc_id),
lines AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM d),
f AS (SELECT doc_id, line, {_SIGNS} AS signs,
        CASE WHEN {_BARS} >= 3 OR ({_BARS} = 2 AND len(regexp_extract_all(line, '\S+')) < 8) THEN 2
             WHEN 10 * ({_MARKS}) > {_SIGNS} THEN 1
             WHEN regexp_matches(lower(line), '{"|".join(BOILERPLATE)}') THEN 3 ELSE 0 END AS fault
      FROM lines WHERE {_SIGNS} > 0),
g AS (SELECT doc_id, count(*) AS n_lines, count(*) - count(DISTINCT line) AS n_dup_lines, count(*) FILTER (fault = 1) AS n_bad_punctuation,
        count(*) FILTER (fault = 2) AS n_navigation, count(*) FILTER (fault = 3) AS n_boilerplate, coalesce(sum(signs) FILTER (fault > 0), 0) AS chars_lost
      FROM f GROUP BY doc_id),
b AS (SELECT doc_id, len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g')) AS word_chars,
        length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS n_symbols FROM d),
a AS (SELECT b.*, coalesce(n_dup_lines, 0)::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words, coalesce(n_lines, 0)::BIGINT AS n_lines,
        coalesce(n_bad_punctuation, 0)::BIGINT AS n_bad_punctuation, coalesce(n_navigation, 0)::BIGINT AS n_navigation, coalesce(n_boilerplate, 0)::BIGINT AS n_boilerplate,
        coalesce(chars_lost, 0)::BIGINT AS chars_lost FROM b LEFT JOIN g USING (doc_id) LEFT JOIN r USING (doc_id))
SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols, n_dup_lines, n_repeat_words,
  n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
  NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND chars_lost <= 0.3 * word_chars AS kept,
  n_lines, n_bad_punctuation, n_navigation, n_boilerplate, chars_lost
FROM a
"""
