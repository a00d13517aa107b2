"""Document fingerprints: Merkle trees over sections, paragraphs and sentence pieces, in DataFrame functions alone.

A section ends at an empty line, a paragraph at a line feed, a piece at a word that ends with a
full stop, exclamation or question mark, or after sixteen words. Hashes of pieces make the
paragraph's, those the section's, those the root. The fingerprint is the root (64 hex digits), then for each
section ``/`` and the start of its hash, for each paragraph ``,`` and the start of its hash, and for each
piece ``.`` and the start of its hash, eight digits each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import load, stored, text_of

_PIECE = r"(?:[^ ]*[^ .!?] +){0,15}[^ ]+ *| +"


def _short(h: Column) -> Column:
    return F.substring(h, 1, 8)


def fingerprint(text: Column) -> Column:
    """The fingerprint of a text; equal for equal texts only, up to collisions of SHA-256 and MD5. Null gives null, the empty text has a fingerprint."""
    pieces = F.transform(F.split(text, "\n\n"), lambda s: F.transform(F.split(s, "\n"), lambda p: F.transform(F.regexp_extract_all(p, F.lit(_PIECE), F.lit(0)), lambda x: F.md5(x.cast("binary")))))
    paragraphs = F.transform(pieces, lambda s: F.transform(s, lambda p: F.struct(F.md5(F.concat_ws("", p).cast("binary")).alias("h"), p.alias("p"))))
    sections = F.transform(paragraphs, lambda s: F.struct(F.md5(F.concat_ws("", s["h"]).cast("binary")).alias("h"), s.alias("s")))
    shown = F.transform(sections, lambda t: F.concat(F.lit("/"), _short(t["h"]), F.concat_ws("", F.transform(t["s"], lambda p: F.concat(F.lit(","), _short(p["h"]), F.concat_ws("", F.transform(p["p"], lambda x: F.concat(F.lit("."), _short(x)))))))))
    return F.concat(F.sha2(F.concat_ws("", F.transform(sections, lambda t: t["h"])).cast("binary"), 256), F.concat_ws("", shown))


def pieces_of(fp: Column) -> Column:
    return F.regexp_extract_all(fp, F.lit(r"\.([0-9a-f]{8})"), F.lit(1))


def likeness(a: Column, b: Column) -> Column:
    """Shared part of two fingerprints' branches: distinct pieces and the root, over all of both; 1 only if the roots agree."""
    same = (F.substring(a, 1, 64) == F.substring(b, 1, 64)).cast("int")
    x, y = pieces_of(a), pieces_of(b)
    shared, every = F.size(F.array_intersect(x, y)), F.size(F.array_union(x, y))
    return F.when(same == 1, F.lit(1.0)).otherwise(shared / (every + 1).cast("double"))


def differing(a: Column, b: Column) -> Column:
    """Where two fingerprints differ: (section, paragraph) numbers, from 0, of the paragraphs whose branch is not in the other text at that place.

    Empty if the roots agree; sections that agree are passed over without a look at their paragraphs.
    """

    def tree(fp: Column) -> Column:
        return F.transform(F.slice(F.split(fp, "/"), 2, 1 << 30), lambda s: F.split(s, ","))

    def walk(x: Column, y: Column) -> Column:
        def section(s: Column, i: Column) -> Column:
            t = F.coalesce(F.get(y, i), F.array().cast("array<string>"))
            places = F.sequence(F.lit(1), F.greatest(F.size(s), F.size(t)) - 1)
            changed = F.filter(places, lambda k: ~F.get(s, k).eqNullSafe(F.get(t, k)))
            return F.when(F.get(s, F.lit(0)).eqNullSafe(F.get(t, F.lit(0))), F.array().cast("array<struct<section:int,paragraph:int>>")).otherwise(F.transform(changed, lambda k: F.struct(i.alias("section"), (k - 1).alias("paragraph"))))

        return F.flatten(F.transform(x, section))

    return F.when(F.substring(a, 1, 64) == F.substring(b, 1, 64), F.array().cast("array<struct<section:int,paragraph:int>>")).otherwise(walk(tree(a), tree(b)))


def neighbours(sizes: DataFrame) -> DataFrame:
    """(id, n, before, n_before): each id with the id before it in ascending order and that one's n; before the first comes the last.

    ``sizes`` has distinct ids. A range partitioning deals them out; the window runs inside each
    range, and the last id of each range, a row for a range, is handed to the next.
    """
    ranged = stored(sizes.repartitionByRange("id").withColumn("range", F.spark_partition_id()), "ranges")
    inside = Window.partitionBy("range").orderBy("id")
    own = F.struct(F.col("id").alias("before"), F.col("n").alias("n_before"))
    ends = ranged.groupBy("range").agg(F.max_by(own, "id").alias("end"))
    whole = ends.agg(F.max(F.struct("range", "end"))["end"].alias("last"))
    ends = ends.crossJoin(F.broadcast(whole)).select("range", F.coalesce(F.lag("end").over(Window.orderBy("range")), F.col("last")).alias("end"))  # one row each: the last of all
    led = ranged.withColumn("own", F.lag(own).over(inside)).join(ends, "range")
    return led.select("id", "n", F.coalesce("own", "end").alias("b")).select("id", "n", "b.*")


def with_next(docs: DataFrame, part: int = 4, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(doc_id, text, n_chars, fingerprint, head, next_fingerprint): each text with the first n_chars/``part`` code points and the fingerprint of the next document by id; after the last comes the first.

    Texts move once, by id; what comes from the next document is its head and fingerprint. Null
    texts are empty; a null id comes first, as the smallest long, which is no id of its own. Rows that share an id share their next document; of
    several such rows the one with the smallest head is the next document of the id before.
    """
    floor = -(1 << 63)
    source = docs.select(F.coalesce(F.col(id_column).cast("long"), F.lit(floor)).alias("id"), text_of(text_column).alias("text"))
    sizes = source.select("id", F.length("text").cast("long").alias("n")).groupBy("id").agg(F.max("n").alias("n"), F.count("*").alias("rows"))
    sizes = stored(sizes, "sizes")
    repeated = not sizes.filter("rows > 1").isEmpty()
    placed = source.join(neighbours(sizes.select("id", "n")), "id")
    nexts = placed.select(F.col("before").alias("id"), F.expr(f"substring(text, 1, int(n_before div {part}))").alias("head"), fingerprint(F.col("text")).alias("next_fingerprint"))
    if repeated:
        nexts = nexts.groupBy("id").agg(F.min(F.struct("head", "next_fingerprint")).alias("x")).select("id", "x.*")
    doc_id = F.nullif("id", F.lit(floor)).alias("doc_id")
    return source.join(nexts, "id").select(doc_id, "text", F.length("text").cast("long").alias("n_chars"), fingerprint(F.col("text")).alias("fingerprint"), F.expr(f"substring(head, 1, int(length(text) div {part}))").alias("head"), "next_fingerprint")


def op5_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    both = with_next(load(spark, sf_dir, "documents"))
    edited = both.withColumn("edited", F.expr("concat(substring(text, 1, int(n_chars - n_chars div 4)), head)"))
    prints = edited.select("doc_id", "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), "fingerprint", fingerprint(F.col("edited")).alias("edited_fingerprint"), "next_fingerprint")
    return prints.select("doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", likeness(F.col("fingerprint"), F.col("edited_fingerprint")).alias("near_edited"), likeness(F.col("fingerprint"), F.col("next_fingerprint")).alias("near_next"))


def _sql_print(text: str) -> str:
    pieces = f"list_transform(regexp_extract_all(p, '{_PIECE}'), lambda x: md5(x))"
    return f"""(SELECT sha256(string_agg(md5(hs), '' ORDER BY i)) || string_agg('/' || md5(hs)[1:8] || shown, '' ORDER BY i) FROM
      (SELECT i, array_to_string(list_transform(ps, lambda q: md5(array_to_string(q, ''))), '') AS hs,
         array_to_string(list_transform(ps, lambda q: ',' || md5(array_to_string(q, ''))[1:8] || array_to_string(list_transform(q, lambda x: '.' || x[1:8]), '')), '') AS shown FROM
        (SELECT i, list_transform(string_split(s, chr(10)), lambda p: {pieces}) AS ps FROM
          (SELECT unnest(string_split({text}, chr(10) || chr(10))) AS s, unnest(range(len(string_split({text}, chr(10) || chr(10))))) AS i))))"""


OP5_SQL = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, length(coalesce(text, ''))::BIGINT AS n_chars FROM documents),
n AS (SELECT *, coalesce(lead(text) OVER (ORDER BY doc_id), first_value(text) OVER (ORDER BY doc_id)) AS next_text FROM d),
e AS (SELECT *, substring(text, 1, n_chars - n_chars // 4) || substring(next_text, 1, n_chars // 4) AS edited FROM n),
f AS (SELECT doc_id, n_chars, sha256(edited) AS edited_sha256, {_sql_print('e.text')} AS fingerprint, {_sql_print('e.edited')} AS edited_fingerprint, {_sql_print('e.next_text')} AS next_fingerprint FROM e),
g AS (SELECT *, list_distinct(regexp_extract_all(fingerprint, '\.([0-9a-f]{{8}})', 1)) AS x, list_distinct(regexp_extract_all(edited_fingerprint, '\.([0-9a-f]{{8}})', 1)) AS y,
        list_distinct(regexp_extract_all(next_fingerprint, '\.([0-9a-f]{{8}})', 1)) AS z FROM f)
SELECT doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint,
  CASE WHEN fingerprint[1:64] = edited_fingerprint[1:64] THEN 1.0::DOUBLE ELSE len(list_intersect(x, y))::DOUBLE / (len(x) + len(y) - len(list_intersect(x, y)) + 1) END AS near_edited,
  CASE WHEN fingerprint[1:64] = next_fingerprint[1:64] THEN 1.0::DOUBLE ELSE len(list_intersect(x, z))::DOUBLE / (len(x) + len(z) - len(list_intersect(x, z)) + 1) END AS near_next
FROM g
"""
