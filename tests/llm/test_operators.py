"""The training-data operators against brute force, and on odd input: nulls, empty and long texts, repeats, empty tables, clashing columns."""

import base64
import gzip
import hashlib
import itertools
import math
import random
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from partguard.llm import bpe, components, hyperdim, licenses, line_rules, merkle, nbsvm, near_dedup, packing, pfor, pieces, registry, token_files, warc

LONG = "lorem ipsum dolor " * 20_000
ODD = [
    (1, "The cat sat on the mat. It was happy there, and so were we.", "en"),
    (2, None, "en"),
    (3, "", None),
    (4, "  two  blanks \n\n and\tlines ", "en"),
    (5, "Der Hund lief über die Straße und bellte laut.", "de"),
    (5, "Der Hund lief über die Straße und bellte laut.", "de"),
    (6, "Der Hund lief über die Straße und bellte laut.", None),
    (7, LONG, "en"),
    (8, "12345 67890 !!!", "de"),
    (None, "No id at all, but some words to read in this line.", "en"),
    (9, "日本語 ▁ mark \U0001f600 <|endoftext|> don't", "de"),
]


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(i, t, lang, "s", 7, "x") for i, t, lang in ODD]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, score string, start long, kept string")


@pytest.fixture(scope="module")
def empty(odd):
    return odd.filter("1 = 0")


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.mark.parametrize("name", sorted(registry.SQL))
def test_matches_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    got, want = registry.QUERIES[name](spark, sf).toPandas(), con.execute(registry.SQL[name]).df()
    rows = lambda f: sorted(tuple("" if pd.isna(v) else repr(float(v)) if isinstance(v, (int, float)) else str(v) for v in r) for r in f[sorted(f.columns)].astype(object).itertuples(index=False))
    assert sorted(got.columns) == sorted(want.columns) and rows(got) == rows(want)


# 1 and 8: tokens ------------------------------------------------------------------------------------

def fresh(path):
    """The library's own tokenizer, as the file has it."""
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


SPECIAL = ["a <|endoftext|> b", "<|endoftext|>", "x<|endoftext|><|endoftext|>\n y", "<|startoftext|>a", "A <|ENDOFTEXT|> B", "a <| b |> c"]


@pytest.mark.parametrize("name,leads", [("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)])
def test_pieces_of_a_text_give_the_ids_of_the_whole(docs, name, leads):
    coder = bpe.PieceEncoder(bpe.public_file(name), leads, limit=50)
    texts = [r["text"] for r in docs.select("text").limit(60).collect()] + [t or "" for _, t, _ in ODD] + ["a  b", " lead", "trail ", "x\n y", "  nb", "a ́b", "10 0 00", "don't 's", "word*** word!!! word", *SPECIAL]
    rng, parts = random.Random(3), [" ", " ", " ", "  ", "\n", "\t", "\u3000", "\u200b", "\xa0", "é", "cat", "Dog's", "0", "42", "...", "_", "'", "ß", "日本", "\u0301", "<|endoftext|>", "\x1c", "\x85", "İ", "\u0958", "Ω", "ǅ"]
    texts += ["".join(rng.choices(parts, k=rng.randrange(12))) for _ in range(2000)]
    library = fresh(bpe.public_file(name))
    for _ in range(2):  # the second time some pieces are kept, others not
        for text, ids in zip(texts, coder.encode_many(texts)):
            assert np.frombuffer(ids, "<u4").tolist() == library.encode(text, add_special_tokens=False).ids, repr(text)
    assert len(coder.known) <= 50


def test_special_tokens_as_text():
    coder = bpe.PieceEncoder(bpe.public_file("byte_bpe_50k.json"), True, special_as_text=True)
    (ids,) = coder.encode_many(["a <|endoftext|> b"])
    assert 50256 not in np.frombuffer(ids, "<u4") and fresh(bpe.public_file("byte_bpe_50k.json")).decode(np.frombuffer(ids, "<u4").tolist()) == "a <|endoftext|> b"


@pytest.mark.parametrize("n", [0, 1, 255, 256, 257, 5000])
def test_blocks_round_trip(n):
    rng = np.random.default_rng(n)
    for high in (1, 2, 300, 50_000, 2**32 - 1):
        ids = rng.integers(0, high, n, dtype=np.uint64).astype("<u4")
        if n > 10:
            ids[rng.integers(0, n, 5)] = 2**32 - 1
        stream = pfor.pack(ids)
        assert (pfor.unpack(stream) == ids).all()
        assert (pfor.unpack(stream, 1, 2) == ids[256:512]).all()


def test_outliers_are_patched():
    ids = np.full(256, 7, "<u4")
    ids[3] = 60_000
    assert len(pfor.pack(ids)) < 64 and (pfor.unpack(pfor.pack(ids)) == ids).all()


def test_token_files(spark, odd, empty, tmp_path):
    path = bpe.public_file("byte_bpe_50k.json")
    token_files.write_token_files(odd, str(tmp_path / "a"), path)
    got = token_files.with_starts(token_files.read_token_files(spark, str(tmp_path / "a"), with_ids=True)).orderBy("start").collect()
    library = fresh(path)
    want = sorted(((-1 if i is None else i), t or "") for i, t, _ in ODD)
    start = 0
    for row, (i, text) in zip(got, want, strict=True):
        ids = library.encode(text, add_special_tokens=False).ids + [2]
        assert (row["doc_id"] if row["doc_id"] is not None else -1, row["start"], row["ids"]) == (i, start, ids)
        assert row["ids_crc32"] == zlib.crc32(np.array(ids, "<u4").tobytes())
        start += len(ids)
    token_files.write_token_files(odd, str(tmp_path / "c"), path, segment_ids=5, file_segments=2)
    again = token_files.with_starts(token_files.read_token_files(spark, str(tmp_path / "c"), with_ids=True)).orderBy("start").collect()
    assert [(r["doc_id"], r["start"], r["ids"]) for r in again] == [(r["doc_id"], r["start"], r["ids"]) for r in got]
    assert len(list((tmp_path / "c").glob("part-*"))) > len(list((tmp_path / "a").glob("part-*")))
    whole = max((tmp_path / "c").glob("part-*"), key=lambda x: x.stat().st_size).read_bytes()
    (tmp_path / "d").mkdir()
    (tmp_path / "d" / "empty").write_bytes(b"")
    assert token_files.read_token_files(spark, str(tmp_path / "d")).count() == 0
    for cut in (10, len(whole) - 9):
        with pytest.raises(ValueError):
            list(pfor.segments(whole[:cut]))
    token_files.write_token_files(empty, str(tmp_path / "b"), path)
    assert token_files.read_token_files(spark, str(tmp_path / "b")).count() == 0


def check_packed(rows, want, size=4096):
    by_doc, by_sequence = {}, {}
    for r in rows:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_sequence.setdefault(r["sequence_id"], []).append(r)
    for doc, ids in want.items():
        at = 0
        for r in sorted(by_doc[doc], key=lambda r: r["start"]):
            assert r["start"] == at and r["doc_tokens"] == len(ids)
            assert r["ids_crc32"] == zlib.crc32(np.array(ids[at : at + r["length"]], "<u4").tobytes())
            at += r["length"]
        assert at == len(ids)
    for got in by_sequence.values():
        at = 0
        for r in sorted(got, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= size
    return [sum(r["length"] for r in got) for got in by_sequence.values()]


def test_packing(spark, sf, docs, odd, empty):
    path = bpe.public_file("word_bpe_49k.json")
    library = fresh(path)
    want = {r["doc_id"]: library.encode(r["text"], add_special_tokens=False).ids + [2] for r in docs.collect()}
    fills = check_packed(packing.pack(docs.repartition(3), path).collect(), want)
    assert len(fills) * 4096 < 1.03 * sum(fills) + 4096
    distinct = odd.filter("doc_id is not null").dropDuplicates(["doc_id"])
    check_packed(packing.pack(distinct, path, size=64, windows=2, top_up=4).collect(), {i: library.encode(t or "", add_special_tokens=False).ids + [2] for i, t, _ in ODD if i is not None}, 64)
    assert packing.pack(odd, path).groupBy("doc_id").count().count() == len({i for i, _, _ in ODD})
    assert packing.pack(empty, path).count() == 0


# 2 and 6: classifiers ------------------------------------------------------------------------------------

def test_language(spark, sf, docs, odd, empty):
    got = registry.QUERIES["op2_language_id"](spark, sf).join(docs.select("doc_id", "lang"), "doc_id").toPandas()
    held = got[got.held_out]
    assert (held.lang == held.lang_pred).mean() > 0.97 and got.score.between(0, 1).all() and len(got) == docs.count()
    assert (got.held_out == [zlib.crc32(str(i).encode()) % 5 == 0 for i in got.doc_id]).all()
    langs, prototypes = hyperdim.train(docs)
    rows = hyperdim.predict(odd, langs, prototypes).collect()
    assert len(rows) == len(ODD)
    assert all((r["lang_pred"] == "und") == (not any(c.isalpha() for c in r["text"] or "")) for r in rows)
    assert hyperdim.train(empty)[0] == []
    assert hyperdim.predict(empty, langs, prototypes).count() == 0
    assert {r["lang_pred"] for r in hyperdim.predict(odd, [], np.zeros((0, 64))).collect()} == {"und"}


def test_language_stage_rejects_what_is_in_no_known_language(spark, docs):
    import corpus_pipeline

    rng = random.Random(1)
    noise = lambda n: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz    ") for _ in range(n))
    strange = ["Слава труду и миру во всём мире, и людям доброй воли", "日本語の文章です。今日は天気がいいですね。", "Ala ma kota, a kot ma psa; to jest zdanie po polsku.", "12 34", *(noise(n) for n in (20, 60, 600, 6000))]
    extra = spark.createDataFrame([(-1 - i, x, None, "s", len(x)) for i, x in enumerate(strange)], docs.schema)
    kept = [r["doc_id"] for r in corpus_pipeline.language(spark, docs.unionByName(extra), "").select("doc_id").collect()]
    clean = {r["doc_id"] for r in docs.collect() if sum(c.isalpha() for c in r["text"]) >= 100}
    assert not [i for i in kept if i < 0] and len(clean - set(kept)) <= 0.01 * len(clean)


def test_sum_of_products_is_the_cosine():
    texts = ["the quick brown fox", "der schnelle braune Fuchs"]
    space, dim = hyperdim.Space(256, 7), 256
    codes, index, doc = hyperdim.trigrams(texts)
    vectors = np.concatenate([v for _, v in space.bind(codes)]).astype(float)
    bundles = np.array([vectors[index[doc == k]].sum(0) for k in range(2)])
    prototype = np.random.default_rng(0).normal(size=dim)
    direct = bundles @ prototype
    summed = np.bincount(doc, weights=(vectors @ prototype)[index])
    assert np.allclose(direct, summed)
    a, b, c = (space.letter(ord(x)).astype(int) for x in "fox")
    fox = [v for k, v in zip(codes, vectors) if k == (ord("f") << 42) | (ord("o") << 21) | ord("x")][0]
    assert (fox == np.roll(a, 2) * np.roll(b, 1) * c).all()


def test_quality(spark, sf, docs, odd, empty):
    got = registry.QUERIES["op6_quality_classifier"](spark, sf).toPandas()
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    both = got.merge(labels.toPandas(), on="doc_id")
    held = both[both.held_out]
    assert (held.predicted == held.quality).mean() > 0.85 and ((got.score >= 0.5) == (got.predicted == 1)).all() and len(got) == docs.count()
    model = nbsvm.train(docs, labels)
    assert len(nbsvm.score(odd, model).filter("score between 0 and 1").collect()) == len(ODD)
    assert nbsvm.score(empty, model).count() == 0
    none = nbsvm.train(empty, labels)
    assert nbsvm.score(odd, none).agg(F.min("score")).first()[0] == pytest.approx(0.5)


# 3: pieces ------------------------------------------------------------------------------------------------

def toy():
    texts = [b"a", b"b", b"c", b"ab", b"bc", b"abc", "▁".encode(), "▁a".encode(), "é".encode()]
    return pieces.Pieces(list(range(9)), texts, [-2.0, -2.5, -2.0, -3.0, -3.5, -6.4, -1.0, -2.2, -3.0], list(range(9, 265)), texts + [b""] * 256, -1)


def best_of_all(p, text):
    """Every segmentation, by recursion."""
    keys = dict(zip(p.keys, p.scores))

    def go(rest):
        if not rest:
            return 0.0
        options = [keys[rest[:n]] + go(rest[n:]) for n in range(1, len(rest) + 1) if rest[:n] in keys]
        width = len(rest.decode()[0].encode())
        if rest[:width] not in keys:
            options.append(p.penalty + go(rest[width:]))
        return max(options)

    return go(text)


def test_segmentation_is_the_best():
    p, rng = toy(), random.Random(3)
    scores = dict(zip(p.ids, p.scores))
    for _ in range(200):
        text = "".join(rng.choice("abcé▁x") for _ in range(rng.randint(1, 9))).encode()
        ids = pieces.segment(p, text)
        unknown = sum(1 for ch in text.decode() if ch == "x")
        got = sum(scores[i] for i in ids if i in scores) + unknown * p.penalty
        assert got == pytest.approx(best_of_all(p, text))


def test_trie_holds_every_piece_and_no_other():
    p = pieces.Pieces.of_model(pieces.public_file("piece_bpe_32k.model"))
    known = set(p.keys)
    for k in random.Random(1).sample(range(len(p.keys)), 500):
        word = p.keys[k] + b"zq"
        assert {word[:end] for end, _ in p.trie.prefixes(word)} == {word[:n] for n in range(1, len(word) + 1) if word[:n] in known}


def test_pieces_round_trip(spark, sf, odd, empty):
    rows = registry.QUERIES["op3_pieces"](spark, sf).collect()
    assert all(r["round_trip"] for r in rows)
    got = pieces.encode(odd, pieces.public_file("piece_bpe_32k.model")).collect()
    assert all(r["round_trip"] for r in got) and all(r["n_pieces"] == 0 for r in got if not r["text"])
    assert pieces.encode(empty, pieces.public_file("piece_bpe_32k.model")).count() == 0
    p = pieces.Pieces.of_model(pieces.public_file("piece_bpe_32k.model"))
    for text in ("two  blanks\nand lines", "a b c"):
        cut = np.frombuffer(pieces.Encoder(p).encode(text), "<u4").tolist()
        assert cut == pieces.segment(p, ("▁" + text.replace(" ", "▁")).encode())


# 4, 5, 7, 9, 10 -----------------------------------------------------------------------------------------------

def test_repeated_words():
    rng = random.Random(7)
    for _ in range(100):
        words = [rng.choice("abc") for _ in range(rng.randint(0, 30))]
        windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
        covered = {i + k for i, w in enumerate(windows) if windows.count(w) > 1 for k in range(3)}
        assert line_rules.repeated_words(words) == len(covered)


def test_line_rules(spark, odd, empty):
    good = "\n".join(f"This is sentence number {i} about topic {i * i}." for i in range(20))
    bad = good + "\n" + "\n".join(" | ".join(f"{x}{i}" for x in ("home", "about", "help", "contact", "search", "login", "register", "more")) for i in range(12))
    made = spark.createDataFrame([(1, good), (2, bad), (3, good + "\nAll rights reserved.")], "doc_id long, text string")
    kept = {r["doc_id"]: (r["kept"], r["base_failed"], r["cleaned"]) for r in line_rules.clean(made, with_text=True).collect()}
    assert kept[1] == (True, False, good) and kept[2][:2] == (False, False) and kept[3] == (True, False, good)
    rows = line_rules.clean(odd).collect()
    assert len(rows) == len(ODD) and all(r["base_failed"] and not r["kept"] for r in rows)
    assert line_rules.clean(empty).count() == 0


def test_fingerprints(spark, odd, empty):
    got = merkle.with_next(odd).collect()
    assert len(got) == len(ODD)
    by_text = {}
    for r in got:
        by_text.setdefault(r["text"], set()).add(r["fingerprint"])
    assert all(len(x) == 1 for x in by_text.values()) and len({next(iter(x)) for x in by_text.values()}) == len(by_text)
    heads = {r["doc_id"]: r["head"] for r in got}
    assert heads[9] == "No id at all, but some words to read in this line."[: len(ODD[-1][1]) // 4] and heads[1] == ""
    assert merkle.with_next(empty).count() == 0
    pair = spark.createDataFrame([("a b.\nc d.\ne f.", "a b.\nc x.\ne f.", "a b.\nc d.\ne f.")], "a string, b string, c string").select(*(merkle.fingerprint(F.col(c)).alias(c) for c in "abc"))
    diff, none, near = pair.select(merkle.differing(F.col("a"), F.col("b")), merkle.differing(F.col("a"), F.col("c")), merkle.likeness(F.col("a"), F.col("b"))).first()
    assert [(d["section"], d["paragraph"]) for d in diff] == [(0, 1)] and none == [] and 0 < near < 1


def brute_components(texts, size, percent):
    sets = {}
    for i, t in texts:
        words = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if c.isascii() else c for c in t or ""))
        sets[i] = {tuple(words[k : k + size]) for k in range(len(words) - size + 1)} or ({tuple(words)} if words else set())
    parent = {i: i for i in sets}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a, b in itertools.combinations(sets, 2):
        shared = len(sets[a] & sets[b])
        if shared and 100 * shared >= percent * (len(sets[a]) + len(sets[b]) - shared):
            x, y = sorted((find(a), find(b)))
            parent[y] = x
    return {i: (len(s), find(i)) for i, s in sets.items()}


def test_near_duplicates(spark, odd, empty):
    rng = random.Random(5)
    base = [f"w{rng.randint(0, 400)}" for _ in range(120)]
    texts = []
    for i in range(120):
        words = list(base) if i < 90 else [f"v{rng.randint(0, 400)}" for _ in range(rng.randint(0, 100))]
        for _ in range(rng.choice([0, 1, 2, 5, 9, 14])):
            if words:
                words[rng.randrange(len(words))] = f"e{rng.randint(0, 10**6)}"
        texts.append((i, " ".join(words)))
    frame = spark.createDataFrame(texts, "doc_id long, text string")
    for size in (2, 5):
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dedup.near_duplicates(frame, shingle=size).collect()}
        assert got == brute_components(texts, size, 80)
    rows = near_dedup.near_duplicates(odd).collect()
    assert len(rows) == len(ODD) and {r["component_id"] for r in rows if r["doc_id"] in (5, 6)} == {5}
    assert all(r["kept"] and r["component_id"] is None for r in rows if r["doc_id"] is None)
    assert near_dedup.near_duplicates(empty).count() == 0


def test_components(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 101), (101, 105), (103, 105), (7, 7)]
    got = {r["id"]: r["component"] for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100, 105: 100, 103: 100}


def test_licences(spark, odd, empty):
    made = spark.createDataFrame([
        (1, "p/LICENSE", "Released under the MIT License."), (2, "p/a/b/code.txt", "nothing to see here"), (3, "p/a/own.txt", "words\nLicensed under the Apache License, Version 2.0.\nmore\nwords"),
        (4, "q/alone.txt", "The license of the fishing boat was granted."), (5, None, "plain"), (6, "p/long.txt", "word " * 900 + "Licensed under CC BY-NC 4.0. " + "word " * 900),
    ], "doc_id long, path string, text string")
    got = {r["doc_id"]: (r["own_license"], r["license"], r["inherited_from"], r["permissive"]) for r in licenses.scan(made).collect()}
    assert got[1] == ("MIT", "MIT", None, True) and got[2] == (None, "MIT", "p/LICENSE", True) and got[3] == ("Apache-2.0", "Apache-2.0", None, True)
    assert got[4] == (None, None, None, False) and got[5] == (None, None, None, False)
    rows = licenses.scan(odd.withColumn("path", F.lit("a/b.txt")).withColumn("license", F.lit(1))).collect()
    assert len(rows) == len(ODD)
    assert licenses.scan(empty.withColumn("path", F.lit("a"))).count() == 0


@pytest.mark.parametrize("n", [20, 3000])
def test_licences_do_not_depend_on_the_number_of_files(spark, n):
    other = spark.range(n).selectExpr("id AS doc_id", "concat('p/', id) AS path", "if(id % 2 = 0, 'this small old file here is under the hill', 'nothing') AS text")
    made = spark.createDataFrame([(-1, "n/a.txt", "This small old file here is released under the MIT License."), (-2, "n/b.txt", "Bxqz is licensed under the Apache License, Version 2.0.")], "doc_id long, path string, text string")
    rows = licenses.scan(other.union(made)).collect()
    assert len(rows) == n + 2 and {r["doc_id"]: r["own_license"] for r in rows if r["own_license"]} == {-1: "MIT", -2: "Apache-2.0"}


def test_licences_inside_long_lines(spark):
    grant = licenses.TEMPLATES[4][1]
    prose = lambda k, n: " ".join(f"w{(k * 31 + i * 7) % 50}" for i in range(n))
    texts = {1: ("CC-BY-NC-4.0", "word " * 900 + "Licensed under CC BY-NC 4.0. " + "word " * 900), 2: ("MIT", f"{prose(2, 100)} {grant} {prose(3, 100)}")}
    texts |= {10 + k: ("MIT", f"{prose(k, 400 + k)} Released under the MIT License. {prose(k, 300)}") for k in range(24)}
    texts |= {40 + k: ("MIT", f"{prose(k, 800 + k)} {grant} {prose(k, 300)}") for k in range(24)}
    texts |= {70: (None, f"{prose(1, 50)} all rights to the boat, released under the bridge {prose(1, 50)}"), 71: (None, "SPDX-License-Identifier: Zlib")}
    rows = licenses.scan(spark.createDataFrame([(i, f"p/{i}", t) for i, (_, t) in texts.items()], "doc_id long, path string, text string")).collect()
    assert {r["doc_id"]: r["own_license"] for r in rows} == {i: want for i, (want, _) in texts.items()}


def test_licence_files_and_wrapped_headers(spark):
    files = [(f"{x}/LICENSE", x, text) for x, text in licenses.FULL]
    mit = dict(licenses.FULL)["MIT"].replace("<year> <copyright holders>", "2020 Zorblax Qwrt Industries")
    files += [("own/COPYING.txt", "MIT", mit), ("code/a.c", "Apache-2.0", "/* Foo\n * Licensed under the\n * Apache License, Version\n * 2.0.\n */\nint main() { return 0; }\n" + "x = y + z;\n" * 20)]
    files += [("both/NOTICE", "Apache-2.0", "Licensed under the Apache License, Version 2.0.\nReleased under the MIT License.")]
    below = [(f"{p.split('/')[0]}/src/deep/x.c", None, "int x = 1;") for p, _, _ in files]
    prose = [(f"prose/{i}", None, "the work of the day and the rights of the people under the law to be in this and that or any other form " * 9) for i in range(30)]
    rows = licenses.scan(spark.createDataFrame([(p, t) for p, _, t in files + below + prose], "path string, text string")).collect()
    got = {r["path"]: r for r in rows}
    assert {p: got[p]["own_license"] for p, _, _ in files + below + prose} == {p: x for p, x, _ in files + below + prose}
    for p, x, _ in files:
        under = got[f"{p.split('/')[0]}/src/deep/x.c"]
        assert (under["license"], under["inherited_from"]) == ((None, None) if p == "code/a.c" else (x, p))
    assert got["code/a.c"]["n_matched"] == 3 and got["both/NOTICE"]["n_matched"] == 2 and got["own/COPYING.txt"]["permissive"]


TRICKY = "x\r\n\r\nWARC/1.1\r\nContent-Length: 5\r\n\r\ny"


@pytest.fixture(scope="module")
def few_pages(spark):
    rows = [(3, "http://a.b/c d#e", "<p>é</p>", 1), (1, "https://h", "<p>é</p>", 1), (2, None, None, 1), (4, "u", "", 1), (5, "http://z/?q=1", TRICKY, 1), (None, "n", "<p>é</p>", 1), (6, "r", "same", 1), (6, "r", "same", 1), (7, "s", "same", 1)]
    return spark.createDataFrame(rows, "page_id long, url string, html string, digest int")


@pytest.mark.parametrize("level", [6, None])
def test_archives(spark, few_pages, tmp_path, level):
    warc.write_warc(warc.transactions(few_pages), str(tmp_path / "w"), level=level)
    records = warc.read_records(spark, str(tmp_path / "w"), with_payload=True, batch_rows=2)
    every = records.collect()
    got = warc.with_referred(warc.assemble(records)).collect()
    assert len(got) == 9 and all(r["request"] is not None for r in got) and len({r["record_id"] for r in every}) == len(every) == 27
    by_id = {r["page_id"]: r for r in got}
    assert by_id[3]["type"] == "revisit" and by_id[3]["referred_page"] == 1 and by_id[4]["type"] == "revisit" and by_id[4]["referred_page"] == 2
    assert bytes(by_id[5]["payload"]).decode() == TRICKY and by_id[5]["payload_bytes"] == len(TRICKY)
    assert by_id[3]["digest"] == "sha1:" + base64.b32encode(hashlib.sha1("<p>é</p>".encode()).digest()).decode() and by_id[3]["payload_bytes"] == len("<p>é</p>".encode())
    assert by_id[None]["type"] == "revisit" and by_id[None]["referred_page"] == 1
    assert [r["type"] for r in got if r["page_id"] == 6] == ["response", "response"] and by_id[7]["referred_page"] == 6
    assert by_id[3]["request"]["line"] == "GET /cd HTTP/1.1" and by_id[1]["request"]["line"] == "GET / HTTP/1.1"
    answers = {r["record_id"]: r for r in every if r["type"] == "response"}
    assert all(bytes(answers[r["refers_to"]]["payload"]) == {1: "<p>é</p>", 2: "", 6: "same"}[r["referred_page"]].encode() for r in got if r["type"] == "revisit")
    warc.write_warc(warc.transactions(few_pages, min_bytes=5), str(tmp_path / "m"), level=level)
    small = {r["page_id"]: r["type"] for r in warc.assemble(warc.read_records(spark, str(tmp_path / "m"))).collect()}
    assert small[4] == "response" and small[3] == "revisit"
    warc.write_warc(warc.transactions(few_pages.filter("1 = 0")), str(tmp_path / "e"), level=level)
    assert warc.read_records(spark, str(tmp_path / "e")).count() == 0


def test_archives_have_a_member_for_each_record_and_bounded_files(spark, sf, tmp_path):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    warc.write_warc(warc.transactions(pages.coalesce(1)).coalesce(1), str(tmp_path / "w"), chunk_bytes=4000, file_chunks=3)
    files = sorted((tmp_path / "w").glob("part-*"))
    sizes, longest, n = [], 0, 0
    for file in files:
        raw = file.read_bytes()
        sizes.append(len(raw))
        while raw:
            member = zlib.decompressobj(31)
            text = member.decompress(raw)
            assert member.eof and len(list(warc.records_in([text]))) == 1
            longest, n, raw = max(longest, len(raw) - len(member.unused_data)), n + 1, member.unused_data
    assert n == 3 * pages.count() and len(files) >= sum(sizes) // (3 * (4000 + longest + 2000)) > 0 and max(sizes) <= 3 * (4000 + longest + 2000)


def test_archives_of_others(spark, tmp_path):
    one = b"WARC/1.0\r\nwarc-type: response\r\nWARC-Record-ID: <a>\r\nContent-Length: 22\r\n\r\nHTTP/1.1 200 OK\r\n\r\nabc\r\n\r\n"
    two = b"WARC/1.0\r\nWARC-Type: warcinfo\r\nWARC-Record-ID: <b>\r\nX-Empty:\r\nContent-Length: 0\r\n\r\n\r\n\r\n"
    long = b"WARC/1.0\r\nWARC-Type: resource\r\nWARC-Record-ID: <c>\r\nContent-Length: 17000000\r\n\r\n" + b"0123456789abcdefg" * 1_000_000 + b"\r\n\r\n"
    (tmp_path / "w").mkdir()
    (tmp_path / "w" / "stream.warc.gz").write_bytes(gzip.compress(one + two + long + one))
    (tmp_path / "w" / "plain.warc").write_bytes(one + b"\r\n" + two)
    (tmp_path / "w" / "none.warc").write_bytes(b"")
    got = warc.read_records(spark, str(tmp_path / "w"), with_payload=True).collect()
    assert sorted(r["record_id"] for r in got) == ["<a>", "<a>", "<a>", "<b>", "<b>", "<c>"]
    assert {(r["payload_bytes"], bytes(r["payload"])) for r in got if r["type"] == "response"} == {(3, b"abc")}
    for cut in (gzip.compress(one)[:-3], one[:-9]):
        with pytest.raises(ValueError):
            list(warc.records_in(warc._inflated(memoryview(cut))))


def test_long_records_end_as_the_separator_needs(spark, tmp_path):
    pages = spark.createDataFrame([(1, "u", "0123456789abcdef" * 1_100_000), (2, "v", "x")], "page_id long, url string, html string").coalesce(1)
    warc.write_warc(warc.transactions(pages), str(tmp_path / "w"))
    got = warc.read_records(spark, str(tmp_path / "w")).filter("type = 'response'").select("payload_bytes").collect()
    assert sorted(r[0] for r in got) == [1, 17_600_000]


def test_pipeline(spark, sf, docs):
    import corpus_pipeline

    kept = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, sf)
        assert kept.columns == docs.columns, name
    ids = {r["doc_id"] for r in kept.select("doc_id").collect()}
    pieces_ = corpus_pipeline.run(spark, sf).select("doc_id").distinct().collect()
    assert {r["doc_id"] for r in pieces_} == ids and 0.5 * docs.count() < len(ids) < docs.count()
    texts = [(r["doc_id"], r["text"]) for r in kept.collect()]
    assert all(c == i for i, (_, c) in brute_components(texts, 5, 80).items())


def test_classifier_against_a_plain_solver():
    rng = np.random.default_rng(8)
    rows = [np.unique(rng.integers(0, 30, 6) + (8 if i % 2 else 0)).astype(np.int64) for i in range(40)]
    labels = np.array([i % 2 for i in range(40)])
    model = nbsvm.fit(rows, labels, epochs=3000)
    seen, size = {s: Counter(int(f) for r, y in zip(rows, labels) if y == s for f in r) for s in (0, 1)}, 1 << nbsvm._BITS
    ratio = {f: math.log((seen[1][f] + 1) / (sum(seen[1].values()) + size)) - math.log((seen[0][f] + 1) / (sum(seen[0].values()) + size)) for f in range(38)}
    x = np.zeros((40, 39))
    for i, r in enumerate(rows):
        x[i, r] = [ratio[int(f)] / math.sqrt(len(r)) for f in r]
    x[:, 38] = 1  # the bias is a weight like the others
    y = np.where(labels > 0, 1.0, -1.0)
    gram = (x @ x.T) * np.outer(y, y)
    alpha, step = np.zeros(40), 1 / np.linalg.eigvalsh(gram)[-1]
    for _ in range(200_000):
        alpha = np.clip(alpha - step * (gram @ alpha - 1), 0, 1)
    want = x @ (x.T @ (alpha * y))
    got = np.array([model.weights[r].sum() / math.sqrt(len(r)) + model.bias for r in rows])
    assert np.abs(got - want).max() < 0.02
