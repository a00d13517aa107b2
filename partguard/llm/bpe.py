"""Whole-text encoding with public tokenizer files, by remembered pieces between blanks."""

from __future__ import annotations

import os
import re
import unicodedata
from itertools import filterfalse, islice

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: White space: a blank that touches another of these, or an end of the text, is not a safe place to cut.
_SPACES = frozenset([c for c in map(chr, range(0x3001)) if c.isspace()] + ["\u180e", "\u200b"])
_SAFE_CUT = re.compile(r"(?<=[^\s\u180e\u200b]) (?=[^\s\u180e\u200b])")

#: Marks at the end of a piece, but for the apostrophe and the underscore.
_MARKS = re.compile(r"(?<=.)[!-&(-/:-@\[-^`{-~]+$")

#: Letters whose lower case and composed form are plain; and how byte-level vocabularies spell the bytes of such letters.
_LATIN = re.compile(r"[A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+").fullmatch
_SHOWN = {*range(33, 127), *range(161, 173), *range(174, 256)}
_BYTE_LETTERS = {b: 256 + k for k, b in enumerate(b for b in range(256) if b not in _SHOWN)}

#: Pieces whose ids are put in place at a time.
_BLOCK = 1 << 20


def _stays_letter(c: str) -> bool:
    """Whether a letter is one without marks also in lower case and composed: otherwise its mark joins the marks after it."""
    return c.isalpha() and (c.isascii() or unicodedata.normalize("NFC", c).lower().isalpha())


class PieceEncoder:
    """Ids of whole texts as little-endian uint32 bytes, equal to those of ``Tokenizer.encode(text, add_special_tokens=False)``.

    A single blank between two other characters always ends a pre-token, both where the blank
    belongs to the next word (``blank_leads``) and where white space is dropped. So a text is cut
    there, and the ids of the first ``limit`` different pieces that a worker meets are kept; other
    pieces go to the library again. Arrow splits the texts and finds the different pieces of a
    batch, so Python sees each of them once a batch. A text with a mark that could start a special
    token's string goes to the library whole, which gives such a string the token's id, as that
    call does; with ``special_as_text`` it is ordinary text.
    """

    def __init__(self, path: str, blank_leads: bool, limit: int = 800_000, special_as_text: bool = False):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import CharDelimiterSplit

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = special_as_text
        added = [] if special_as_text else [x.content for x in self.tokenizer.get_added_tokens_decoder().values()]
        #: No text without one of these holds an added token, in any case of letters.
        self.signs = sorted({re.match(r"[^\w\s]+|.+", x, re.DOTALL)[0] for x in added})
        self.known: dict[str, bytes] = {} if blank_leads else {"": b""}
        self.known_first: dict[str, bytes] = {}
        self.marks: dict[str, bytes] = {}
        self.limit = limit
        self.blank = " " if blank_leads else ""
        self.words = Tokenizer(self.tokenizer.model)
        self.words.pre_tokenizer = CharDelimiterSplit("\n")
        if blank_leads:  # a piece starts at each token that starts with a blank
            lead = self.tokenizer.encode(" ", add_special_tokens=False).tokens[0]
            self.starts = np.zeros(self.tokenizer.get_vocab_size(), bool)
            self.starts[[i for x, i in self.tokenizer.get_vocab().items() if x.startswith(lead)]] = True
        else:  # a lone digit is always a word of its own: it parts pieces that have none
            (self.digit,) = self.tokenizer.encode("0", add_special_tokens=False).ids
            self.ends = np.zeros(self.tokenizer.get_vocab_size(), bool)
            self.ends[[i for x, i in self.tokenizer.get_vocab().items() if x.endswith("</w>")]] = True

    def _singly(self, pieces: list[str], blank: str) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch_fast([blank + x for x in pieces], add_special_tokens=False)]

    def _plain(self, words: list[str]) -> dict[str, bytes]:
        """Ids of pieces of Latin letters alone. Such a piece is one pre-token, so the library's model gets it as it is, without its regular expressions."""
        spelt = [x if x.isascii() else x.encode().decode("latin-1").translate(_BYTE_LETTERS) for x in (words if self.blank else map(str.lower, words))]
        joined = "\u0120" + "\n\u0120".join(spelt) if self.blank else "\n".join(spelt)
        ids = np.array(self.words.encode_batch_fast([joined], add_special_tokens=False)[0].ids, "<u4")
        if self.blank:
            begins = np.flatnonzero(self.starts[ids]).tolist()
            ends = [*begins[1:], len(ids)]
        else:
            ends = (np.flatnonzero(self.ends[ids]) + 1).tolist()
            begins = [0, *ends[:-1]]
        if len(ends) != len(words):
            return self._library(words)
        raw = ids.tobytes()
        return {x: raw[4 * i : 4 * j] for x, i, j in zip(words, begins, ends)}

    def _library(self, pieces: list[str]) -> dict[str, bytes]:
        """Ids of pieces that stood after a blank: joined to one text, for a call for each piece costs ten times as much."""
        plain = [x for x in pieces if x and "0" not in x] if not self.blank else pieces
        joined = " " + " ".join(plain) if self.blank else " 0 ".join(plain)
        ids = np.array(self.tokenizer.encode_batch_fast([joined], add_special_tokens=False)[0].ids, "<u4")
        raw = ids.tobytes()
        if self.blank:
            ends = [*np.flatnonzero(self.starts[ids]).tolist()[1:], len(ids)]
            begins = [0, *ends[:-1]]
        else:
            at = np.flatnonzero(ids == self.digit).tolist()
            begins, ends = [0, *(x + 1 for x in at)], [*at, len(ids)]
        if len(ends) != len(plain):  # cannot happen while the cuts are safe; then nothing is taken from the joined text
            return dict(zip(pieces, self._singly(pieces, self.blank)))
        out = {x: raw[4 * i : 4 * j] for x, i, j in zip(plain, begins, ends)}
        if len(out) < len(pieces):
            rest = [x for x in pieces if x not in out]
            out.update(zip(rest, self._singly(rest, self.blank)))
        return out

    def _made(self, pieces: list[str]) -> dict[str, bytes]:
        """Ids of new pieces. ASCII marks after a letter are a pre-token of their own, so word and marks are looked up apart."""
        parted, words, known = [], dict.fromkeys(x for x in pieces if x.isalpha()), self.known
        for x in pieces:
            if x in words:
                continue
            m = _MARKS.search(x)
            if m and _stays_letter(x[m.start() - 1]):
                parted.append((x, x[: m.start()], m[0]))
            else:
                words[x] = None
        missing = list({w for _, w, _ in parted if w not in known} | words.keys())
        plain = list(filter(_LATIN, missing))
        out = self._plain(plain) if plain else {}
        if len(out) < len(missing):
            out.update(self._library([x for x in missing if x not in out]))
        new = list({m for _, _, m in parted if m not in self.marks})
        self.marks.update(zip(new, self._singly(new, "")))
        for x, w, m in parted:
            out[x] = (out.get(w) or known[w]) + self.marks[m]
        if len(self.marks) > self.limit:
            self.marks.clear()
        return out

    def _special(self, texts: pa.Array) -> np.ndarray:
        found = np.zeros(len(texts), bool)
        for sign in self.signs:
            found |= pc.match_substring(texts, sign, ignore_case=any(map(str.isalpha, sign))).to_numpy(zero_copy_only=False)
        return found

    def _whole(self, text: str, special: bool) -> bytes:
        """Ids of a text that must not be cut at every blank."""
        if special or not self.blank:
            return self._singly([text], "")[0]
        first, *rest = _SAFE_CUT.split(text)
        made = self._made([x for x in dict.fromkeys(rest) if x[-1] not in _SPACES]) if rest else {}
        return self._singly([first], "")[0] + b"".join(made[x] if x in made else self._singly([x], self.blank)[0] for x in rest)

    def encode_flat(self, texts: pa.Array, end_id: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts (strings, none null) in one array, and each text's number of them; ``end_id`` is put after each text."""
        n = len(texts)
        if not n:
            return np.zeros(0, "<u4"), np.zeros(0, np.int64)
        cut = pc.split_pattern(texts.cast(pa.large_string()), " ")
        bounds = cut.offsets.to_numpy().astype(np.int64)
        coded = cut.values.slice(bounds[0], bounds[-1] - bounds[0]).dictionary_encode()
        bounds = bounds - bounds[0]
        at, words = coded.indices.to_numpy().astype(np.int64), coded.dictionary.to_numpy(zero_copy_only=False).tolist()
        entries = list(map(self.known.get, words))
        unknown = [i for i, x in enumerate(entries) if x is None]
        special = self._special(texts)
        odd = special.copy()
        edge = np.zeros((2, len(words)), bool)  # pieces that start or end with white space, or are empty: the cuts beside them are not safe
        if self.blank:
            for i in unknown:
                w = words[i]
                if not w.isalpha() and (not w or w[0] in _SPACES or w[-1] in _SPACES):
                    edge[:, i] = not w or w[0] in _SPACES, not w or w[-1] in _SPACES
            bad = np.flatnonzero(edge[1, at[:-1]] | edge[0, at[1:]])  # a cut after piece i, or the end of a text
            bad = bad[~np.isin(bad + 1, bounds)]
            odd[np.searchsorted(bounds, bad, side="right") - 1] = True
        keep = np.ones(len(at), bool)
        for k in np.flatnonzero(odd):
            keep[bounds[k] : bounds[k + 1]] = False
        inner = keep.copy()
        inner[bounds[:-1]] = False
        needed = np.zeros(len(words), bool)
        needed[at[inner]] = True
        single = [i for i in np.flatnonzero(needed & edge[1]).tolist() if words[i]]
        for i, ids in zip(single, self._singly([words[i] for i in single], self.blank)):
            entries[i] = ids
        needed &= ~edge[1]
        plain = [i for i, x in zip(unknown, needed[unknown].tolist()) if x]
        new = self._made([words[i] for i in plain]) if plain else {}
        for i in plain:
            entries[i] = new[words[i]]
        # entries of first pieces, of texts that are not cut, and of the end follow those of the words
        first = [words[i] for i in at[bounds[:-1]].tolist()]
        absent = list(set(filterfalse(self.known_first.__contains__, (x for x, o in zip(first, odd.tolist()) if not o))))
        self.known_first.update(zip(absent, self._singly(absent, "")))
        for i in np.flatnonzero(~needed).tolist():
            entries[i] = entries[i] or b""
        m = len(entries)
        entries += [self._whole(texts[k].as_py(), bool(special[k])) if odd[k] else self.known_first[x] for k, x in enumerate(first)]
        at[bounds[:-1]] = np.arange(m, m + n)
        keep[bounds[:-1]] = True
        pieces = np.add.reduceat(keep.astype(np.int64), bounds[:-1])
        at = at[keep]
        if end_id is not None:
            entries.append(np.array([end_id], "<u4").tobytes())
            at = np.insert(at, np.cumsum(pieces), len(entries) - 1)
            pieces = pieces + 1
        sizes = np.fromiter(map(len, entries), np.int64, len(entries)) >> 2
        places, store = np.cumsum(sizes) - sizes, np.frombuffer(b"".join(entries), "<u4")
        each = sizes[at]
        out = np.empty(int(each.sum()), "<u4")
        done = 0
        for i in range(0, len(at), _BLOCK):
            some = each[i : i + _BLOCK]
            total = int(some.sum())
            out[done : done + total] = store[np.repeat(places[at[i : i + _BLOCK]] - (np.cumsum(some) - some), some) + np.arange(total)]
            done += total
        self.known.update(islice(new.items(), max(0, self.limit - len(self.known))))
        for x in absent[: max(0, len(self.known_first) - self.limit)]:
            del self.known_first[x]
        return out, np.add.reduceat(each, np.cumsum(pieces) - pieces)

    def encode_many(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as bytes."""
        ids, counts = self.encode_flat(pa.array(texts, pa.string()))
        raw, ends = ids.tobytes(), np.cumsum(counts).tolist()
        return [raw[4 * a : 4 * b] for a, b in zip([0, *ends], ends)]


_ENCODERS: dict[tuple[str, bool], PieceEncoder] = {}


def encoder(path: str, blank_leads: bool) -> PieceEncoder:
    """One encoder for each file and Python worker."""
    if (path, blank_leads) not in _ENCODERS:
        _ENCODERS[path, blank_leads] = PieceEncoder(path, blank_leads)
    return _ENCODERS[path, blank_leads]


def public_file(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))
