"""Whole-text encoding with a tokenizer file, at the speed of its distinct words.

Both tokenizer files cut a text into pieces and encode each piece by itself, so the ids of a text are
the ids of its pieces one after another. Each distinct piece goes through the tokenizers library
once per worker and is then looked up. The cut is made here only for texts whose characters are all
below U+0250, with character classes taken from that range; any other text, any text that holds the
string of an added token (which the library gives its own id), and any file whose pieces are not
known to be independent, goes through the library whole.
"""

from __future__ import annotations

import json
import os
import re
import unicodedata
from itertools import chain

import numpy as np
import regex
from tokenizers import Tokenizer

#: Distinct pieces kept in a worker (some 0.17 MB a thousand); what is new beyond that is encoded each time it comes.
STORE = 800_000
_LIMIT = 0x250
_OTHER = re.compile(f"[^\\x00-{chr(_LIMIT - 1)}]|\\u0130")


def _class(kind: str) -> str:
    """The characters of a Unicode class below the limit, as ranges of a pattern."""
    inside, out = [c for c in range(_LIMIT) if regex.match(kind, chr(c))], []
    for c in inside:
        if out and out[-1][1] == c - 1:
            out[-1][1] = c
        else:
            out.append([c, c])
    return "".join(f"\\u{a:04x}-\\u{b:04x}" for a, b in out)


def _patterns() -> dict[str, re.Pattern]:
    letter, number, space = _class(r"\p{L}"), _class(r"\p{N}"), _class(r"\s")
    short = "'s|'t|'re|'ve|'m|'ll|'d"
    return {
        "bytes": re.compile(f"{short}| ?[{letter}]+| ?[{number}]+| ?[^{space}{letter}{number}]+|[{space}]+(?![^{space}])|[{space}]+"),
        "words": re.compile(f"{short}|[{letter}]+|[{number}]|[^{space}{letter}{number}]+"),
    }


class Encoder:
    """encode(text) -> ids, equal to those of the library for the whole text.

    With ``special_as_text`` the strings of special tokens in a text are ordinary text, as the
    library has it with ``encode_special_tokens``; by default they get their own ids.
    """

    def __init__(self, path: str, store: int | None = None, special_as_text: bool = False):
        self.store = store or STORE
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self.library = Tokenizer.from_file(path)
        self.library.encode_special_tokens = special_as_text
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        added = [t for t in spec.get("added_tokens") or [] if not (special_as_text and t.get("special"))]
        self.added = re.compile("|".join(re.escape(t["content"]) for t in added), re.I) if added else None
        self.kind = self._kind(spec)
        self.cut = _patterns().get(self.kind)
        self._clear()

    @staticmethod
    def _kind(spec: dict) -> str:
        pre, norm = spec.get("pre_tokenizer") or {}, spec.get("normalizer")
        if pre.get("type") == "ByteLevel" and norm is None and pre.get("use_regex", True) and not pre.get("add_prefix_space"):
            return "bytes"
        if pre.get("type") == "Sequence" and [x["type"] for x in (norm or {}).get("normalizers", [])] == ["NFC", "Replace", "Lowercase"]:
            first = pre["pretokenizers"][0]
            if first["type"] == "Split" and first["pattern"].get("Regex") == r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+":
                return "words"
        return "whole"

    def _clear(self) -> None:
        self.place: dict[str, int] = {}
        self.first, self.count, self.pieces = np.zeros(1024, np.int64), np.zeros(1024, np.int32), 0
        self.ids, self.used = np.zeros(1 << 16, np.uint32), 0

    def _encoded(self, new: list[str], apart: bool) -> tuple[np.ndarray, np.ndarray]:
        """The ids of pieces one after another, and how many each has.

        Pieces that stay apart in a joined text are encoded as one text, which spares an object for
        each; that they did stay apart shows in the number of words the library counts.
        """
        if apart:
            got = self.library.encode((" " if self.kind == "words" else "").join(new), add_special_tokens=False)
            words = got.word_ids
            if words and None not in words and words[-1] + 1 == len(new):
                return np.array(got.ids, np.uint32), np.bincount(np.array(words, np.int64), minlength=len(new))
        each = [e.ids for e in self.library.encode_batch_fast(new, add_special_tokens=False)]
        return np.array([i for ids in each for i in ids], np.uint32), np.array([len(ids) for ids in each], np.int64)

    def _append(self, new: list[str], place: dict[str, int]) -> None:
        alone = [] if self.kind == "words" else [p for p in new if not (p[0] == " " and p[1:].isalpha())]
        others = set(alone)
        for some, apart in (([p for p in new if p not in others], True), (alone, False)):
            if not some:
                continue
            ids, counts = self._encoded(some, apart)
            need, n = self.used + len(ids), self.pieces + len(some)
            if n > len(self.first):
                self.first, self.count = (np.concatenate([x, np.zeros(n, x.dtype)]) for x in (self.first, self.count))
            if need > len(self.ids):
                self.ids = np.concatenate([self.ids, np.zeros(need, np.uint32)])
            self.count[self.pieces : n] = counts
            self.first[self.pieces : n] = self.used + np.cumsum(counts) - counts
            self.ids[self.used : need] = ids
            place.update(zip(some, range(self.pieces, n), strict=True))
            self.used, self.pieces = need, n

    def encode(self, text: str) -> np.ndarray:
        """The ids of a whole text, as unsigned 32-bit integers."""
        return self.encode_all([text])[0]

    def encode_all(self, texts: list[str]) -> list[np.ndarray]:
        """The ids of each of some whole texts; their new pieces are learned together."""
        out: list[np.ndarray | None] = [None] * len(texts)
        rows, found = [], []
        for k, text in enumerate(texts):
            plain = text.isascii() or _latin(text)
            small = text
            if self.kind == "words":  # characters below U+0100 are composed already
                small = (text if plain else unicodedata.normalize("NFC", text)).lower()
            if self.cut is None or self._has_added(text) or not plain and (_OTHER.search(text) or _OTHER.search(small)):
                out[k] = np.array(self.library.encode(text, add_special_tokens=False).ids, np.uint32)
                continue
            rows.append(k)
            found.append(self.cut.findall(small))
        for k, ids in zip(rows, self._looked_up(found), strict=True):
            out[k] = ids
        return out

    def _has_added(self, text: str) -> bool:
        """Letter case aside, since an added token may be matched after lower-casing."""
        return self.added is not None and self.added.search(text) is not None

    def _looked_up(self, found: list[list[str]]) -> list[np.ndarray]:
        sizes = np.array([len(f) for f in found], np.int64)
        flat = list(chain.from_iterable(found))
        at = np.array(list(map(self.place.get, flat)), np.float64)  # None becomes nan
        missing, mark = np.flatnonzero(np.isnan(at)).tolist(), None
        if missing:
            new = list(dict.fromkeys([flat[k] for k in missing]))
            place = self.place
            if self.pieces + len(new) > self.store:
                place, mark = {}, (self.pieces, self.used)
            self._append(new, place)
            at[missing] = [place[flat[k]] for k in missing]
        which = at.astype(np.int64)
        counts = self.count[which]
        ends = np.concatenate([[0], np.cumsum(counts, dtype=np.int64)])
        spots = np.arange(int(ends[-1]))
        spots += np.repeat(self.first[which] - ends[:-1], counts)
        ids = self.ids[spots]
        if mark:
            self.pieces, self.used = mark
        cuts = ends[np.concatenate([[0], np.cumsum(sizes)])].tolist()
        return [ids[x:y] for x, y in zip(cuts, cuts[1:], strict=False)]


def _latin(text: str) -> bool:
    """All characters below U+0100; found at the speed of a copy."""
    try:
        text.encode("latin-1")
    except UnicodeEncodeError:
        return False
    return True


READY: dict[tuple, Encoder] = {}


def encoder(path: str, store: int | None = None) -> Encoder:
    """One encoder for each file, store size and worker."""
    if (path, store) not in READY:
        READY[path, store] = Encoder(path, store)
    return READY[path, store]
