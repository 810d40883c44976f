"""Text encoders: a protocol, and the offline one (hashed character n-grams, a few synonyms applied first)."""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5
from typing import Protocol

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from coltypes.functions.exprs import BUCKETS


class Encoder(Protocol):
    """Unit vectors for texts; a sentence encoder fits here."""

    width: int

    def encode(self, texts: list[str]) -> np.ndarray: ...


class NgramEncoder:
    """Counts of 2- and 3-grams in md5 buckets, to unit length; the same numbers as the SQL form gives."""

    width = BUCKETS

    def __init__(self, synonyms: dict[str, str] | None = None):
        self.synonyms = synonyms or {}
        self.places: dict[str, int] = {}
        self.tables: dict[int, np.ndarray] = {}

    def __getstate__(self) -> dict:
        return {"synonyms": self.synonyms, "places": {}, "tables": {}}

    def _place(self, gram: str) -> int:
        if gram not in self.places:
            if len(self.places) > 500_000:
                self.places.clear()
            self.places[gram] = int(md5(gram.encode()).hexdigest()[:8], 16) % BUCKETS
        return self.places[gram]

    def _buckets(self, points: np.ndarray, n: int) -> np.ndarray:
        """The bucket of each n-gram of code points: from a table (bucket + 1) below U+0100, one by one of the different ones beyond."""
        if n not in self.tables:
            self.tables[n] = np.zeros(1 << 8 * n, np.uint16)  # pages that no gram touches take no memory
        table, last = self.tables[n], len(points) - n + 1
        parts = [points[i : last + i] for i in range(n)]
        narrow = np.logical_and.reduce([p < 256 for p in parts])
        code = sum(np.where(narrow, p, 0) << 8 * (n - 1 - i) for i, p in enumerate(parts))
        for c in np.unique(code[(table[code] == 0) & narrow]).tolist():
            table[c] = self._place("".join(chr(c >> 8 * (n - 1 - i) & 255) for i in range(n))) + 1
        found = table[code].astype(np.int64) - 1
        wide = np.nonzero(~narrow)[0]
        if len(wide):
            keys, back = np.unique(sum(p[wide] << 21 * (n - 1 - i) for i, p in enumerate(parts)), return_inverse=True)
            found[wide] = np.array([self._place("".join(chr(c >> 21 * (n - 1 - i) & 0x1FFFFF) for i in range(n))) for c in keys.tolist()])[back]
        return found

    def _counts(self, marked: list[str]) -> np.ndarray:
        """Grams of each text by bucket, all texts in one run over their code points."""
        points = np.frombuffer("".join(marked).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
        owner = np.repeat(np.arange(len(marked)), [len(m) for m in marked])
        out = np.zeros(len(marked) * self.width, np.int64)
        for n in (2, 3):
            last = len(points) - n + 1
            if last > 0:
                own = owner[:last] == owner[n - 1 :]
                out += np.bincount((owner[:last] * self.width + self._buckets(points, n))[own], minlength=len(out))
        return out.reshape(len(marked), self.width)

    def encode(self, texts: list[str]) -> np.ndarray:
        out, begin = np.zeros((len(texts), self.width)), 0
        while begin < len(texts):
            marked, held = [], 0
            while begin + len(marked) < len(texts) and held < 500_000 and len(marked) < 2000:
                text = texts[begin + len(marked)]
                marked.append(f"^{self.synonyms.get(text, text)}$")
                held += len(marked[-1])
            v = self._counts(marked)
            norm = np.sqrt((v * v).sum(axis=1))[:, None]
            out[begin : begin + len(marked)] = v / norm
            begin += len(marked)
        return out


def encoder_udf(encoder: Encoder):
    """encode(text) -> array<double>, in Arrow batches; the encoder is made once for each task."""
    @F.pandas_udf("array<double>")
    def encode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in batches:
            yield pd.Series(list(encoder.encode([t or "" for t in texts])))

    return encode


def encode(text: Column, encoder: Encoder | None = None) -> Column:
    return encoder_udf(encoder or NgramEncoder())(text)
