"""Secret scans: sure patterns alone, weak parts of a credential only together.

Sure kinds (each leftmost, non-overlapping, a match that is too short is consumed and dropped):
``assign`` a keyword with a value, ``access`` an access identifier, ``hex`` a long hexadecimal run.

Multipart linking. Parts of a credential that mean little alone are found as roles: an *identifier*
(a client or user name in a setting, or an access identifier), a *secret* (a long mixed token, the
value of a sure assignment, or a long hexadecimal run) and an *endpoint* (a URL, a host with a port,
an address in a setting). Every part has a scope, ``reach`` code points on from its end and back from
its start; two parts meet when one overlaps the other's scope, which is so both ways or neither.
A weak candidate (``ident``, ``weak``, ``endpoint``) is reported when it meets a complement: a secret
an identifier or an endpoint, these two a secret. An endpoint that meets an identifier which meets a
secret is reported too. Parts may lie over each other. Reported spans come on top of the sure ones.

Spans are code points, end exclusive. Defined cases: null text counts as empty (no span); the same
place may carry several kinds; columns other than doc_id and text pass or are not read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.llm import common

#: All kinds in the order in which spans of one start are listed.
KINDS = ("assign", "access", "hex", "ident", "weak", "endpoint")

# The patterns of the sure kinds and the least lengths of their matches.
ASSIGN = re.compile(r"""((?ai:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ASSIGN_LEAST = 6
ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
HEX = re.compile(r"[0-9a-f]{24,}")

# No part has a greatest length, so a long one is one span; the bounds of a bare host are those of host names (fixed values).
IDENT = re.compile(r"""(?ai:\b(?:client_?id|user_?name|user|login|account_?id|key_?id|access_?key_?id))["']?\x20*[:=]\x20*["']?([A-Za-z0-9_.@-]{3,})""")
WEAK = re.compile(r"[A-Za-z0-9+/_-]{20,}={0,2}")
ENDPOINT = re.compile(r"""(?ai:\b(?:https?|postgres(?:ql)?|mysql|mongodb|redis|amqp|s3|ftp)://[^\s"'<>]{3,}|\b(?:host|endpoint|server|url)["']?\x20*[:=]\x20*["']?[A-Za-z0-9][A-Za-z0-9.-]{2,}(?::\d{2,5})?|\b[a-z0-9][a-z0-9-]{0,62}(?:\.[a-z0-9-]{1,63}){1,8}:\d{2,5}\b)""")


@dataclass(frozen=True)
class Settings:
    reach: int = 400


def sure(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the sure kinds, in order."""
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_LEAST]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text)]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


def _mixed(token: str) -> bool:
    """A token of both cases and digits, as generated secrets are."""
    return any(c.isdigit() for c in token) and any(c.islower() for c in token) and any(c.isupper() for c in token)


class _Parts:
    """Sorted intervals, looked up by the scope that they overlap."""

    def __init__(self, parts: list[tuple[int, int]]):
        self.parts = sorted(parts)
        self.starts = np.array([s for s, _ in self.parts], np.int64)
        # intervals may be nested: the farthest end so far is sorted where the ends are not
        self.farthest = np.maximum.accumulate(np.array([e for _, e in self.parts], np.int64))

    def meeting(self, anchors: list[tuple[int, int]], reach: int) -> list[list[tuple[int, int]]]:
        """For each anchor the parts that its scope overlaps."""
        if not self.parts or not anchors:
            return [[] for _ in anchors]
        low, high = np.array(anchors, np.int64).T + np.array([[-reach], [reach]])
        first, last = np.searchsorted(self.farthest, low, "left"), np.searchsorted(self.starts, high, "right")
        return [[p for p in self.parts[i:j] if p[1] >= x] for i, j, x in zip(first.tolist(), last.tolist(), low.tolist(), strict=True)]


def _weak(text: str, found: list[tuple[int, int, int]]) -> list[tuple[int, int]]:
    """Long mixed tokens that touch no sure span."""
    taken = _Parts([(s, e - 1) for s, _, e in found])
    tokens = [(m.start(), m.end()) for m in WEAK.finditer(text) if _mixed(m.group())]
    return [t for t, met in zip(tokens, taken.meeting([(s, e - 1) for s, e in tokens], 0), strict=True) if not met]


def linked(text: str, found: list[tuple[int, int, int]], settings: Settings = Settings()) -> list[tuple[int, int, int]]:
    """(start, kind, end) of weak parts with a complement in their scope."""
    signs = "=" in text or ":" in text  # in every identifier setting and every endpoint
    access = [(s, e) for s, kind, e in found if kind == 1]
    if not signs and not access:
        return []
    weak = _weak(text, found)
    secrets = sorted(weak + [(s, e) for s, kind, e in found if kind != 1])
    if not secrets:
        return []
    ids = [(m.start(), m.end()) for m in IDENT.finditer(text)] if signs else []
    ends = [(m.start(), m.end()) for m in ENDPOINT.finditer(text)] if signs else []
    known, weak_set = _Parts(secrets), set(weak)
    out: set[tuple[int, int, int]] = set()

    def meet(parts: list[tuple[int, int]], kind: int | None) -> list[tuple[int, int]]:
        """Report parts that meet a secret, and these secrets; returns the parts."""
        met = []
        for part, inside in zip(parts, known.meeting(parts, settings.reach), strict=True):
            if inside:
                met.append(part)
                out.update((s, 4, e) for s, e in inside if (s, e) in weak_set)
        if kind is not None:
            out.update((s, kind, e) for s, e in met)
        return met

    anchors = meet(ids, 3) + meet(access, None)
    meet(ends, 5)
    for inside in _Parts(ends).meeting(anchors, settings.reach):
        out.update((s, 5, e) for s, e in inside)
    return sorted(out)


def scan(text: str, settings: Settings = Settings()) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """Sure spans and all spans of a whole text, each (start, kind, end) in order."""
    found = sure(text)
    return found, sorted(found + linked(text, found, settings))


def written(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[kind]}:{start}:{end}" for start, kind, end in spans)


FOUND = "doc_id long, n_assign long, n_access long, n_hex long, n_linked long, base_sha256 string, spans string"


def find(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """One row per document: counts of the sure kinds and of linked parts, the digest of the sure spans, all spans."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for text in common.texts_of(batch.column("text")):
                base, spans = scan(text, settings)
                kinds = [kind for _, kind, _ in base]
                rows.append((kinds.count(0), kinds.count(1), kinds.count(2), len(spans) - len(base), sha256(written(base).encode()).hexdigest(), written(spans)))
            columns = list(zip(*rows, strict=True)) or [()] * 6
            yield pa.record_batch([batch.column("doc_id"), *(pa.array(c, pa.int64()) for c in columns[:4]), *(pa.array(c, pa.string()) for c in columns[4:])], ["doc_id", "n_assign", "n_access", "n_hex", "n_linked", "base_sha256", "spans"])

    common.prepare(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, FOUND)


def masked(text: str, spans: list[tuple[int, int, int]], mark: str = "[SECRET]") -> str:
    """The text with each run of overlapping spans replaced by a mark."""
    out, at = [], 0
    for start, _, end in spans:
        if start >= at:
            out += [text[at:start], mark]
        at = max(at, end)
    return "".join([*out, text[at:]])


def mask(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """The documents in the columns that came, with secrets masked; n_chars, where there is one, follows the text."""
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, changed = batch.column("text").to_pylist(), []
            for k, text in enumerate(texts):
                if text:
                    spans = scan(text, settings)[1]
                    if spans:
                        texts[k] = masked(text, spans)
                        changed.append(k)
            if not changed:
                yield batch
                continue
            columns = dict(zip(names, batch.columns, strict=True))
            columns["text"] = pa.array(texts, batch.column("text").type)
            if "n_chars" in names and pa.types.is_integer(batch.column("n_chars").type):
                lengths = columns["n_chars"].to_pylist()
                for k in changed:
                    lengths[k] = len(texts[k])
                columns["n_chars"] = pa.array(lengths, batch.column("n_chars").type)
            yield pa.record_batch(list(columns.values()), schema=batch.schema)

    common.prepare(docs.sparkSession)
    return docs.mapInArrow(run, docs.schema)
