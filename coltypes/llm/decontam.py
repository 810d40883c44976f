"""Benchmark decontamination by greedy string tiling, which also catches reordered passages.

Texts become words (ASCII letters and digits in lower case, bytes of other scripts; ASCII
punctuation separates). Runs of ``least`` words are seeds. Seeds of the benchmark are joined with
the running hashes of every whole document; a document and an item with a shared seed are tiled:
the longest match of unmarked words is marked in both, again and again, down to ``least`` words
(matches are runs of equal Karp-Rabin hashes along a diagonal). The coverage is the
share of the item's words under tiles; at ``threshold`` or more the document is contaminated.

The benchmark is taken in blocks of bounded size, each broadcast in turn against all documents; the
driver holds one block at a time, and each block costs a pass over the documents.

Defined cases: null or word-less texts match nothing; an item of fewer than ``least`` words is one
seed of its full length; equal items are all reported; a repeated document row is reported each time.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.llm import common, wordhash


@dataclass(frozen=True)
class Settings:
    least: int = 5
    threshold: float = 0.5
    #: bytes of benchmark text in one block, which is what is broadcast at once
    block_bytes: int = 16 << 20


def _runs(item: np.ndarray, text: np.ndarray, size: int, most: int = 1 << 20) -> list[tuple[int, int, int]]:
    """(length, start in text, start in item) of all maximal runs of equal words of ``size`` and more.

    Seeds that meet are taken about ``most`` at a time and joined along their diagonals, so words that
    repeat cost time, but no memory beyond the runs.
    """
    seeds, running = wordhash.shingles(item, size), wordhash.shingles(text, size)
    order = np.argsort(seeds, kind="stable")
    low, high = (np.searchsorted(seeds[order], running, side) for side in ("left", "right"))
    hit = np.flatnonzero(high > low)
    counts = (high - low)[hit]
    done = np.cumsum(counts)
    parts, first = [np.zeros((3, 0), np.int64)], 0
    while first < len(hit):
        last = max(first + 1, int(np.searchsorted(done, (done[first - 1] if first else 0) + most, "right")))
        n = counts[first:last]
        t = np.repeat(hit[first:last], n)
        p = order[np.repeat(low[hit[first:last]] - np.cumsum(n) + n, n) + np.arange(len(t))]
        parts.append(_joined(t - p, t, t + 1))
        first = last
    diagonal, start, end = _joined(*np.concatenate(parts, axis=1))
    return list(zip((end - start + size - 1).tolist(), start.tolist(), (start - diagonal).tolist(), strict=True))


def _joined(diagonal: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Stretches [start, end) on diagonals, those that meet made one."""
    order = np.lexsort((start, diagonal))
    diagonal, start, end = diagonal[order], start[order], end[order]
    new = np.ones(len(start), bool)
    new[1:] = (diagonal[1:] != diagonal[:-1]) | (start[1:] != end[:-1])
    at = np.flatnonzero(new)
    return np.array([diagonal[at], start[at], end[np.append(at[1:], len(end)) - 1] if len(at) else start[at]])


def tiles(item: np.ndarray, text: np.ndarray, least: int) -> list[tuple[int, int, int]]:
    """(start in item, start in text, length): greedy tiles of two sequences of word hashes, longest first, then leftmost in the text."""
    size = min(least, len(item), len(text))
    if size == 0:
        return []
    heap = [(-n, t, p) for n, t, p in _runs(item, text, size)]
    heapify(heap)
    used_item, used_text, left, out = bytearray(len(item)), bytearray(len(text)), len(item), []
    while heap and left >= size:
        n, t, p = heappop(heap)
        n = -n
        used = [x | y for x, y in zip(used_item[p : p + n], used_text[t : t + n], strict=True)]
        if not any(used):
            used_item[p : p + n] = used_text[t : t + n] = b"\x01" * n
            left -= n
            out.append((p, t, n))
            continue
        begun = 0
        for k in [*(k for k, u in enumerate(used) if u), n]:  # what is still free of it comes again
            if k - begun >= size:
                heappush(heap, (begun - k, t + begun, p + begun))
            begun = k + 1
    return out


@dataclass
class Block:
    """Items of the benchmark and the sorted seeds that point to them."""

    ids: list
    words: list[np.ndarray]
    seeds: np.ndarray
    owners: np.ndarray
    sizes: list[int]
    marks: np.ndarray

    @classmethod
    def of(cls, ids: list, texts: list[str | None], least: int) -> Block:
        raw, offsets = wordhash.utf8(pa.array(texts, pa.string()))
        hashes, _, _, at = wordhash.words(raw, offsets, wordhash.ALNUM_WORDS)
        words = [hashes[at[k] : at[k + 1]] for k in range(len(ids))]
        seeds, owners = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        for k, w in enumerate(words):
            own = np.unique(wordhash.shingles(w, least))
            seeds.append(own), owners.append(np.full(len(own), k))
        seeds, owners = np.concatenate(seeds), np.concatenate(owners)
        order = np.argsort(seeds, kind="stable")
        marks = np.zeros(1 << 20, bool)
        marks[seeds & np.uint64((1 << 20) - 1)] = True
        short = sorted({len(w) for w in words if 0 < len(w) < least})
        return cls(list(ids), words, seeds[order], owners[order], [*short, least], marks)

    def hits(self, hashes: np.ndarray, at: np.ndarray) -> list[tuple[int, int]]:
        """(row, item) pairs of a batch's texts with a shared seed."""
        found = set()
        for size in self.sizes:
            n = len(hashes) - size + 1
            if n <= 0 or not len(self.seeds):
                continue
            running = wordhash.shingles(hashes, size)
            near = np.flatnonzero(self.marks[running & np.uint64((1 << 20) - 1)])
            row = np.searchsorted(at, near, "right") - 1
            near, row = near[near + size <= at[row + 1]], row[near + size <= at[row + 1]]
            low, high = (np.searchsorted(self.seeds, running[near], side) for side in ("left", "right"))
            for r, x, y in zip(row[low < high].tolist(), low[low < high].tolist(), high[low < high].tolist(), strict=True):
                found.update((r, int(k)) for k in self.owners[x:y])
        return sorted(found)

    def matches(self, column: pa.Array, s: Settings) -> list[tuple[int, int, float, int, int]]:
        """(row, item, coverage, tiles, words covered) at the threshold or above."""
        raw, offsets = wordhash.utf8(column)
        hashes, _, _, at = wordhash.words(raw, offsets, wordhash.ALNUM_WORDS)
        out = []
        for row, k in self.hits(hashes, at):
            got = tiles(self.words[k], hashes[at[row] : at[row + 1]], s.least)
            covered = sum(n for _, _, n in got)
            if covered >= s.threshold * len(self.words[k]):
                out.append((row, k, covered / len(self.words[k]), len(got), covered))
        return out


def blocks(benchmark: DataFrame, s: Settings) -> Iterator[Block]:
    """The benchmark in blocks, one after another; each is bounded, their number follows the benchmark."""
    rows = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(1, -(-total // s.block_bytes))
    for k in range(n):
        part = rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k).toPandas().sort_values(["item_id", "text"])
        yield Block.of([None if i != i else int(i) for i in part["item_id"]], [t if isinstance(t, str) else None for t in part["text"]], s.least)


FOUND = "doc_id long, item_id long, coverage double, n_tiles int, covered_words int"


def find(docs: DataFrame, benchmark: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """One row per contaminated document and benchmark item in it: doc_id, item_id, coverage, n_tiles, covered_words."""
    spark = common.prepare(docs.sparkSession)
    rows, out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), None
    for block in blocks(benchmark, settings):
        held = spark.sparkContext.broadcast(block)

        def run(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            block = held.value
            for whole in batches:
                for batch in common.pieces(whole, "text"):
                    got = block.matches(batch.column("text"), settings)
                    yield pa.record_batch([batch.column("doc_id").take(pa.array([g[0] for g in got], pa.int64())), pa.array([block.ids[g[1]] for g in got], pa.int64()), pa.array([g[2] for g in got], pa.float64()), pa.array([g[3] for g in got], pa.int32()), pa.array([g[4] for g in got], pa.int32())], ["doc_id", "item_id", "coverage", "n_tiles", "covered_words"])

        part = rows.mapInArrow(run, FOUND)
        out = part if out is None else out.union(part)
    return out


def keep_clean(docs: DataFrame, benchmark: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """The documents without contaminated ones, in the columns that came."""
    spark = common.prepare(docs.sparkSession)
    schema = docs.schema
    for block in blocks(benchmark, settings):
        held = spark.sparkContext.broadcast(block)

        def run(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            for whole in batches:
                for batch in common.pieces(whole, "text"):
                    keep = np.ones(batch.num_rows, bool)
                    keep[[g[0] for g in held.value.matches(batch.column("text"), settings)]] = False
                    yield batch.filter(pa.array(keep))

        docs = docs.mapInArrow(run, schema)
    return docs
