"""Near-duplicate groups: banded MinHash candidates, sequential Bayesian pruning, exact verification.

Definition. A text is lower-cased in A-Z and cut into words at ASCII white space; its set holds the
distinct runs of ``width`` words (fewer words: the whole sequence as one; no word: the empty set,
linked with nothing). Two texts are linked when ``100 * |A and B| >= percent * |A or B|``; documents
of one connected component form a group, named by its smallest doc_id.

How. Texts with equal sets collapse to one key before anything is banded. Each key has a MinHash
signature of 16-bit values, cut into bands; keys that share a band are candidates, compared in units
of bounded size (see ``linkage``) so that no bucket is expanded into rows of pairs. First the
signatures of a unit are compared batch by batch and a pair is dropped once the posterior
probability of the similarity falls below ``miss``; only texts of keys with a pair left are fetched,
and these pairs are confirmed on their full sets.

Keys are 64-bit hashes of sets. A second hash shows whether two sets ever met in one key; then all
is done again with other hashes, so a merge stands for equal sets.

Defined cases: null text counts as empty; a row with a null doc_id links with nothing and stays;
rows that repeat a doc_id are judged each by its own text, told apart by a 64-bit hash of it; of each
group one (doc_id, text) is kept, that of the smallest doc_id and then of the smallest hash. Rows
alike in both are one document that came more than once: they stay or go together. Other columns are
not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coltypes.llm import common, wordhash
from coltypes.llm.linkage import Tables, classes, sifted, thinned


@dataclass(frozen=True)
class Settings:
    """width and percent define a link; the rest is how candidates are found.

    With 32 bands of 5 rows a pair at similarity 0.8 shares no band with probability 3e-6.
    """

    width: int = 5
    percent: int = 80
    bands: int = 32
    rows: int = 5
    batch: int = 32
    miss: float = 1e-6
    #: keys and shingles in one block; a unit compares two
    block_keys: int = 256
    block_shingles: int = 1 << 17

    @property
    def size(self) -> int:
        return self.bands * self.rows


SKETCH = "doc_id long, print long, n_shingles long, key long, check long, signature binary"
#: Bytes of one value of a signature.
VALUE = 2


@lru_cache(maxsize=4)
def _family(size: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(977)
    a = rng.integers(0, 1 << 32, size, dtype=np.uint64).astype(np.uint32) | np.uint32(1)
    return a, rng.integers(0, 1 << 32, size, dtype=np.uint64).astype(np.uint32)


def signature(unique: np.ndarray, size: int) -> np.ndarray:
    """The minimum of each of ``size`` hash functions over a set of 64-bit hashes, mixed to 16 bits.

    Minima of large sets are all small, so their high bits alone tell nothing; the product spreads them.
    """
    a, b = _family(size)
    low = (unique >> np.uint64(32)).astype(np.uint32)
    best = np.full(size, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(low), 256):
        m = low[at : at + 256, None] * a
        m += b
        np.minimum(best, m.min(axis=0), out=best)
    return ((best * np.uint32(0x9E3779B1)) >> np.uint32(16)).astype("<u2")


def _sets(batch: pa.RecordBatch, width: int) -> Iterator[np.ndarray]:
    raw, offsets = wordhash.utf8(batch.column("text"))
    hashes, _, _, at = wordhash.words(raw, offsets, wordhash.SPACE_ENDS)
    for runs in wordhash.row_shingles(hashes, at, width):
        yield wordhash.unique(runs)


def _keys(unique: np.ndarray, seed: int) -> tuple[int | None, int | None]:
    """Two 64-bit hashes of a set, of a family given by the seed; none for the empty set."""
    if not len(unique):
        return None, None
    both = blake2b(unique.tobytes(), digest_size=16, salt=seed.to_bytes(8, "little")).digest()
    return tuple(int.from_bytes(both[k : k + 8], "little", signed=True) for k in (0, 8))


def _sketcher(s: Settings, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.lean()
        for whole in batches:
            for batch in common.pieces(whole, "text"):
                sets = list(_sets(batch, s.width))
                keys = [_keys(u, seed) for u in sets]
                signatures = [signature(u, s.size).tobytes() if len(u) else None for u in sets]
                columns = [pa.array([len(u) for u in sets], pa.int64()), *(pa.array([k[j] for k in keys], pa.int64()) for j in (0, 1)), pa.array(signatures, pa.binary())]
                yield pa.record_batch([batch.column("doc_id").cast(pa.int64()), batch.column("print"), *columns], ["doc_id", "print", "n_shingles", "key", "check", "signature"])

    return run


@lru_cache(maxsize=4)
def least_matches(s: Settings) -> np.ndarray:
    """For 1, 2, ... batches: the fewest equal positions at which the posterior of similarity >= percent is above ``miss``.

    Uniform prior on the similarity; the stored 16 bits also agree by chance once in 65536.
    """
    grid = (np.arange(2000) + 0.5) / 2000
    same = grid + (1 - grid) / (1 << 8 * VALUE)
    out = []
    for n in range(s.batch, s.size + 1, s.batch):
        m = np.arange(n + 1)[:, None]
        logs = m * np.log(same) + (n - m) * np.log1p(-same)
        mass = np.exp(logs - logs.max(axis=1, keepdims=True))
        posterior = mass[:, grid >= s.percent / 100].sum(axis=1) / mass.sum(axis=1)
        out.append(int(np.argmax(posterior >= s.miss)))
    return np.array(out)


def survivors(signatures: np.ndarray, sizes: np.ndarray, parts: np.ndarray, was: np.ndarray, s: Settings, least: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (i < j) of different parts and units before, of fitting sizes, whose signatures stay likely through all batches."""
    across, found = np.ascontiguousarray(signatures.T), []
    for low in range(0, len(sizes), 256):
        at = slice(low, low + 256)
        fit = (parts[at, None] != parts) & (was[at, None] != was) & (np.arange(len(sizes)) > np.arange(len(sizes))[at, None])
        fit &= 100 * np.minimum(sizes[at, None], sizes) >= s.percent * np.maximum(sizes[at, None], sizes)
        equal = np.zeros(fit.shape, np.uint8)
        for row in across[: s.batch]:
            equal += row[at, None] == row
        i, j = np.nonzero(fit & (equal >= least[0]))
        same, i = equal[i, j].astype(np.int64), i + low
        for k, need in enumerate(least[1:], 1):
            for row in across[k * s.batch : (k + 1) * s.batch]:
                same += row[i] == row[j]
            alive = same >= need
            i, j, same = i[alive], j[alive], same[alive]
        found.append((i, j))
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def _signatures(column: pa.ChunkedArray, size: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), "<u2").reshape(-1, size)


def overlaps(sets: list[np.ndarray], columns: int = 4096) -> np.ndarray:
    """Sizes of all intersections of some sets, by products of their incidence matrix in strips."""
    who = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    _, which, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = counts > 1
    place = np.cumsum(shared) - 1
    keep = shared[which]
    who, which = who[keep], place[which[keep]]
    order = np.argsort(which, kind="stable")
    who, which = who[order], which[order]
    total = np.zeros((len(sets), len(sets)), np.float32)
    for low in range(0, int(shared.sum()), columns):
        at = slice(*np.searchsorted(which, [low, low + columns]))
        strip = np.zeros((len(sets), columns), np.float32)
        strip[who[at], which[at] - low] = 1
        total += strip @ strip.T
    return total.astype(np.int64)


def spanning(sets: list[np.ndarray], pairs: tuple[np.ndarray, np.ndarray], parts: np.ndarray, s: Settings) -> list[list[int]]:
    """Of likely pairs the linked ones, as groups of places whose parts they join into one."""
    i, j = pairs
    sizes = np.array([len(x) for x in sets])
    if len(i) > 4 * len(sets):
        both = overlaps(sets)[i, j]
    else:
        both = np.array([len(np.intersect1d(sets[x], sets[y], assume_unique=True)) for x, y in zip(i, j, strict=True)], np.int64)
    sure = 100 * both >= s.percent * (sizes[i] + sizes[j] - both) if len(i) else np.zeros(0, bool)
    root: dict[int, int] = {}

    def top(x: int) -> int:
        while root.get(x, x) != x:
            root[x] = root.get(root[x], root[x])
            x = root[x]
        return x

    joined: set[int] = set()
    for x, y in zip(i[sure].tolist(), j[sure].tolist(), strict=True):
        p, q = top(int(parts[x])), top(int(parts[y]))
        if p != q:
            root[max(p, q)] = min(p, q)
            joined |= {x, y}
    groups: dict[int, list[int]] = {}
    for x in sorted(joined):
        groups.setdefault(top(int(parts[x])), []).append(x)
    return list(groups.values())


LIKELY = "unit long, key long, part long, was long, n long, doc_id long, print long, signature binary"


def _likely(s: Settings):
    """The rows of a unit that have a likely pair."""
    def run(group: pa.Table) -> pa.Table:
        signatures = _signatures(group.column("signature"), s.size)
        pairs = survivors(signatures, *(group.column(c).to_numpy() for c in ("n", "part", "was")), s, least_matches(s))
        return group.take(pa.array(np.unique(np.concatenate(pairs))))

    return run


def _confirmed(s: Settings):
    """Links that join the parts of a unit, from its likely rows with their texts; a row that came twice counts once."""
    def run(group: pa.Table) -> pa.Table:
        keys = group.column("key").to_numpy()
        keys, first = np.unique(keys, return_index=True)
        group = group.take(pa.array(first))
        sets = [u for batch in group.select(["text"]).to_batches() for u in _sets(batch, s.width)]
        parts = group.column("part").to_numpy()
        sizes = np.array([len(u) for u in sets])
        pairs = survivors(_signatures(group.column("signature"), s.size), sizes, parts, group.column("was").to_numpy(), s, least_matches(s))
        groups = spanning(sets, pairs, parts, s)
        a = [keys[g[0]] for g in groups for _ in g[1:]]
        b = [keys[x] for g in groups for x in g[1:]]
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return run


def _print(docs: DataFrame) -> Column:
    """What tells rows of one doc_id apart: a hash of the text, null as empty."""
    return F.xxhash64(F.coalesce(docs["text"].cast("string"), F.lit("")))


class _Search:
    """The tables of one run: sketch has all rows, keys one row for each set with the least document that has it."""

    def __init__(self, docs: DataFrame, s: Settings):
        self.spark, self.s, self.tables = common.prepare(docs.sparkSession), s, Tables("near")
        self.docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
        self.docs = self.docs.withColumn("print", _print(self.docs))
        met, seed = 1, 0
        while met:
            self.tables.drop(docs)
            self.sketch = self.tables.keep(self.docs.mapInArrow(_sketcher(s, seed), SKETCH), "sketch")
            met = self._collapse()
            seed += 1

    def _collapse(self) -> int:
        """Make keys; returns how many keys stand for more than one set."""
        rows = self.sketch.where("key is not null and doc_id is not null").groupBy("key")
        keys = rows.agg(F.min(F.struct("doc_id", "print")).alias("least"), F.min("n_shingles").alias("n"), F.first("signature").alias("signature"), F.min("check").alias("lo"), F.max("check").alias("hi"))
        self.keys, total = self.tables.keep_with(keys.select("key", "n", "least.*", "signature", "lo", "hi"), "keys", met=F.expr("if(lo <> hi, 1, 0)"))
        return total["met"]

    def buckets(self) -> DataFrame:
        """(band, key, n) of all bands that hold two keys."""
        size = VALUE * self.s.rows
        bands = F.array(*[F.xxhash64(F.lit(k), F.substring("signature", k * size + 1, size)) for k in range(self.s.bands)])
        shared = self.keys.select(F.explode(bands).alias("band")).groupBy("band").agg(F.count("*").alias("c")).where("c > 1").select("band")
        shared, total = self.tables.keep_with(shared, "shared", rows=F.lit(1))
        rows = thinned(self.keys.select(F.explode(bands).alias("band"), "key", "n"), "band", shared, total["rows"])
        return self.tables.keep(rows.join(shared, "band", "left_semi"), "buckets")

    def unit_links(self, rows: DataFrame) -> DataFrame:
        """Links (a, b) of units (unit, key, part, was): signatures first, then the texts of what stays likely."""
        rows, total = self.tables.keep_with(rows, "units", rows=F.lit(1))
        owners = thinned(self.keys, "key", rows, total["rows"]).select("key", "n", "doc_id", "print", "signature")
        signed = rows.join(owners, "key").select(*[c.split()[0] for c in LIKELY.split(", ")])
        likely, total = self.tables.keep_with(signed.groupBy("unit").applyInArrow(_likely(self.s), LIKELY), "likely", rows=F.lit(1))
        texts = thinned(self.docs, "doc_id", likely, total["rows"])
        told = texts.join(likely, ["doc_id", "print"]).dropDuplicates(["doc_id", "print", "unit"])
        told = told.select("unit", "key", "part", "was", "signature", "text")
        return self.tables.keep(told.groupBy("unit").applyInArrow(_confirmed(self.s), "a long, b long").distinct(), "links")

    def classes(self) -> DataFrame | None:
        return classes(self.buckets(), self.unit_links, self.tables, self.s.block_keys, self.s.block_shingles)


def _judged(docs: DataFrame, settings: Settings) -> DataFrame:
    """The rows of ``groups`` with the hash of their text, print."""
    run = _Search(docs, settings)
    part = run.classes()
    keyed = run.keys.select("key", F.struct("doc_id", "print").alias("least"))
    if part is None:
        roots = keyed.select("key", F.col("least").alias("root"))
    else:
        keyed = keyed.join(part, "key", "left").withColumn("part", F.coalesce("part", "key"))
        roots = keyed.select("key", "part").join(keyed.groupBy("part").agg(F.min("least").alias("root")), "part").select("key", "root")
    roots = run.tables.keep(roots, "roots")  # stored, so that a key with many rows can be split in the join
    rows = run.sketch.select("doc_id", "print", "n_shingles", "key")
    root = F.when(F.col("doc_id").isNotNull(), F.col("root"))  # null for a row that links with nothing
    kept = F.coalesce((F.col("doc_id") == root["doc_id"]) & (F.col("print") == root["print"]), F.lit(True))
    out = rows.join(roots, "key", "left").select("doc_id", "print", "n_shingles", F.coalesce(root["doc_id"], F.col("doc_id")).alias("component_id"), kept.alias("kept"))
    out = common.settled(out)
    run.tables.drop(out)
    return out


def groups(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept (the one of its group; a null doc_id stays)."""
    return _judged(docs, settings).drop("print")


def keep_one(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """The documents without all but one of each group, in the columns that came."""
    gone = _judged(docs, settings).where("not kept").select("doc_id", "print").distinct()
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), _print(docs).alias("print"), F.struct(*[docs[f"`{c}`"] for c in docs.columns]).alias("row"))
    maybe, others = sifted(rows, "print", gone, gone.count())
    kept = maybe.join(gone, ["doc_id", "print"], "left_anti").select("row.*")
    return kept if others is None else kept.union(others.select("row.*"))
