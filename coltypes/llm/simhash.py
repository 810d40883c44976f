"""SimHash fingerprints: weighted term hashes vote on 64 signed bits; permuted block tables find what is near.

Terms are runs of ``width`` words (ASCII white space ends a word, A-Z in lower case; a shorter text
is one term), each weighted by the square root of its count. Bit j is set when the terms with bit j
outweigh those without. Two fingerprints at Hamming distance d have likeness 1 - d / 64.

Search within a radius: a fingerprint is cut into ``blocks`` blocks; at most ``radius`` of them can
differ, so of every choice of ``blocks - radius`` blocks one agrees in full. Each choice is a table
keyed by the chosen bits; fingerprints under one key are candidates, checked on all 64 bits.

Edited texts: the last quarter of a text is replaced by the head of the next document in ascending
doc_id (nulls first; repeated ids by a hash of the text; after the last comes the first). Documents
are dealt in ranges of ids; the first row of a range also goes to the range before, so one pass over
sorted rows sees every neighbour.

Defined cases: null text counts as empty; the fingerprint of a text without words is 0; equal texts
have equal fingerprints.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from hashlib import sha256
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coltypes.llm import common, wordhash
from coltypes.llm.linkage import Tables, classes, thinned

BITS = 64


@dataclass(frozen=True)
class Settings:
    width: int = 2
    radius: int = 3
    blocks: int = 6


def fingerprints(column: pa.Array, width: int) -> np.ndarray:
    """64-bit fingerprints of whole texts."""
    raw, offsets = wordhash.utf8(column)
    hashes, _, _, at = wordhash.words(raw, offsets, wordhash.SPACE_ENDS)
    out = np.zeros(len(at) - 1, np.uint64)
    for k, runs in enumerate(wordhash.row_shingles(hashes, at, width)):
        terms, counts = wordhash.counted(runs)
        if len(terms):
            bits = np.unpackbits(terms.view(np.uint8).reshape(-1, 8), axis=1).astype(np.float32)
            weight = np.sqrt(counts).astype(np.float32)
            votes = 2 * (weight @ bits) - weight.sum()
            out[k] = np.packbits(votes > 0).view(np.uint64)[0]
    return out


def written(fingerprint: np.ndarray) -> pa.Array:
    return pa.array([f"{v:016x}" for v in fingerprint.tolist()], pa.string())


def likeness(one: np.ndarray, two: np.ndarray) -> np.ndarray:
    return 1 - np.bitwise_count(one ^ two) / BITS


def fingerprint(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """One row per document: doc_id, fingerprint (as a signed long)."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in common.pieces(whole, "text"):
                yield pa.record_batch([batch.column("doc_id"), pa.array(fingerprints(batch.column("text"), settings.width).view(np.int64))], ["doc_id", "fingerprint"])

    common.prepare(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, fingerprint long")


def edited(text: str, following: str) -> str:
    """The last quarter (rounded down) replaced by as many first characters of the next text, or all it has."""
    n = len(text) // 4
    return text[: len(text) - n] + following[:n]


EDITED = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
_DEALT = "part int, after int, doc_id long, text string, tie long"


def compare_edited(docs: DataFrame, settings: Settings = Settings(), files: int | None = None) -> DataFrame:
    """One row per document: its fingerprint, that of its edited text, and the likeness to the edited text and to the next document."""
    spark = common.prepare(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    least = -(1 << 63)
    order = F.coalesce("doc_id", F.lit(least))
    n = files or max(1, rows.rdd.getNumPartitions())
    ids = rows.select(order.alias("at"))
    cuts = np.unique(np.array(ids.approxQuantile("at", [k / n for k in range(1, n)], 0.2 / n) if n > 1 else [], np.float64)).astype(np.int64)

    def ranged(values: np.ndarray) -> np.ndarray:
        return np.searchsorted(cuts, values, "right").astype(np.int32)

    def range_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first: dict[int, int] = {}
        for batch in batches:
            at = batch.column("at").to_numpy()
            for part, value in zip(ranged(at).tolist(), at.tolist(), strict=True):
                first[part] = min(first.get(part, value), value)
        yield pa.record_batch([pa.array(list(first), pa.int32()), pa.array(list(first.values()), pa.int64())], ["part", "first"])

    # a row for each range: as many as there are partitions
    firsts = {r["part"]: r["first"] for r in ids.mapInArrow(range_of, "part int, first long").groupBy("part").agg(F.min("first").alias("first")).collect()}
    ranges = sorted(firsts)
    # the first id of a range goes to the range before it as well, that of the first range to the last
    copies = {firsts[part]: ranges[k - 1] for k, part in enumerate(ranges)}

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        heads = np.array(sorted(copies), np.int64)
        for batch in batches:
            at = batch.column("at").to_numpy()
            own = pa.record_batch([pa.array(ranged(at)), pa.array(np.zeros(len(at), np.int32)), batch.column("doc_id"), batch.column("text"), batch.column("tie")], ["part", "after", "doc_id", "text", "tie"])
            yield own
            again = np.flatnonzero(np.isin(at, heads))
            if len(again):
                more = own.take(pa.array(again))
                yield pa.record_batch([pa.array([copies[v] for v in at[again].tolist()], pa.int32()), pa.array(np.ones(len(again), np.int32)), *more.columns[2:]], more.schema.names)

    dealt = rows.select("doc_id", "text", order.alias("at"), F.xxhash64("text").alias("tie")).mapInArrow(deal, _DEALT)
    dealt = dealt.repartitionById(len(cuts) + 1, F.col("part")).sortWithinPartitions("after", F.col("doc_id").asc_nulls_first(), "tie")

    def told(ids: list, texts: list[str]) -> pa.RecordBatch:
        """Rows for all texts but the last, each with its successor."""
        own = fingerprints(pa.array(texts, pa.large_string()), settings.width)
        changed = [edited(t, u) for t, u in zip(texts, texts[1:], strict=False)]
        theirs = fingerprints(pa.array(changed, pa.large_string()), settings.width)
        digests = [sha256(t.encode("utf-8", "surrogatepass")).hexdigest() for t in changed]
        return pa.record_batch([pa.array(ids[:-1], pa.int64()), pa.array([len(t) for t in texts[:-1]], pa.int64()), pa.array(digests, pa.string()), written(own[:-1]), written(theirs), pa.array(likeness(own[:-1], theirs)), pa.array(likeness(own[:-1], own[1:]))], [c.split()[0] for c in EDITED.split(", ")])

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, texts, done = [], [], False
        for whole in batches:
            for batch in common.pieces(whole, "text"):
                for doc_id, text, after in zip(batch.column("doc_id").to_pylist(), common.texts_of(batch.column("text")), batch.column("after").to_pylist(), strict=True):
                    if done:
                        break
                    ids.append(doc_id), texts.append(text)
                    done = bool(after)
                if len(texts) > 1:
                    yield told(ids, texts)
                    ids, texts = ids[-1:], texts[-1:]

    return dealt.mapInArrow(walk, EDITED)


def block_keys(fingerprint: Column, settings: Settings = Settings()) -> list[Column]:
    """The key of a fingerprint in each permuted table, with the table's number in it."""
    edges = [BITS * k // settings.blocks for k in range(settings.blocks + 1)]
    masks = []
    for kept in combinations(range(settings.blocks), settings.blocks - settings.radius):
        mask = sum(((1 << (edges[k + 1] - edges[k])) - 1) << edges[k] for k in kept)
        masks.append(mask - (1 << 64) if mask >> 63 else mask)
    return [F.xxhash64(F.lit(k), fingerprint.bitwiseAND(F.lit(mask).cast("long"))) for k, mask in enumerate(masks)]


def _unit(settings: Settings):
    """Of the keys of a unit, pairs within the radius that join its parts."""
    def run(group: pa.Table) -> pa.Table:
        keys, parts = group.column("key").to_numpy(), group.column("part").to_numpy()
        prints, label, pairs = keys.view(np.uint64), parts.copy(), []
        for k in range(len(keys)):
            for j in np.flatnonzero(np.bitwise_count(prints[k] ^ prints[k + 1 :]) <= settings.radius) + k + 1:
                if label[j] != label[k]:
                    pairs.append((min(keys[k], keys[j]), max(keys[k], keys[j])))
                    label[label == label[j]] = label[k]
        return pa.table({"a": pa.array([p[0] for p in pairs], pa.int64()), "b": pa.array([p[1] for p in pairs], pa.int64())})

    return run


def near_classes(prints: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """Rows (doc_id, fingerprint) with class_id: the smallest doc_id that a chain of fingerprints within the radius reaches.

    Equal fingerprints are one key; null doc_ids get no class. Every pair within the radius shares a
    table's key, so no link is missed.
    """
    spark, tables = prints.sparkSession, Tables("simhash")
    rows, path = common.stored(prints.select("doc_id", "fingerprint"), "simhash-prints")
    owned = tables.keep(rows.where("doc_id is not null").groupBy(F.col("fingerprint").alias("key")).agg(F.min("doc_id").alias("least")), "keys")
    keyed = owned.select("key", F.explode(F.array(*block_keys(F.col("key"), settings))).alias("band"))
    shared = keyed.groupBy("band").agg(F.count("*").alias("c")).where("c > 1").select("band")
    shared, total = tables.keep_with(shared, "shared", rows=F.lit(1))
    buckets = tables.keep(thinned(keyed, "band", shared, total["rows"]).join(shared, "band", "left_semi"), "buckets")

    def unit_links(units: DataFrame) -> DataFrame:
        return tables.keep(units.groupBy("unit").applyInArrow(_unit(settings), "a long, b long").distinct(), "unit-near")

    part = classes(buckets.withColumn("n", F.lit(1)), unit_links, tables, 1024, 1024)
    if part is None:
        roots = owned.select("key", F.col("least").alias("class_id"))
    else:
        joined = owned.join(part, "key", "left").withColumn("part", F.coalesce("part", "key"))
        roots = joined.select("key", "part").join(joined.groupBy("part").agg(F.min("least").alias("class_id")), "part").select("key", "class_id")
    out = rows.join(roots.withColumnRenamed("key", "fingerprint"), "fingerprint", "left").select("doc_id", "fingerprint", F.when(F.col("doc_id").isNotNull(), F.col("class_id")).alias("class_id"))
    out = common.stored(out, "simhash-classes")[0]
    tables.drop(out)
    common.remove(spark, path)
    return out
