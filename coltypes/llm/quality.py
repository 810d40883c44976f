"""Quality classifier: text that compresses better with a dictionary of good text than with one of bad text is good.

Training. ``per_label`` labelled documents of each label (the smallest by a hash of the id; the bound
is a parameter) are split in two. All blocks of the first half's whole texts train one zstandard
dictionary per label. On the second half a logistic calibration is fitted to what the two compressors give for the whole
text: the size difference over the sum of sizes and over the raw size, the better ratio, and the
length, with their products (a text of many repeats is small under either dictionary, which the
ratio tells apart).

Scoring. Every text is cut into blocks of ``block`` bytes; all blocks of the whole text are
compressed with both dictionaries and the sizes are summed.

Defined cases: null text counts as empty; an empty text gets the share of good labels in training;
with no label of one kind every text gets that share (0.5 without labels); a null doc_id is never
learned from; label values other than 0 and 1 are left out; a repeated label row counts each time.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coltypes.llm import common


@dataclass(frozen=True)
class Settings:
    per_label: int = 6000
    block: int = 512
    dictionary_bytes: int = 112 << 10
    level: int = 1
    threshold: float = 0.3
    ridge: float = 1e-4


@dataclass
class Model:
    """Two dictionaries and the calibration; a few hundred kB at any size of the corpus."""

    prior: float
    settings: Settings
    good: bytes = b""
    bad: bytes = b""
    shift: list[float] = field(default_factory=list)
    scale: list[float] = field(default_factory=list)
    weights: list[float] = field(default_factory=list)

    def compressors(self) -> list[zstandard.ZstdCompressor]:
        out = []
        for data in (self.good, self.bad):
            d = zstandard.ZstdCompressionDict(data)
            d.precompute_compress(level=self.settings.level)
            out.append(zstandard.ZstdCompressor(level=self.settings.level, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False))
        return out

    def score(self, sizes: np.ndarray) -> np.ndarray:
        """Probability of label 1 from rows of (raw, good, bad) sizes."""
        out = np.full(len(sizes), self.prior)
        some = sizes[:, 0] > 0
        if self.weights and some.any():
            x = (_basis(sizes[some]) - self.shift) / self.scale
            out[some] = 1 / (1 + np.exp(-np.clip(x @ np.array(self.weights), -30, 30)))
        return out


def _basis(sizes: np.ndarray) -> np.ndarray:
    raw, good, bad = sizes.T.astype(float)
    difference, share = (bad - good) / np.maximum(bad + good, 1), (bad - good) / np.maximum(raw, 1)
    ratio, length = np.minimum(good, bad) / np.maximum(raw, 1), np.log1p(raw) / 10
    return np.c_[np.ones(len(raw)), difference, share, ratio, ratio**2, difference * ratio, length, length * ratio]


def sizes(texts: list[str], model: Model) -> np.ndarray:
    """(raw, compressed with good, compressed with bad) bytes of whole texts."""
    step = model.settings.block
    good, bad = model.compressors()
    out = np.zeros((len(texts), 3), np.int64)
    for k, text in enumerate(texts):
        data = text.encode("utf-8", "surrogatepass")
        g = b = 0
        for at in range(0, len(data), step):
            block = data[at : at + step]
            g += len(good.compress(block))
            b += len(bad.compress(block))
        out[k] = len(data), g, b
    return out


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float) -> np.ndarray:
    w = np.zeros(x.shape[1])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (p * (1 - p) + 1e-9)[:, None]).T @ x + ridge * len(y) * np.eye(len(w))
        w += np.linalg.solve(h, x.T @ (y - p) - ridge * len(y) * w)
    return w


def _blocks(s: Settings):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            labels, blocks = [], []
            for label, text in zip(batch.column("label").to_pylist(), common.texts_of(batch.column("text")), strict=True):
                data = text.encode("utf-8", "surrogatepass")
                for at in range(0, len(data), s.block):
                    labels.append(label), blocks.append(data[at : at + s.block])
            yield pa.record_batch([pa.array(labels, pa.int32()), pa.array(blocks, pa.binary())], ["label", "block"])

    return run


def _size_rows(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = sizes(common.texts_of(batch.column("text")), model)
            yield pa.record_batch([batch.column("label").cast(pa.int32()), *(pa.array(got[:, k]) for k in range(3))], ["label", "raw", "good", "bad"])

    return run


def fit(docs: DataFrame, labels: DataFrame, learn: Callable[[Column], Column] = lambda doc_id: F.lit(True), settings: Settings = Settings()) -> Model:
    """Train on rows of ``labels`` (doc_id, quality) whose id passes ``learn``.

    The sample of labels is bounded, so it is broadcast and no text is shuffled.
    """
    s = settings
    common.prepare(docs.sparkSession)
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("label")).where("doc_id is not null and label in (0, 1)").where(learn(F.col("doc_id")))
    counts = {r["label"]: r["n"] for r in known.groupBy("label").agg(F.count("*").alias("n")).collect()}
    prior = counts.get(1, 0) / sum(counts.values()) if counts else 0.5
    if len(counts) < 2:
        return Model(prior, s)
    order = (F.xxhash64("doc_id"), F.col("doc_id"))
    sample = known.where("label = 0").orderBy(*order).limit(s.per_label).union(known.where("label = 1").orderBy(*order).limit(s.per_label))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(sample), "doc_id")
    half = F.pmod(F.xxhash64("doc_id", F.lit("half")), F.lit(2))
    blocks = texts.where(half == 0).select("label", "text").mapInArrow(_blocks(s), "label int, block binary").distinct().toPandas()
    model = Model(prior, s)
    kinds = {label: sorted(bytes(b) for b in blocks.loc[blocks["label"] == label, "block"]) for label in (0, 1)}
    model.good, model.bad = _dictionary(kinds[1], s), _dictionary(kinds[0], s)
    rows = texts.where(half == 1).select("label", "text").mapInArrow(_size_rows(model), "label int, raw long, good long, bad long").where("raw > 0").toPandas()
    rows = rows.sort_values(list(rows.columns), kind="stable")
    y = rows["label"].to_numpy(float)
    if len(set(y)) == 2:
        x = _basis(rows[["raw", "good", "bad"]].to_numpy())
        shift, scale = x.mean(axis=0), x.std(axis=0) + 1e-9
        shift[0], scale[0] = 0, 1
        weights = _logistic((x - shift) / scale, y, s.ridge)
        # the sample holds the labels in other shares than all labelled documents do
        weights[0] += np.log(prior / (1 - prior)) - np.log(y.mean() / (1 - y.mean()))
        model.weights, model.shift, model.scale = weights.tolist(), shift.tolist(), scale.tolist()
    return model


def _dictionary(blocks: list[bytes], s: Settings) -> bytes:
    """A trained dictionary; too few blocks to train on become a dictionary as they are."""
    try:
        return zstandard.train_dictionary(s.dictionary_bytes, blocks, k=64, d=8).as_bytes()
    except (zstandard.ZstdError, ValueError):
        return b"".join(blocks)[-s.dictionary_bytes :] or b"\n" * 8


def score(docs: DataFrame, model: Model) -> DataFrame:
    """One row per document: doc_id, score, predicted."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in common.pieces(whole, "text"):
                got = model.score(sizes(common.texts_of(batch.column("text")), model))
                yield pa.record_batch([batch.column("doc_id"), pa.array(got), pa.array((got >= model.settings.threshold).astype(np.int32))], ["doc_id", "score", "predicted"])

    common.prepare(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, score double, predicted int")


def keep_good(docs: DataFrame, model: Model) -> DataFrame:
    """The rows, in the columns that came, whose text is predicted good."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = model.score(sizes(common.texts_of(batch.column("text")), model))
            yield batch.filter(pa.array(got >= model.settings.threshold))

    common.prepare(docs.sparkSession)
    return docs.mapInArrow(run, docs.schema)
