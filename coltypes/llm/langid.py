"""Language identification by interpolated Kneser-Ney character models, one per language.

Text becomes lower-case letters with one space for any run of other characters. For each language a
model of ``order`` characters is trained: the top order has raw counts, lower orders continuation
counts (the number of different characters before), each order is discounted and interpolated with
the one below, and the lowest with a uniform share. All models live in one table per order: the
sorted 64-bit hashes of all n-grams of any language, a directory over their leading bits, and a row
of log-probabilities (and of back-off weights) with a column per language. A character's n-gram is
looked up in the highest order; only what is not there falls to the next. The language with the
lowest cross-entropy per character wins; the posterior of a softmax whose temperature was calibrated
on training texts left out of the counts is the score. A text is *rejected* when its best
cross-entropy is above the calibrated quantile of that language's own texts.

Training uses at most ``per_language`` documents of each language (the smallest by a hash of the id;
the bound is a parameter), whole.

Defined cases: null, empty and letterless texts are ``und`` with score 0; with no training data all
are; equal cross-entropies go to the alphabetically first language; a null doc_id or lang is never
learned from.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coltypes.llm import common, wordhash

UNKNOWN = "und"
_SPACE = 32


@dataclass(frozen=True)
class Settings:
    order: int = 4
    per_language: int = 400
    #: of the sample, one document in so many is kept out of the counts, to calibrate
    left_out: int = 5
    #: share of a language's own texts that calibrated rejection may refuse
    refused: float = 0.005


def _letters() -> np.ndarray:
    """For each code point: itself in lower case if a letter (or mark), a space if not."""
    out = np.full(0x110000, _SPACE, np.uint32)
    for c in range(0x110000):
        ch = chr(c)
        if ch.isalpha():
            low = ch.lower()
            out[c] = ord(low) if len(low) == 1 else c
    return out


_TABLES: list[np.ndarray] = []


def _table() -> np.ndarray:
    if not _TABLES:
        _TABLES.append(_letters())
    return _TABLES[0]


def characters(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Normalised code points of all texts, a space before and after each, and rows + 1 offsets."""
    joined = "\x00".join(t.replace("\x00", " ") for t in texts) + "\x00"
    raw = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    ends = np.flatnonzero(raw == 0) + 1
    codes = _table()[raw]
    keep = np.ones(len(codes), bool)
    blank = codes == _SPACE
    keep[1:] = ~(blank[1:] & blank[:-1])
    keep[ends - 1] = True  # the end of a text is always there; a space before it is not
    before = ends - 2
    before = before[before >= 0]
    keep[before[blank[before] & (raw[before] != 0)]] = False
    starts = np.concatenate([[0], ends[:-1]])
    lead = starts[blank[starts] & (raw[starts] != 0)]
    keep[lead] = False
    at = np.concatenate([[0], np.cumsum(keep)[ends - 1]])
    return codes[keep], at


def _grams(codes: np.ndarray, at: np.ndarray, order: int) -> list[np.ndarray]:
    """For n = 1..order the hash of the n characters that end at each place; before a text there are spaces."""
    h, out = np.zeros(len(codes), np.uint64), []
    wide = codes.astype(np.uint64)
    for n in range(order):
        shifted = wide
        if n:
            shifted = np.empty_like(wide)
            shifted[n:] = wide[:-n]
            shifted[:n] = _SPACE
            for j in range(n):
                early = at[:-1] + j
                shifted[early[early < at[1:]]] = _SPACE
        h = h + wordhash.mix(shifted + np.uint64((n + 1) << 32))
        out.append(wordhash.mix(h + np.uint64(n + 1)))
    return out


def _before(grams: list[np.ndarray], at: np.ndarray, order: int) -> list[np.ndarray]:
    """For n = 1..order-1 the hash of the n characters before each place."""
    blank = np.full(order, _SPACE, np.uint32)
    spaces = [g[-1] for g in _grams(blank, np.array([0, order]), order)]
    out = []
    for n in range(order - 1):
        shifted = np.empty_like(grams[n])
        shifted[1:] = grams[n][:-1]
        shifted[at[:-1][at[:-1] < len(shifted)]] = spaces[n]
        out.append(shifted)
    return out


class Sorted:
    """A sorted hash array with a directory over leading bits; ``find`` gives places, -1 where absent."""

    def __init__(self, hashes: np.ndarray):
        self.hashes = hashes
        self.bits = max(1, min(22, int(len(hashes)).bit_length() + 1))
        heads = (hashes >> np.uint64(64 - self.bits)).astype(np.int64)
        self.starts = np.searchsorted(heads, np.arange((1 << self.bits) + 1)).astype(np.int32)
        self.longest = int(np.diff(self.starts).max()) if len(hashes) else 0

    def find(self, wanted: np.ndarray) -> np.ndarray:
        out = np.full(len(wanted), -1, np.int32)
        if not len(self.hashes):
            return out
        head = (wanted >> np.uint64(64 - self.bits)).astype(np.int64)
        at, end = self.starts[head], self.starts[head + 1]
        open_ = np.flatnonzero(at < end)
        for _ in range(self.longest):
            here = at[open_]
            hit = self.hashes[here] == wanted[open_]
            out[open_[hit]] = here[hit]
            open_ = open_[~hit]
            at[open_] += 1
            open_ = open_[at[open_] < end[open_]]
            if not len(open_):
                break
        return out


@dataclass
class Model:
    """Tables by order; ``log_p[n]`` and ``log_gamma[n]`` have a row per n-gram or context and a column per language."""

    settings: Settings
    languages: list[str] = field(default_factory=list)
    grams: list[Sorted] = field(default_factory=list)
    contexts: list[Sorted] = field(default_factory=list)
    log_p: list[np.ndarray] = field(default_factory=list)
    log_gamma: list[np.ndarray] = field(default_factory=list)
    floor: np.ndarray | None = None
    temperature: float = 1.0
    limits: np.ndarray | None = None

    def entropy(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Cross-entropy in nats per character, a row per text and a column per language, and which texts have a letter."""
        codes, at = characters(texts)
        order = self.settings.order
        grams = _grams(codes, at, order)
        before = _before(grams, at, order)
        total = np.zeros((len(codes), len(self.languages)), np.float32)
        open_ = np.arange(len(codes))
        for n in range(order - 1, -1, -1):
            place = self.grams[n].find(grams[n][open_])
            hit = place >= 0
            total[open_[hit]] += self.log_p[n][place[hit]]
            open_ = open_[~hit]
            if not len(open_):
                break
            if n == 0:
                total[open_] += self.floor
                break
            place = self.contexts[n].find(before[n - 1][open_])
            some = place >= 0
            total[open_[some]] += self.log_gamma[n][place[some]]
        lengths = np.diff(at)
        sums = np.add.reduceat(total, at[:-1], axis=0, dtype=np.float64) if len(texts) else np.zeros((0, len(self.languages)))
        lettered = np.add.reduceat((codes != _SPACE).astype(np.int64), at[:-1]) > 0 if len(texts) else np.zeros(0, bool)
        return -sums / np.maximum(lengths, 1)[:, None], lettered

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """(language, score, rejected) of whole texts."""
        if not self.languages:
            return [UNKNOWN] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
        h, lettered = self.entropy(texts)
        best = h.argmin(axis=1)
        score = np.exp(-_log_sum(-(h - h.min(axis=1, keepdims=True)) / self.temperature))
        rejected = ~lettered | (h[np.arange(len(texts)), best] > self.limits[best])
        return [self.languages[k] if ok else UNKNOWN for k, ok in zip(best, lettered, strict=True)], np.where(lettered, score, 0.0), rejected


def _log_sum(x: np.ndarray) -> np.ndarray:
    return np.log(np.exp(x).sum(axis=1))


def _counted(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return np.unique(hashes, return_counts=True)


def build(texts: dict[str, list[str]], s: Settings) -> Model:
    """Train on whole texts by language; the sizes of the tables follow the sample, which is bounded."""
    model = Model(s, sorted(k for k, v in texts.items() if any(v)))
    if not model.languages:
        return model
    order, each = s.order, []
    for language in model.languages:
        codes, places = characters(texts[language])
        own = _grams(codes, places, order)
        contexts_here = _before(own, places, order)
        levels = []
        for n in range(order):
            # the n+1 characters here, without the first (the lower-order n-gram) and without the last (the context)
            lower = own[n - 1] if n else np.zeros(len(codes), np.uint64)
            before = contexts_here[n - 1] if n else np.zeros(len(codes), np.uint64)
            hashes, first, counts = np.unique(own[n], return_index=True, return_counts=True)
            levels.append({"gram": hashes, "count": counts.astype(float), "context": before[first], "lower": lower[first]})
        for n in range(order - 1):  # lower orders count the different characters before
            kinds, counts = _counted(levels[n + 1]["lower"])
            place = np.searchsorted(kinds, levels[n]["gram"]).clip(0, len(kinds) - 1)
            found = kinds[place] == levels[n]["gram"]
            levels[n]["count"] = np.where(found, counts[place], 1).astype(float)
        each.append(levels)
    alphabet = len(np.unique(np.concatenate([levels[0]["gram"] for levels in each])))
    below = None
    model.floor = np.full(len(each), -np.log(alphabet + 1), np.float32)
    for n in range(order):
        grams = np.unique(np.concatenate([levels[n]["gram"] for levels in each]))
        contexts = np.unique(np.concatenate([levels[n]["context"] for levels in each]))
        p = np.zeros((len(grams), len(each)))
        gamma = np.ones((len(contexts), len(each)))
        ctx_of, low_of = np.zeros(len(grams), np.uint64), np.zeros(len(grams), np.uint64)
        for k, levels in enumerate(each):
            x = levels[n]
            at = np.searchsorted(grams, x["gram"])
            ctx_of[at], low_of[at] = x["context"], x["lower"]
            cat = np.searchsorted(contexts, x["context"])
            once, twice = (x["count"] == 1).sum(), (x["count"] == 2).sum()
            discount = once / (once + 2 * twice) if once else 0.5
            mass = np.bincount(cat, x["count"], len(contexts))
            kinds = np.bincount(cat, minlength=len(contexts))
            seen = mass > 0
            gamma[seen, k] = np.maximum(discount * kinds[seen] / mass[seen], 1e-6)
            p[at, k] = np.maximum(x["count"] - discount, 0) / mass[cat]
        spot = np.searchsorted(contexts, ctx_of)
        if n == 0:
            p += gamma[spot] / (alphabet + 1)
            model.floor = (np.log(gamma[0]) - np.log(alphabet + 1)).astype(np.float32)
        else:
            p += gamma[spot] * below[1][np.searchsorted(below[0], low_of)]
        below = (grams, p)
        model.grams.append(Sorted(grams)), model.contexts.append(Sorted(contexts))
        model.log_p.append(np.log(p).astype(np.float32)), model.log_gamma.append(np.log(gamma).astype(np.float32))
    model.limits = np.full(len(each), np.inf)
    return model


def calibrate(model: Model, texts: dict[str, list[str]]) -> None:
    """Temperature (best likelihood of the true language) and rejection limits, from texts that were not counted."""
    rows, truth = [], []
    for k, language in enumerate(model.languages):
        h, lettered = model.entropy(texts.get(language, []))
        h = h[lettered]
        if len(h):
            rows.append(h), truth.append(np.full(len(h), k))
            model.limits[k] = np.quantile(h[:, k], 1 - model.settings.refused) * 1.1
    if rows:
        h, y = np.concatenate(rows), np.concatenate(truth)
        h = h - h.min(axis=1, keepdims=True)
        costs = {t: float(np.mean(h[np.arange(len(y)), y] / t + _log_sum(-h / t))) for t in np.geomspace(0.01, 1, 25)}
        model.temperature = min(costs, key=costs.get)


def fit(docs: DataFrame, learn: Callable[[Column], Column] = lambda doc_id: F.lit(True), settings: Settings = Settings()) -> Model:
    """Train on a bounded sample of the documents whose id passes ``learn``."""
    common.prepare(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text")).where("doc_id is not null and lang is not null and text is not null").where(learn(F.col("doc_id")))
    # a share of each language by hash, some more than are wanted, so that what is ranked doesn't grow with the rows
    wanted = settings.per_language + 6 * settings.per_language**0.5
    share = rows.groupBy("lang").agg((wanted / F.count("*")).alias("share"))
    draw = F.xxhash64("doc_id")
    some = rows.select("doc_id", "lang").join(share, "lang").where(F.pmod(draw, F.lit(1 << 30)) < F.col("share") * (1 << 30))
    order = W.partitionBy("lang").orderBy(draw, "doc_id")
    ids = some.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= settings.per_language).select("doc_id", "rank")
    sample = rows.join(F.broadcast(ids), "doc_id").orderBy("lang", "rank").toPandas()
    counted: dict[str, list[str]] = {}
    left: dict[str, list[str]] = {}
    for language, rank, text in zip(sample["lang"], sample["rank"], sample["text"], strict=True):
        (left if rank % settings.left_out == 0 else counted).setdefault(language, []).append(text)
    model = build(counted, settings)
    calibrate(model, left)
    return model


PREDICTED = "doc_id long, lang_pred string, score double, rejected boolean"


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """One row per document: doc_id, lang_pred, score, rejected."""
    spark = common.prepare(docs.sparkSession)
    held = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in common.pieces(whole, "text", 512 << 10):
                language, score, rejected = held.value.predict(common.texts_of(batch.column("text")))
                yield pa.record_batch([batch.column("doc_id"), pa.array(language, pa.string()), pa.array(score), pa.array(rejected)], ["doc_id", "lang_pred", "score", "rejected"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, PREDICTED)
