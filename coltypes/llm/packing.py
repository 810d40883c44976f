"""Vector bin packing of token sequences under limits on tokens, segments and loss-bearing tokens.

Every item asks for a vector (tokens, 1 segment, loss-bearing tokens) and every sequence offers a
capacity. A sequence is filled by the dot-product heuristic: of the items that fit into what is left,
the one with the largest scalar product of its demand and the residual, both as shares of the
capacity, comes next; so the scarcest dimension that an item is rich in counts most. With ``cut`` the
gap that no item fits is filled with the head of the largest item, whose rest goes back to the pool.

Each task packs its own stream in windows of ``window`` items; the last unfilled sequence of a window
goes on into the next one, so a task pads one sequence at most (with ``cut``, and while segments do
not run out first). A document longer than a sequence fills sequences of its own first.

The loss-bearing tokens of an item are its last ones, as the answer follows the prompt; so each cut
knows how many it takes along.

Defined cases: null text counts as empty (its end id alone is packed); an item that asks for more
than a capacity, when it may not be cut, gets a sequence of its own; repeated rows are packed each;
an item without tokens (null or 0) takes a segment.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.llm import bpe, common


@dataclass(frozen=True)
class Settings:
    tokens: int = 2048
    segments: int = 256
    loss: int = 2048
    window: int = 1024
    cut: bool = True
    #: distinct pieces of text that a worker remembers the ids of
    store: int = 400_000

    @property
    def capacity(self) -> np.ndarray:
        return np.array([self.tokens, self.segments, self.loss], float)


class Packer:
    """Packs items of (name, tokens, loss) into sequences; ``take`` yields (name, first token, length, sequence, offset)."""

    def __init__(self, s: Settings, first_sequence: int = 0):
        self.s, self.sequence = s, first_sequence
        self.pool: list[tuple] = []  # (name, first, length, loss)
        self.open: list[tuple] = []  # pieces of the sequence being filled
        self.left = s.capacity.copy()

    def _close(self) -> list[tuple]:
        out, at = [], 0
        for name, first, length in self.open:
            out.append((name, first, length, self.sequence, at))
            at += length
        self.open, self.left = [], self.s.capacity.copy()
        self.sequence += bool(out)
        return out

    def _place(self, name, first: int, length: int, loss: int) -> None:
        self.open.append((name, first, length))
        self.left -= (length, 1, loss)

    def add(self, name, length: int, loss: int) -> Iterator[tuple]:
        """Take an item in; yields the pieces of sequences that are full."""
        s, first = self.s, 0
        if s.cut:
            loss = min(loss, length)
            while length > first:
                step = min(s.tokens, length - first - loss + s.loss)
                if length - first < step:
                    break
                yield (name, first, step, self.sequence_of_own(), 0)
                first += step
                loss = min(loss, length - first)
        elif length > s.tokens or loss > s.loss:
            yield (name, 0, length, self.sequence_of_own(), 0)
            return
        if length > first or not length:
            self.pool.append((name, first, length - first, loss))
        if len(self.pool) >= s.window:
            yield from self._pack(s.window // 2)

    def sequence_of_own(self) -> int:
        """A full sequence beside the open one: numbers stay unique as the open one moves on."""
        self.sequence += 1
        return self.sequence - 1

    def _pack(self, most_left: int) -> Iterator[tuple]:
        cap = self.s.capacity
        demand = np.array([(n, 1, loss) for _, _, n, loss in self.pool], float).reshape(-1, 3)
        alive = np.ones(len(self.pool), bool)
        count = len(self.pool)
        while count > most_left:
            fits = alive & (demand <= self.left).all(axis=1)
            if fits.any():
                gain = np.where(fits, (demand / cap) @ (self.left / cap), -1.0)
                k = int(gain.argmax())
                name, first, n, loss = self.pool[k]
                self._place(name, first, n, loss)
                alive[k] = False
                count -= 1
            elif self.s.cut and self.left[0] >= 1 and self.left[1] >= 1 and self.left[2] >= 1:
                k = int(np.where(alive, demand[:, 0], -1).argmax())
                name, first, n, loss = self.pool[k]
                head = int(min(self.left[0], n - 1, n - loss + self.left[2]))
                if head < 1:
                    yield from self._close()
                    continue
                part = max(0, head - (n - loss))
                self._place(name, first, head, part)
                self.pool[k] = (name, first + head, n - head, loss - part)
                demand[k] = (n - head, 1, loss - part)
                yield from self._close()
                continue
            else:
                yield from self._close()
                continue
            if self.left.min() < 1:
                yield from self._close()
        self.pool = [p for p, a in zip(self.pool, alive, strict=True) if a]

    def finish(self) -> Iterator[tuple]:
        yield from self._pack(0)
        yield from self._close()


PACKED = "doc_id long, start long, length long, ids binary, loss_mask binary, doc_tokens long, sequence_id long, offset long"


def _mask(total: int, loss: int, first: int, length: int, offset: int) -> bytes:
    out = np.zeros(length, np.uint8)
    out[max(0, total - loss - first) :] = 1
    if not offset:
        out[:1] = 0  # nothing stands before it
    return out.tobytes()


def pack_sequences(docs: DataFrame, tokenizer: str, end_id: int, settings: Settings = Settings(), loss: str | None = None) -> DataFrame:
    """One row per piece of a document: its ids, its loss mask, where it starts in the document and in its sequence.

    ids holds little-endian uint32 and loss_mask one byte (0 or 1) for each id; the pieces of a
    sequence_id in the order of offset are the sequence. ``loss`` names a column of ``docs`` with the
    number of loss-bearing ids, the last ones of a document with its end id. Without it, or where it is
    null, all ids bear loss. The first id of a sequence never does, though it is counted under the limit.
    """
    s = settings
    names = ["doc_id", "start", "length", "ids", "loss_mask", "doc_tokens", "sequence_id", "offset"]
    kinds = [pa.binary() if n in ("ids", "loss_mask") else pa.int64() for n in names]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = bpe.encoder(tokenizer, s.store)
        packer = Packer(s, TaskContext.get().partitionId() << 40)
        held: dict[int, list] = {}  # of documents not wholly placed: doc_id, ids, loss-bearing ids, ids still to place
        serial = 0

        def told(placed: list[tuple]) -> pa.RecordBatch:
            rows = []
            for name, first, length, sequence, offset in placed:
                entry = held[name]
                doc_id, ids, bearing, _ = entry
                rows.append((doc_id, first, length, ids[first : first + length].tobytes(), _mask(len(ids), bearing, first, length, offset), len(ids), sequence, offset))
                entry[3] -= length
                if not entry[3]:
                    del held[name]
            columns = list(zip(*rows, strict=True)) or [()] * len(names)
            return pa.record_batch([pa.array(c, kind) for c, kind in zip(columns, kinds, strict=True)], names)

        for batch in (piece for whole in batches for piece in common.pieces(whole, "text", 1 << 19)):
            placed = []
            for doc_id, wanted, ids in zip(batch.column("doc_id").to_pylist(), batch.column("loss").to_pylist(), encoder.encode_all(common.texts_of(batch.column("text"))), strict=True):
                ids = np.append(ids, np.uint32(end_id)).astype("<u4")
                bearing = len(ids) if wanted is None else min(max(wanted, 0), len(ids))
                held[serial] = [doc_id, ids, bearing, len(ids)]
                placed += packer.add(serial, len(ids), bearing)
                serial += 1
            yield told(placed)
        yield told(list(packer.finish()))

    common.prepare(docs.sparkSession)
    bearing = (docs[loss] if loss else F.lit(None)).cast("long").alias("loss")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), bearing).mapInArrow(run, PACKED)


def digest(packed: DataFrame) -> DataFrame:
    """The pieces with the checksum of their ids in place of these and of the mask."""
    return packed.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def pack_documents(docs: DataFrame, tokenizer: str, end_id: int, settings: Settings = Settings(), loss: str | None = None) -> DataFrame:
    """The digest of ``pack_sequences``."""
    return digest(pack_sequences(docs, tokenizer, end_id, settings, loss))


def assign(items: DataFrame, settings: Settings = Settings(cut=False)) -> DataFrame:
    """Sequences for whole instruction examples given as (item_id, tokens, loss): item_id, sequence_id, offset, tokens, loss."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(settings, TaskContext.get().partitionId() << 40)
        losses: dict[int, tuple] = {}
        serial = 0

        def told(placed: list[tuple]) -> pa.RecordBatch:
            rows = [(*losses[name], length, sequence, offset) if first + length < losses[name][2] else (*losses.pop(name), length, sequence, offset) for name, first, length, sequence, offset in placed]
            columns = list(zip(*[(r[0], r[4], r[5], r[3], r[1]) for r in rows], strict=True)) or [()] * 5
            return pa.record_batch([pa.array(c, pa.int64()) for c in columns], ["item_id", "sequence_id", "offset", "tokens", "loss"])

        for batch in batches:
            placed = []
            for item, tokens, loss in zip(*(batch.column(c).to_pylist() for c in ("item_id", "tokens", "loss")), strict=True):
                tokens, loss = max(tokens or 0, 0), max(loss or 0, 0)
                losses[serial] = (item, loss, tokens)
                placed += packer.add(serial, tokens, loss)
                serial += 1
            yield told(placed)
        yield told(list(packer.finish()))

    common.prepare(items.sparkSession)
    return items.selectExpr("cast(item_id as long) item_id", "cast(tokens as long) tokens", "cast(loss as long) loss").mapInArrow(run, "item_id long, sequence_id long, offset long, tokens long, loss long")


COUNTED = "conv_id long, tokens long, loss long"


def conversation_items(conversations: DataFrame, tokenizer: str, end_id: int, bearing: str = "assistant", store: int | None = None) -> DataFrame:
    """(item_id, tokens, loss): one item per conversation; every turn ends with the end id, and turns of one role bear loss.

    Turns are counted where they lie and only counts are summed, so a conversation may have any
    number of turns. Null texts count as empty; turns without a conv_id are one item.
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = bpe.encoder(tokenizer, store)
        for batch in (piece for whole in batches for piece in common.pieces(whole, "text")):
            tokens = np.array([len(ids) + 1 for ids in encoder.encode_all(common.texts_of(batch.column("text")))], np.int64)
            loss = np.where(batch.column("bears").to_numpy(zero_copy_only=False), tokens, 0)
            yield pa.record_batch([batch.column("conv_id"), pa.array(tokens), pa.array(loss)], ["conv_id", "tokens", "loss"])

    common.prepare(conversations.sparkSession)
    bears = F.coalesce(F.col("role") == bearing, F.lit(False)).alias("bears")
    turns = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("text").cast("string").alias("text"), bears)
    counted = turns.mapInArrow(run, COUNTED)
    return counted.groupBy(F.col("conv_id").alias("item_id")).agg(F.sum("tokens").alias("tokens"), F.sum("loss").alias("loss"))
