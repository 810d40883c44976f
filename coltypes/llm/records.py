"""Length-delimited binary records of token ids, with a separate offset index for shuffled reads.

File format. A data file is a run of frames: the payload's length as an unsigned 64-bit integer, the
masked CRC-32C of those 8 bytes, the payload, the masked CRC-32C of the payload; all little-endian.
The mask rotates the checksum right by 15 bits and adds a constant, so that checksums of data that
hold checksums stay sound. A payload is doc_id (signed 64 bits; a flag byte tells whether it is
null), the width of an id in bytes (2 where the vocabulary fits, else 4), and the ids. An index file
holds for each frame its offset, its length, its document's first id in the file, and its number of
ids, as unsigned 64-bit integers.

Files follow ascending doc_id (nulls first; repeated ids by a hash of the text): file k holds range
k of the ids. Each task writes a file under a name of its own and renames it when it is whole, so a
task that runs twice, or is lost, leaves the same file. Reading checks every checksum.

Defined cases: null text counts as empty and yields the end id alone; an empty table yields no file.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coltypes.llm import bpe, common

# Fixed values of the format: the reversed Castagnoli polynomial and the constant of the mask.
POLYNOMIAL = 0x82F63B78
MASK = 0xA282EAD8

_CHUNK = 256


def _byte_table() -> np.ndarray:
    t = np.arange(256, dtype=np.uint32)
    for _ in range(8):
        t = np.where(t & 1, (t >> 1) ^ np.uint32(POLYNOMIAL), t >> 1).astype(np.uint32)
    return t


_TABLE = _byte_table()


def _shift_tables() -> np.ndarray:
    """Tables, one for each byte of the state, that carry a state over a chunk of zero bytes."""
    state = (np.arange(256, dtype=np.uint32)[None, :] << (8 * np.arange(4, dtype=np.uint32))[:, None]).reshape(-1)
    for _ in range(_CHUNK):
        state = _TABLE[state & 0xFF] ^ (state >> 8)
    return state.reshape(4, 256)


_SHIFT = _shift_tables()


def crc32c(payloads: list[bytes]) -> np.ndarray:
    """CRC-32C of many byte strings at once: all their chunks step together, then chunks are joined record by record."""
    if not payloads:
        return np.zeros(0, np.uint32)
    lengths = np.array([len(p) for p in payloads], np.int64)
    chunks = np.maximum(1, -(-(lengths + 4) // _CHUNK))
    first = np.concatenate([[0], np.cumsum(chunks)])
    grid = np.zeros(int(first[-1]) * _CHUNK, np.uint8)
    for k, p in enumerate(payloads):  # zeros in front leave a zero state as it is
        end = int(first[k + 1]) * _CHUNK
        grid[end - len(p) : end] = np.frombuffer(p, np.uint8)
    starts = first[1:] * _CHUNK - lengths
    # a start state of all ones is the same as the first four bytes inverted; four zero bytes in front would be needed below that
    short = lengths < 4
    for j in range(4):
        at = (starts + j)[~short]
        grid[at] ^= 0xFF
    grid = np.ascontiguousarray(grid.reshape(-1, _CHUNK).T)
    state = np.zeros(grid.shape[1], np.uint32)
    for row in grid:
        state = _TABLE[(state ^ row) & 0xFF] ^ (state >> 8)
    out = state[first[:-1]]
    for j in range(1, int(chunks.max())):
        on = np.flatnonzero(chunks > j)
        s = out[on]
        out[on] = _SHIFT[0][s & 0xFF] ^ _SHIFT[1][(s >> 8) & 0xFF] ^ _SHIFT[2][(s >> 16) & 0xFF] ^ _SHIFT[3][s >> 24] ^ state[first[on] + j]
    for k in np.flatnonzero(short):
        s = 0xFFFFFFFF
        for b in payloads[k]:
            s = int(_TABLE[(s ^ b) & 0xFF]) ^ (s >> 8)
        out[k] = s
    return out ^ np.uint32(0xFFFFFFFF)


def masked(crc: np.ndarray) -> np.ndarray:
    return ((crc >> 15) | (crc << 17)) + np.uint32(MASK)


def frames(payloads: list[bytes]) -> list[bytes]:
    """Each payload with its length and both masked checksums."""
    heads = [struct.pack("<Q", len(p)) for p in payloads]
    sums, head_sums = masked(crc32c(payloads)), masked(crc32c(heads))
    return [b"".join((h, struct.pack("<I", hs), p, struct.pack("<I", s))) for h, hs, p, s in zip(heads, head_sums.tolist(), payloads, sums.tolist(), strict=True)]


def payload(doc_id: int | None, ids: np.ndarray, width: int) -> bytes:
    return struct.pack("<qBB", doc_id or 0, doc_id is None, width) + ids.astype(f"<u{width}").tobytes()


def parsed(data: bytes) -> tuple[int | None, np.ndarray]:
    doc_id, null, width = struct.unpack_from("<qBB", data)
    return (None if null else doc_id), np.frombuffer(data, f"<u{width}", offset=10).astype("<u4")


class Damaged(ValueError):
    """A frame whose length or checksum is wrong."""


def read(source, most: int = 4 << 20) -> Iterator[list[bytes]]:
    """Lists of payloads, checked, from an open file; about ``most`` bytes at a time."""
    rest, want = b"", most
    while True:
        data = source.read(want)
        last, rest, at, heads, bodies, sums = not data, rest + data, 0, [], [], []
        want = most
        while len(rest) - at >= 12:
            (n,) = struct.unpack_from("<Q", rest, at)
            if n > 1 << 40:
                raise Damaged("length")
            if len(rest) - at < n + 16:
                if last:
                    raise Damaged("cut off")
                want = max(most, n + 16 - (len(rest) - at))  # the rest of a long frame at once
                break
            heads.append(rest[at : at + 8])
            bodies.append(rest[at + 12 : at + 12 + n])
            sums.append((struct.unpack_from("<I", rest, at + 8)[0], struct.unpack_from("<I", rest, at + 12 + n)[0]))
            at += n + 16
        if bodies:
            told = np.array(sums, np.uint32)
            if (masked(crc32c(heads)) != told[:, 0]).any() or (masked(crc32c(bodies)) != told[:, 1]).any():
                raise Damaged("checksum")
            yield bodies
        rest = rest[at:]
        if last:
            if rest:
                raise Damaged("cut off")
            return


def read_at(data_uri: str, index_uri: str, order: list[int]) -> Iterator[tuple[int | None, np.ndarray]]:
    """Records of one file in any order, by its index."""
    store, path = fs.FileSystem.from_uri(data_uri)
    index_store, index_path = fs.FileSystem.from_uri(index_uri)
    with index_store.open_input_stream(index_path) as f:
        index = np.frombuffer(f.read(), "<u8").reshape(-1, 4)
    with store.open_input_file(path) as f:
        for k in order:
            frame = f.read_at(int(index[k, 1]), int(index[k, 0]))
            yield parsed(next(read(pa.BufferReader(frame)))[0])


def uri(path: str) -> str:
    return path if "://" in path else f"file://{path.removeprefix('file:')}"


MANIFEST = "file long, data string, offsets string, n_docs long, n_tokens long"


def write(docs: DataFrame, tokenizer: str, end_id: int, folder: str, files: int | None = None) -> DataFrame:
    """Encode, append the end id and write; returns the manifest, one row per file in ascending order of ids, which the driver holds."""
    spark = common.prepare(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    files = files or max(1, rows.rdd.getNumPartitions())
    rows = rows.repartitionByRange(files, "doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))
    folder = uri(folder)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = bpe.encoder(tokenizer)
        width = 2 if encoder.library.get_vocab_size() <= 1 << 16 and end_id < 1 << 16 else 4
        k, attempt = TaskContext.get().partitionId(), uuid.uuid4().hex[:8]
        store, base = fs.FileSystem.from_uri(folder)
        store.create_dir(base, recursive=True)
        data, offsets = f"part-{k:06d}.records", f"part-{k:06d}.index"
        n_docs = n_tokens = at = 0
        with store.open_output_stream(f"{base}/.{data}.{attempt}") as out, store.open_output_stream(f"{base}/.{offsets}.{attempt}") as index:
            for whole in batches:
                for batch in common.pieces(whole, "text", 1 << 20):
                    ids = [np.append(x, np.uint32(end_id)) for x in encoder.encode_all(common.texts_of(batch.column("text")))]
                    made = frames([payload(i, x, width) for i, x in zip(batch.column("doc_id").to_pylist(), ids, strict=True)])
                    entries = np.zeros((len(made), 4), "<u8")
                    for j, (frame, x) in enumerate(zip(made, ids, strict=True)):
                        entries[j] = at, len(frame), n_tokens, len(x)
                        at, n_tokens = at + len(frame), n_tokens + len(x)
                    out.write(b"".join(made))
                    index.write(entries.tobytes())
                    n_docs += len(made)
        store.move(f"{base}/.{offsets}.{attempt}", f"{base}/{offsets}")
        store.move(f"{base}/.{data}.{attempt}", f"{base}/{data}")
        yield pa.record_batch([pa.array([k]), pa.array([f"{folder}/{data}"]), pa.array([f"{folder}/{offsets}"]), pa.array([n_docs], pa.int64()), pa.array([n_tokens], pa.int64())], ["file", "data", "offsets", "n_docs", "n_tokens"])

    written = rows.mapInArrow(run, MANIFEST).where("n_docs > 0").collect()
    return spark.createDataFrame(sorted(written), MANIFEST)


ROWS = "doc_id long, start long, n_tokens long, ids_crc32 long"


def read_back(manifest: DataFrame) -> DataFrame:
    """One row per record: doc_id, start (ids of all documents before it), n_tokens, ids_crc32 of its ids as 32-bit integers.

    The manifest has a row per file, so its running sum is made on the driver.
    """
    spark: SparkSession = manifest.sparkSession
    listed, before, rows = sorted(manifest.collect(), key=lambda r: r["file"]), 0, []
    for place, r in enumerate(listed):
        rows.append((place, r["data"], before))
        before += r["n_tokens"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, start in zip(batch.column("data").to_pylist(), batch.column("before").to_pylist(), strict=True):
                store, inner = fs.FileSystem.from_uri(path)
                with store.open_input_stream(inner) as source:
                    for bodies in read(source):
                        out = []
                        for body in bodies:
                            doc_id, ids = parsed(body)
                            out.append((doc_id, start, len(ids), zlib.crc32(ids.tobytes())))
                            start += len(ids)
                        yield pa.record_batch([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["doc_id", "start", "n_tokens", "ids_crc32"])

    frame = spark.createDataFrame(rows, "place int, data string, before long")
    return frame.repartitionById(max(1, len(rows)), F.col("place")).mapInArrow(run, ROWS)
