"""Binary token files: static range asymmetric numeral systems.

A file holds the ids of consecutive documents. Its frequency table (of the file's
own ids, scaled to a power of two) is shared by all its blocks. A block holds a
fixed number of ids, dealt over lanes that are coded side by side; it has its own
states and words, decoder checkpoints at which decoding can begin, and checksums of
its bytes and of its ids, so that blocks and their parts decode in parallel.

Files are rows of a binary column, written by Spark's own writer (atomic, on any
store): a lost executor's task is written again from its range of documents.
Documents are dealt out by ranges of their ids, so only partition sums, never
rows, are needed to give each document its place.

Edge cases: null and empty texts are their end id alone; repeated rows and ids are
stored each, ties ordered by text; null ids come first; an empty table gives no file.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import materialize
from .common import id_and_text, released
from .tokens import CachedEncoder

SCALE = 20  # bits of the frequency scale
LOW = 1 << 31  # a state is in [LOW, LOW << 32)
LANES = 1024
BLOCK = 1 << 18  # ids in a block
EVERY = 128  # steps between checkpoints
FILE = 4_000_000  # ids after which a file ends with its document
_MAGIC = b"RANS1\0\0\0"


def frequency_table(ids: np.ndarray, size: int) -> np.ndarray:
    """Counts scaled to a sum of 2**SCALE; no id that occurs gets 0."""
    counts = np.bincount(ids, minlength=size).astype(np.int64)
    if not counts.any():
        return counts
    freq = np.where(counts > 0, np.maximum(1, counts * (1 << SCALE) // counts.sum()), 0)
    over = int(freq.sum()) - (1 << SCALE)
    if over < 0:
        freq[np.argmax(freq)] -= over
    while over > 0:
        big = np.flatnonzero(freq > 1)
        big = big[np.argsort(-freq[big], kind="stable")]
        cut = np.minimum(freq[big] - 1, np.maximum(1, freq[big] * over // max(1, int(freq[big].sum()))))
        done = np.cumsum(cut)
        cut = np.where(done <= over, cut, np.maximum(0, cut - (done - over)))
        freq[big] -= cut
        over -= int(cut.sum())
    return freq


def encode_block(ids: np.ndarray, freq: np.ndarray, start: np.ndarray) -> bytes:
    n = len(ids)
    steps = -(-n // LANES)
    x = np.full(LANES, LOW, np.uint64)
    words: list[np.ndarray] = [None] * steps
    marks = []
    f_all, s_all = freq[ids].astype(np.uint64), start[ids].astype(np.uint64)
    limit = np.uint64((LOW >> SCALE) << 32)
    for t in range(steps - 1, -1, -1):
        lo, hi = t * LANES, min((t + 1) * LANES, n)
        f, live = f_all[lo:hi], x[: hi - lo]
        full = live >= limit * f
        words[t] = live[full].astype(np.uint32)
        live = np.where(full, live >> np.uint64(32), live)
        q = live // f
        x[: hi - lo] = (q << np.uint64(SCALE)) + (live - q * f) + s_all[lo:hi]
        if t % EVERY == 0:
            marks.append((t, x.copy()))
    sizes = np.cumsum([0, *map(len, words)])
    stream = np.concatenate(words) if words else np.zeros(0, np.uint32)
    head = b"".join(struct.pack("<II", t, sizes[t]) + s.astype("<u8").tobytes() for t, s in reversed(marks))
    body = struct.pack("<III", n, len(marks), len(stream)) + head + stream.astype("<u4").tobytes()
    return struct.pack("<II", zlib.crc32(body), zlib.crc32(ids.astype("<u4"))) + body


def decode_block(block: bytes, freq: np.ndarray, start: np.ndarray, slots: np.ndarray, first: int = 0, last: int | None = None) -> np.ndarray:
    """ids [first, last) of a block, begun at the checkpoint before first; all of them are checked against their sum."""
    crc, id_crc = struct.unpack_from("<II", block)
    body = memoryview(block)[8:]
    if zlib.crc32(body) != crc:
        raise ValueError("block is damaged")
    n, n_marks, n_words = struct.unpack_from("<III", body)
    last = n if last is None else min(last, n)
    if first >= last:
        return np.zeros(0, np.uint32)
    size = 8 + 8 * LANES
    at = max((i for i in range(n_marks) if struct.unpack_from("<I", body, 12 + i * size)[0] * LANES <= first), default=0)
    t, word = struct.unpack_from("<II", body, 12 + at * size)
    x = np.frombuffer(body, "<u8", LANES, 12 + at * size + 8).astype(np.uint64)
    stream = np.frombuffer(body, "<u4", n_words, 12 + n_marks * size).astype(np.uint64)
    begun, out = t * LANES, []
    mask, scale, low = np.uint64((1 << SCALE) - 1), np.uint64(SCALE), np.uint64(LOW)
    freq, start = freq.astype(np.uint64), start.astype(np.uint64)
    while t * LANES < last:
        k = min(LANES, n - t * LANES)
        live = x[:k]
        slot = live & mask
        s = slots[slot]
        live = freq[s] * (live >> scale) + slot - start[s]
        need = np.flatnonzero(live < low)
        live[need] = (live[need] << np.uint64(32)) | stream[word : word + len(need)]
        word += len(need)
        x[:k] = live
        out.append(s)
        t += 1
    ids = np.concatenate(out)[first - begun : last - begun]
    if first == 0 and last == n and zlib.crc32(ids.astype("<u4")) != id_crc:
        raise ValueError("ids are damaged")
    return ids


def _table_bytes(freq: np.ndarray) -> bytes:
    used = np.flatnonzero(freq)
    return zlib.compress(np.diff(used, prepend=-1).astype("<u4").tobytes() + freq[used].astype("<u4").tobytes(), 6)


def _table_of(data: bytes) -> np.ndarray:
    both = np.frombuffer(zlib.decompress(data), "<u4").astype(np.int64)
    used = np.cumsum(both[: len(both) // 2]) - 1
    freq = np.zeros(int(used[-1]) + 1 if len(used) else 1, np.int64)
    freq[used] = both[len(both) // 2 :]
    return freq


def write_file(doc_ids: list[int | None], sizes: np.ndarray, ids: np.ndarray) -> bytes:
    """magic | n docs | n blocks | table | document ids, null marks, sizes | block lengths | blocks"""
    freq = frequency_table(ids, int(ids.max()) + 1 if len(ids) else 1)
    start = np.cumsum(freq) - freq
    blocks = [encode_block(ids[i : i + BLOCK], freq, start) for i in range(0, len(ids), BLOCK)]
    table = _table_bytes(freq)
    docs = np.array([d or 0 for d in doc_ids], "<i8").tobytes() + np.array([d is None for d in doc_ids], np.uint8).tobytes() + np.asarray(sizes, "<u8").tobytes()
    head = struct.pack("<QQQ", len(doc_ids), len(blocks), len(table)) + table + docs + np.array([len(b) for b in blocks], "<u8").tobytes()
    return _MAGIC + struct.pack("<IQ", zlib.crc32(head), len(head)) + head + b"".join(blocks)


def open_file(data: bytes):
    """(document ids, sizes, read) of a file; read(first, last) decodes only the blocks, and parts of blocks, that it needs."""
    if data[:8] != _MAGIC:
        raise ValueError("not a token file")
    crc, size = struct.unpack_from("<IQ", data, 8)
    head = memoryview(data)[20 : 20 + size]
    if zlib.crc32(head) != crc:
        raise ValueError("header is damaged")
    n, n_blocks, n_table = struct.unpack_from("<QQQ", head)
    freq = _table_of(bytes(head[24 : 24 + n_table]))
    start = np.cumsum(freq) - freq
    slots = np.repeat(np.arange(len(freq), dtype=np.uint32), freq)
    at = 24 + n_table
    docs, null = np.frombuffer(head, "<i8", n, at), np.frombuffer(head, np.uint8, n, at + 8 * n)
    sizes = np.frombuffer(head, "<u8", n, at + 9 * n).astype(np.int64)
    ends = np.cumsum(np.frombuffer(head, "<u8", n_blocks, at + 17 * n).astype(np.int64)) + 20 + size

    def read(first: int, last: int) -> np.ndarray:
        out = []
        for b in range(first // BLOCK, -(-last // BLOCK)):
            block = data[ends[b - 1] if b else 20 + size : ends[b]]
            out.append(decode_block(block, freq, start, slots, max(0, first - b * BLOCK), min(BLOCK, last - b * BLOCK)))
        return np.concatenate(out) if out else np.zeros(0, np.uint32)

    return [None if z else int(d) for d, z in zip(docs, null)], sizes, read


def _writer(path: str, end_id: int):
    def write(batches):
        from pyspark import TaskContext

        encoder, part = CachedEncoder.of(path), TaskContext.get().partitionId()
        docs, held, total, number = [], [], 0, 0

        def file():
            ids = np.concatenate(held)
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([number], pa.int32()), pa.array([len(ids)], pa.int64()), pa.array([write_file(docs, np.array([len(x) for x in held]), ids)], pa.binary())], names=["part", "number", "n_ids", "data"])

        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                some = batch.slice(lo, 500)
                sizes, ids = encoder.encode_column(some.column(1))
                ends = np.cumsum(sizes)
                closed = np.insert(ids, ends, encoder.dtype.type(end_id))
                for d, part_ids in zip(some.column(0).to_pylist(), np.split(closed, (ends + np.arange(1, len(ends) + 1))[:-1])):
                    docs.append(d)
                    held.append(part_ids)
                    total += len(part_ids)
                    if total >= FILE:
                        yield file()
                        docs, held, total, number = [], [], 0, number + 1
        if docs:
            yield file()

    return write


def _reader(batches):
    for batch in batches:
        for i in range(batch.num_rows):
            part, number = batch.column(0)[i].as_py(), batch.column(1)[i].as_py()
            docs, sizes, read = open_file(batch.column(3)[i].as_py())
            ids = read(0, int(sizes.sum())).astype("<u4")
            ends = np.cumsum(sizes)
            crc = [zlib.crc32(ids[e - s : e]) for s, e in zip(sizes, ends)]
            n = len(docs)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(n, part, np.int32)), pa.array(np.full(n, number, np.int32)), pa.array(docs, pa.int64()), pa.array(ends - sizes), pa.array(sizes), pa.array(crc, pa.int64())], names=["part", "number", "doc_id", "local", "n_tokens", "ids_crc32"])


def write_tokens(docs: DataFrame, path: str, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode all texts, in ascending order of their ids, into token files: ``part, number, n_ids, data``, written and reread."""
    rows = id_and_text(docs, id_col, text_col).repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    return materialize(rows.mapInArrow(released(_writer(path, end_id)), "part int, number int, n_ids long, data binary"), "tokens")


def read_tokens(files: DataFrame) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every document in the files."""
    sizes = files.select("part", "number", "n_ids")
    parts = sizes.groupBy("part").agg(F.sum("n_ids").alias("n"))
    before = lambda *by: Window.partitionBy(*by).rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select("part", F.coalesce(F.sum("n").over(before(F.lit(0)).orderBy("part")), F.lit(0)).alias("base"))
    offsets = sizes.join(parts, "part").select("part", "number", (F.col("base") + F.coalesce(F.sum("n_ids").over(before("part").orderBy("number")), F.lit(0))).alias("base"))
    found = files.mapInArrow(released(_reader), "part int, number int, doc_id long, local long, n_tokens long, ids_crc32 long")
    return found.join(offsets, ["part", "number"]).select("doc_id", (F.col("base") + F.col("local")).alias("start"), "n_tokens", "ids_crc32")
