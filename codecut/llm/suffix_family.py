"""Repeated passages by a logarithmic family of sparse suffix arrays.

Every byte covered by a ``width``-byte string that also starts earlier (in a document with a smaller
id, or earlier in the same one) is removed; strings are judged on the input and do not cross documents.

Sampling. Each window of ``width`` bytes elects an anchor: the ``gram`` bytes in it whose
fingerprint is smallest, the leftmost if tied. Equal windows elect equal anchors at equal places,
so comparing anchored suffixes finds every repeat; with grams of 32 bytes, one position in 35 is an anchor.
Consecutive windows with one anchor form a run.

Index family. A batch of text gets a sparse suffix array: its runs, ordered by the fingerprint of the
anchor and then of the whole stretch that the run covers (suffix order is taken over
fingerprints, not over bytes: only equality of long prefixes counts here). A new batch is
merge-scanned against all levels; of equal runs the earliest stays and the others are found repeated.
Then it becomes a level, and levels of like size merge, so there are logarithmically many.

Distribution. Each task feeds its batches into a family of its own. What is equal there
collapses, so a passage or group of copies that a third of all documents hold costs one run a task.
The runs left go to buckets of anchors; a bucket again is a family, fed by the tasks' arrays.
Anchors with one kind of run are settled there. Where an anchor has runs that differ (the edges of passages),
the windows in those runs are asked for again with longer grams, and at last with grams of the whole
width, where a run is one window and nothing is left open. An anchor that already has several kinds of run in one
task is passed on by that task at once, with a note for its bucket, so a very frequent phrase never gathers in a bucket.
Text is shuffled once, by document; all its uses read the same exchange.

Fingerprints have 64 bits for anchors and 64 more for runs; in the last pass, which decides on single windows, the
64 more come from an independent family. There are at least as many buckets as the bytes of all texts fill at ``BUCKET`` bytes each.

Edge cases: null text is empty; texts shorter than a window lose nothing; null ids (and the smallest long, which stands for them) come before all others; rows with
one id and different texts are documents of their own, in the order of their texts' hashes; rows that repeat (id and
text) are judged once and all get that result; an empty table gives an empty result; texts of any length
are cut into overlapping pieces for memory only.
"""

from __future__ import annotations

import hashlib
import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import checkpoint
from .common import boxed, quoted, released

GRAMS = (32, 72)  # then the width itself
GROUP = 1 << 20  # bytes that are fingerprinted at once
BUCKET = 1 << 28  # bytes of text whose runs make a bucket: as many bytes of runs, where nothing is repeated
_PLACE = np.uint64((1 << 23) - 1)
_BASES = (0x9E3779B97F4A7C15, 0xD1342543DE82EF95)  # odd
_FIRST = -(1 << 63)

_RUN = np.dtype([("h", "<u8"), ("c", "<u8"), ("k", "<i8"), ("t", "<i8"), ("pos", "<i4"), ("len", "<i4")])


def _mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(29))
    x = x * np.uint64(0xA0761D6478BD642F)
    return x ^ (x >> np.uint64(32))


class _Rolling:
    """Fingerprints of any stretch of a group of bytes, by prefix sums of powers."""

    _made: dict[int, "_Rolling"] = {}

    @classmethod
    def get(cls, which: int = 0) -> "_Rolling":
        """One of two independent families of fingerprints."""
        if which not in cls._made:
            cls._made[which] = cls(which)
        return cls._made[which]

    def __init__(self, which: int):
        n = GROUP + 4096
        self.bytes = np.random.default_rng(20_24 + which).integers(0, 1 << 64, 256, dtype=np.uint64)
        self.up = self._powers(_BASES[which], n)
        self.down = self._powers(pow(_BASES[which], -1, 1 << 64), n)

    @staticmethod
    def _powers(base: int, n: int) -> np.ndarray:
        out = np.full(n, base, np.uint64)
        out[0] = 1
        return np.cumprod(out)

    def sums(self, data: np.ndarray) -> np.ndarray:
        out = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(self.bytes[data] * self.up[: len(data)], out=out[1:])
        return out

    def of(self, sums: np.ndarray, at: np.ndarray, size) -> np.ndarray:
        return _mix((sums[at + size] - sums[at]) * self.down[at])


def _valid(n: int, starts: np.ndarray, ends: np.ndarray, width: int) -> np.ndarray:
    """Which of n places begin a window within its piece."""
    mark = np.zeros(n + 1, np.int32)
    long = ends - starts >= width
    np.add.at(mark, starts[long], 1)
    np.add.at(mark, ends[long] - width + 1, -1)
    return np.cumsum(mark[:n]) > 0


def runs_of(data: np.ndarray, starts: np.ndarray, windows: np.ndarray, width: int, gram: int):
    """(piece, position in the piece, covered length, anchor fingerprint, run fingerprint) of the runs among the windows at the given places."""
    roll = _Rolling.get()
    sums = roll.sums(data)
    grams = _mix((sums[gram:] - sums[:-gram]) * roll.down[: len(data) - gram + 1])
    if gram == width:
        anchor = windows
        new = np.arange(len(windows))
    else:
        low = (grams & ~_PLACE) | np.arange(len(grams), dtype=np.uint64)
        span, want = 1, width - gram + 1
        while span < want:
            step = min(span, want - span)
            low = np.minimum(low[:-step], low[step:])
            span += step
        anchor = (low[windows] & _PLACE).astype(np.int64)
        new = np.flatnonzero(np.concatenate([[True], (np.diff(windows) != 1) | (np.diff(anchor) != 0)]))
    lo, count, anchor = windows[new], np.diff(np.concatenate([new, [len(windows)]])), anchor[new]
    size = count + width - 1
    if gram < width:
        run = _mix(roll.of(sums, lo, size) ^ ((anchor - lo) * 1_000_003 + count).astype(np.uint64))
    else:  # nothing looks at these windows again: a second, independent fingerprint
        other = _Rolling.get(1)
        run = other.of(other.sums(data), lo, width)
    piece = np.searchsorted(starts, lo, "right") - 1
    return piece, lo - starts[piece], size, grams[anchor], run


class SuffixFamily:
    """Levels of sparse suffix arrays; ``repeated`` gets the runs that a smaller equal one makes superfluous."""

    def __init__(self):
        self.levels: list[np.ndarray] = []
        self.repeated: list[np.ndarray] = []

    @staticmethod
    def sort(runs: np.ndarray) -> np.ndarray:
        runs = runs[np.argsort(runs["h"], kind="stable")]
        same = runs["h"][1:] == runs["h"][:-1]
        tied = np.flatnonzero(np.concatenate([same, [False]]) | np.concatenate([[False], same]))
        if len(tied):
            part = runs[tied]
            runs[tied] = part[np.lexsort([part[x] for x in ("pos", "t", "k", "c", "h")])]
        return runs

    def _settle(self, runs: np.ndarray) -> np.ndarray:
        """Of sorted runs, the earliest of each kind."""
        if len(runs) < 2:
            return runs
        same = np.concatenate([[False], (runs["h"][1:] == runs["h"][:-1]) & (runs["c"][1:] == runs["c"][:-1])])
        if not same.any():
            return runs
        first = runs[np.maximum.accumulate(np.where(same, 0, np.arange(len(runs))))]
        again = same & ((runs["k"] != first["k"]) | (runs["t"] != first["t"]) | (runs["pos"] != first["pos"]))
        if again.any():
            self.repeated.append(runs[again])
        return runs[~same]

    def add(self, batch: np.ndarray) -> None:
        batch = self._settle(self.sort(batch))
        for i, level in enumerate(self.levels):  # the merge scan
            if not len(level) or not len(batch):
                continue
            place = np.minimum(np.searchsorted(level["h"], batch["h"]), len(level) - 1)
            hit = np.flatnonzero(level["h"][place] == batch["h"])
            if not len(hit):
                continue
            shared = np.unique(batch["h"][hit])
            lo, hi = np.searchsorted(level["h"], shared), np.searchsorted(level["h"], shared, "right")
            theirs = np.repeat(lo - np.cumsum(hi - lo) + (hi - lo), hi - lo) + np.arange(int((hi - lo).sum()))
            both = self._settle(self.sort(np.concatenate([level[theirs], batch[hit]])))
            self.levels[i] = np.delete(level, theirs)
            batch = self.sort(np.concatenate([np.delete(batch, hit), both]))
        self.levels.append(batch)
        self.levels.sort(key=len, reverse=True)
        while len(self.levels) > 1 and len(self.levels[-2]) < 2 * len(self.levels[-1]):
            last = self.levels.pop()
            self.levels[-1] = self._settle(self.sort(np.concatenate([self.levels[-1], last])))
            self.levels.sort(key=len, reverse=True)

    def merged(self) -> np.ndarray:
        """All levels as one suffix array."""
        if not self.levels:
            return np.zeros(0, _RUN)
        out = self._settle(self.sort(np.concatenate(self.levels)))
        self.levels = [out]
        return out

    def take_repeated(self) -> np.ndarray:
        out = np.concatenate(self.repeated) if self.repeated else np.zeros(0, _RUN)
        self.repeated = []
        return out


def _pack(runs: np.ndarray) -> bytes:
    """Columns as planes of bytes, so that bytes that are all alike cost nothing once compressed."""
    return struct.pack("<I", len(runs)) + b"".join(np.ascontiguousarray(runs[f]).view(np.uint8).reshape(len(runs), -1).T.tobytes() for f in _RUN.names) if len(runs) else struct.pack("<I", 0)


def _unpack(data: bytes) -> np.ndarray:
    (n,) = struct.unpack_from("<I", data)
    out, at = np.zeros(n, _RUN), 4
    for f in _RUN.names:
        w = _RUN[f].itemsize
        out[f] = np.ascontiguousarray(np.frombuffer(data, np.uint8, n * w, at).reshape(w, n).T).view(_RUN[f]).ravel()
        at += n * w
    return out


_BATCH = 300_000  # runs in a batch of a family
_KINDS = {"runs": 0, "many": 1, "edges": 2, "gone": 3}


def _rows(bucket: np.ndarray, kind: str, runs: np.ndarray):
    """(bucket, kind, data) rows of runs, one a bucket."""
    order = np.argsort(bucket, kind="stable")
    bucket, runs = bucket[order], runs[order]
    cuts = np.flatnonzero(np.diff(bucket)) + 1
    firsts = np.concatenate([[0], cuts]).astype(int)
    lasts = np.concatenate([cuts, [len(runs)]]).astype(int)
    for lo in range(0, len(firsts), 256):
        some = slice(lo, lo + 256)
        data = [_pack(runs[a:b]) for a, b in zip(firsts[some], lasts[some])]
        yield pa.RecordBatch.from_arrays([pa.array(bucket[firsts[some]].astype(np.int32)), pa.array(np.full(len(data), _KINDS[kind], np.int32)), pa.array(data, pa.binary())], names=["bucket", "kind", "data"])


def _by_fingerprint(runs: np.ndarray, buckets: int) -> np.ndarray:
    return ((runs["h"] >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64)


def _by_document(runs: np.ndarray, buckets: int) -> np.ndarray:
    return np.abs(runs["k"] % buckets)


def _joined(runs: np.ndarray) -> np.ndarray:
    """Overlapping or touching covered stretches of a document as one."""
    if len(runs) < 2:
        return runs
    runs = runs[np.lexsort([runs["pos"], runs["t"], runs["k"]])]
    end = runs["pos"].astype(np.int64) + runs["len"]
    other = np.concatenate([[True], (runs["k"][1:] != runs["k"][:-1]) | (runs["t"][1:] != runs["t"][:-1])])
    group = np.cumsum(other)
    reach = np.maximum.accumulate(end + group * (1 << 33)) - group * (1 << 33)
    new = other | np.concatenate([[True], runs["pos"][1:] > reach[:-1]])
    first = np.flatnonzero(new)
    out = runs[first]
    out["len"] = np.maximum.reduceat(end, first) - out["pos"]
    return out


def _pieces(texts, width: int, most: int = GROUP):
    """Groups of pieces of the texts: (data, starts, ends, which text, offset in it)."""
    held, size = [], 0
    for i, text in enumerate(texts):
        data = text.as_buffer() if isinstance(text, pa.Scalar) else text
        data = np.frombuffer(data, np.uint8) if data is not None and len(data) else np.zeros(0, np.uint8)
        for lo in range(0, max(1, len(data) - width + 1), most - width + 1):
            piece = data[lo : lo + most]
            if size + len(piece) > most and held:
                yield _group(held)
                held, size = [], 0
            held.append((i, lo, piece))
            size += len(piece)
    if held:
        yield _group(held)


def _group(held):
    ends = np.cumsum([len(p) for _, _, p in held])
    return np.concatenate([p for _, _, p in held]), np.concatenate([[0], ends[:-1]]), ends, np.array([i for i, _, _ in held]), np.array([lo for _, lo, _ in held])


def _asked(spans, which, offset, starts, ends, width: int, n: int) -> np.ndarray:
    """Which of n places begin a window that was asked for; spans: the packed stretches of each text."""
    mark = np.zeros(n + 1, np.int32)
    for j, (i, lo) in enumerate(zip(which, offset)):
        pos, size = spans[i] >> 32, spans[i] & 0xFFFFFFFF
        first = np.maximum(pos, lo)
        last = np.minimum(pos + size, lo + ends[j] - starts[j]) - width + 1
        some = last > first
        if some.any():
            np.add.at(mark, first[some] - lo + starts[j], 1)
            np.add.at(mark, last[some] - lo + starts[j], -1)
    return np.cumsum(mark[:n]) > 0


def _scan(width: int, gram: int, buckets: int):
    """Runs of a task's texts (with a fourth column: only of the windows asked for), settled in a family, dealt to buckets."""

    def run(batches):
        family, held, size = SuffixFamily(), [], 0
        for batch in batches:
            k = batch.column(0).to_numpy(zero_copy_only=False)
            t = batch.column(1).to_numpy(zero_copy_only=False)
            spans = [x.values.to_numpy(zero_copy_only=False) for x in batch.column(3)] if batch.num_columns > 3 else None
            for data, starts, ends, which, offset in _pieces(batch.column(2), width):
                if len(data) < width:
                    continue
                n = len(data) - width + 1
                windows = np.flatnonzero(_valid(n, starts, ends, width) if spans is None else _asked(spans, which, offset, starts, ends, width, n))
                if not len(windows):
                    continue
                piece, pos, covers, anchor, kind = runs_of(data, starts, windows, width, gram)
                runs = np.zeros(len(piece), _RUN)
                runs["h"], runs["c"], runs["k"], runs["t"], runs["pos"], runs["len"] = anchor, kind, k[which[piece]], t[which[piece]], pos + offset[piece], covers
                held.append(runs)
                size += len(runs)
                if size > _BATCH:
                    family.add(np.concatenate(held))
                    held, size = [], 0
        if held:
            family.add(np.concatenate(held))
        left = family.merged()
        gone = _joined(family.take_repeated())
        if len(gone):
            yield from _rows(_by_document(gone, buckets), "gone", gone)
        if len(left):
            same = left["h"][1:] == left["h"][:-1]
            several = np.concatenate([same, [False]]) | np.concatenate([[False], same])
            if gram == width:
                several[:] = False
            alone, edges = left[~several], left[several]
            if len(alone):
                yield from _rows(_by_fingerprint(alone, buckets), "runs", alone)
            if len(edges):
                notes = edges[np.concatenate([[True], edges["h"][1:] != edges["h"][:-1]])]
                yield from _rows(_by_fingerprint(notes, buckets), "many", notes)
                yield from _rows(_by_document(edges, buckets), "edges", edges)

    return run


def _spans(runs: np.ndarray, edge: bool):
    for lo in range(0, len(runs), 100_000):
        part = runs[lo : lo + 100_000]
        both = (part["pos"].astype(np.int64) << 32) | part["len"]
        yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(part["k"])), pa.array(np.ascontiguousarray(part["t"])), pa.array(np.full(len(part), edge)), pa.array(both)], names=["k", "t", "edge", "span"])


def _meet(last: bool):
    """Buckets' families: what is repeated and, but for the last grams, which runs are still open."""

    def run(batches):
        family, notes, held, size = SuffixFamily(), [], [], 0
        for batch in batches:
            for kind, data in zip(batch.column(1).to_pylist(), batch.column(2)):
                runs = _unpack(data.as_buffer())
                if kind == _KINDS["runs"]:
                    held.append(runs)
                    size += len(runs)
                    if size > _BATCH:
                        family.add(np.concatenate(held))
                        held, size = [], 0
                elif kind == _KINDS["many"]:
                    notes.append(runs["h"])
                else:
                    yield from _spans(runs, kind == _KINDS["edges"])
        if held:
            family.add(np.concatenate(held))
        left = family.merged()
        yield from _spans(_joined(family.take_repeated()), False)
        if len(left) and not last:
            same = left["h"][1:] == left["h"][:-1]
            several = np.concatenate([same, [False]]) | np.concatenate([[False], same])
            if notes:
                several |= np.isin(left["h"], np.concatenate(notes))
            yield from _spans(left[several], True)

    return run


def cut_spans(size: int, spans: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal (starts, ends) of the union of packed spans."""
    if not len(spans):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    spans = np.sort(spans)
    lo, hi = spans >> 32, np.minimum((spans >> 32) + (spans & 0xFFFFFFFF), size)
    reach = np.maximum.accumulate(hi)
    new = np.flatnonzero(np.concatenate([[True], lo[1:] > reach[:-1]]))
    return lo[new], np.concatenate([reach[new[1:] - 1], reach[-1:]])


def _cleaner(emit_text: bool):
    def run(batches):
        for batch in batches:
            n, gone, parts, kept = [], [], [], []
            for text, spans in zip(batch.column(2), batch.column(3)):
                data = text.as_buffer()
                data = data.to_pybytes() if data is not None else b""
                lo, hi = cut_spans(len(data), spans.values.to_numpy(zero_copy_only=False) if spans.is_valid else np.zeros(0, np.int64))
                n.append(len(data))
                gone.append(int((hi - lo).sum()))
                parts.append(len(lo))
                rest = b"".join(data[a:b] for a, b in zip([0, *hi.tolist()], [*lo.tolist(), len(data)])) if len(lo) else data
                kept.append(rest.decode("utf-8", "ignore") if emit_text else hashlib.sha256(rest).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(parts, pa.int64()), pa.array(kept, pa.string())], names=["k", "t", "n_bytes", "n_removed", "n_spans", "kept"])

    return run


def bucket_count(rows: DataFrame, column: str) -> int:
    """Buckets that keep each one's family within a task's memory, and no fewer than the shuffle partitions."""
    size = rows.agg(F.sum(F.octet_length(column))).first()[0] or 0
    return max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-size // BUCKET))


def remove_repeats(docs: DataFrame, width: int = 100, emit_text: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_bytes, n_removed, n_spans, kept`` for every row of docs (with emit_text also ``t``, which tells repeated ids apart).

    ``kept`` is the lowercase hex SHA-256 of the remaining bytes or, with emit_text, the
    remaining text (characters that lost some of their bytes are left out).
    """
    if width < 8:
        raise ValueError("width must be at least 8")
    text = F.coalesce(docs[text_col].cast("string"), F.lit(""))
    rows = docs.select(F.coalesce(docs[id_col].cast("long"), F.lit(_FIRST)).alias("k"), text.alias("text"))
    buckets = bucket_count(rows, "text")
    twice = checkpoint(rows.groupBy("k").agg(F.count("*").alias("n")).where("n > 1").select("k"))
    repeat = not twice.isEmpty()
    if repeat:  # ids that repeat: tell their texts apart
        mark = twice.withColumn("again", F.lit(True))
        rows = rows.join(mark, "k", "left").select("k", "text", F.when(F.col("again"), F.xxhash64("text")).otherwise(F.lit(0)).alias("t"))
    else:
        rows = rows.withColumn("t", F.lit(0).cast("long"))
    rows = rows.select("k", "t", "text")
    shape = "bucket int, kind int, data binary"
    spans = "k long, t long, edge boolean, span long"
    grams, gone, source = [*[g for g in GRAMS if g < width], width], None, rows
    for gram in grams:
        met = source.mapInArrow(released(_scan(width, gram, buckets)), shape).repartitionById(buckets, F.col("bucket")).mapInArrow(released(_meet(gram == width)), spans)
        found = met.where("not edge") if gram < width else met
        gone = found if gone is None else gone.union(found)
        if gram < width:
            asked = met.where("edge").groupBy("k", "t").agg(F.collect_list("span").alias("spans"))
            # every join shuffles the same columns of the texts by the same keys: one exchange serves all
            source = rows.join(asked, ["k", "t"]).select("k", "t", "text", "spans")
    gone = gone.groupBy("k", "t").agg(F.collect_list("span").alias("spans"))
    out = rows.join(gone, ["k", "t"], "left").select("k", "t", "text", "spans").mapInArrow(released(_cleaner(emit_text)), "k long, t long, n_bytes long, n_removed long, n_spans long, kept string")
    out = out.select(F.nullif("k", F.lit(_FIRST)).alias("doc_id"), "t", "n_bytes", "n_removed", "n_spans", "kept")
    return out if emit_text else out.drop("t")


def without_repeats(docs: DataFrame, width: int = 100) -> DataFrame:
    """The rows of docs with the repeated passages taken out of ``text`` (and ``n_chars``, where docs has it, brought up to date)."""
    cleaned = remove_repeats(docs, width, emit_text=True).where("n_removed > 0").select(F.coalesce("doc_id", F.lit(_FIRST)).alias("k"), "t", F.col("kept").alias("new")).dropDuplicates(["k", "t"])
    id_, text = F.coalesce(F.col("row.doc_id").cast("long"), F.lit(_FIRST)), F.coalesce(F.col("row.text").cast("string"), F.lit(""))
    rows = boxed(docs).select("row", id_.alias("key"), F.xxhash64(text).alias("hash"))
    both = rows.join(cleaned, (F.col("key") == F.col("k")) & ((F.col("t") == 0) | (F.col("t") == F.col("hash"))), "left")
    changed = {"text": F.coalesce("new", F.col("row.text"))}
    if "n_chars" in docs.columns:
        changed["n_chars"] = F.when(F.col("new").isNull(), F.col("row.n_chars")).otherwise(F.length("new")).cast(docs.schema["n_chars"].dataType)
    return both.select(*[changed.get(c, F.col(f"row.{quoted(c)}")).alias(c) for c in docs.columns])
