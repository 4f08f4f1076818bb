"""Chat formatting by columnar byte assembly.

A turn is written as ``<|turn:ROLE|>TEXT<|end|>`` and a line feed. Roles and texts are escaped
reversibly: a backslash is doubled, and one is put inside every ``<|`` and ``|>``, so a mark can
only come from the template. For each Arrow batch, numpy computes the lengths of all
segments, their offsets by cumulative sums, and scatter indices by which contents and
headers are copied into one preallocated buffer; no text passes through a Python string.

The loss mask is a list of byte spans: the escaped texts of assistant turns.

Scale: turns of a conversation are brought together and sorted by turn, then streamed; a
conversation that spans batches becomes several segments in order, so that even one conversation
that holds a third of all turns needs the memory of a batch only.

Edge cases: null text and null role are empty; ties of (conversation, turn) are ordered by role and
text; repeated rows are turns of their own; a null conversation id is one conversation; an
empty table gives no row.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import materialize

OPEN, MIDDLE, CLOSE = b"<|turn:", b"|>", b"<|end|>\n"
_TURN = re.compile(rb"<\|turn:(.*?)\|>(.*?)<\|end\|>\n", re.S)
_ESCAPED = re.compile(rb"\\(.)", re.S)
SCHEMA = "conv_id long, segment int, n_turns int, data binary, loss array<long>"


def _escape(column: pa.Array) -> pa.Array:
    column = pc.replace_substring(column.cast(pa.large_string()), "\\", "\\\\")
    column = pc.replace_substring(column, "<|", "<\\|")
    return pc.replace_substring(column, "|>", "|\\>")


def unescape(data: bytes) -> bytes:
    return _ESCAPED.sub(rb"\1", data)


def _raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, bytes) of a string column without nulls."""
    if column.offset:
        column = pa.concat_arrays([column])
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64, len(column) + 1) if offsets else np.zeros(len(column) + 1, np.int64)
    return at, np.frombuffer(data, np.uint8) if data else np.zeros(0, np.uint8)


def _copy(out: np.ndarray, to: np.ndarray, at: np.ndarray, data: np.ndarray) -> None:
    """Copy the pieces data[at[i]:at[i + 1]] to out[to[i]:]."""
    sizes = np.diff(at)
    out[np.repeat(to - at[:-1], sizes) + np.arange(at[0], at[-1])] = data[at[0] : at[-1]]


def assemble(roles: pa.Array, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(buffer, turn offsets, text starts, text ends) for escaped columns without nulls."""
    role_at, role_data = _raw(roles)
    text_at, text_data = _raw(texts)
    role_size, text_size = np.diff(role_at), np.diff(text_at)
    fixed = len(OPEN) + len(MIDDLE) + len(CLOSE)
    turn = np.concatenate([[0], np.cumsum(role_size + text_size + fixed)])
    out = np.empty(int(turn[-1]), np.uint8)
    role_to = turn[:-1] + len(OPEN)
    middle = role_to + role_size
    text_to = middle + len(MIDDLE)
    text_end = text_to + text_size
    for mark, to in ((OPEN, turn[:-1]), (MIDDLE, middle), (CLOSE, text_end)):
        out[to[:, None] + np.arange(len(mark))] = np.frombuffer(mark, np.uint8)
    _copy(out, role_to, role_at, role_data)
    _copy(out, text_to, text_at, text_data)
    return out, turn, text_to, text_end


def _format(trained: str):
    def run(batches):
        previous, segment = (None, False), 0
        for batch in batches:
            if not batch.num_rows:
                continue
            ids = batch.column(0)
            key = ids.fill_null(0).to_numpy(zero_copy_only=False)
            null = ids.is_null().to_numpy(zero_copy_only=False)
            out, turn, text_to, text_end = assemble(_escape(batch.column(1)), _escape(batch.column(2)))
            learn = pc.equal(batch.column(1), trained).to_numpy(zero_copy_only=False)
            first = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (null[1:] != null[:-1])]))
            last = np.concatenate([first[1:], [len(key)]])
            at = turn[np.concatenate([first, [len(key)]])]
            data = pa.Array.from_buffers(pa.large_binary(), len(first), [None, pa.py_buffer(at.astype(np.int64)), pa.py_buffer(out)])
            base = np.repeat(turn[first], last - first)
            spans = np.stack([text_to - base, text_end - base], 1)[learn].ravel()
            n_spans = np.concatenate([[0], np.cumsum(np.add.reduceat(learn.astype(np.int64), first))]) * 2
            segments = np.zeros(len(first), np.int32)
            if previous == (int(key[0]), bool(null[0])):
                segments[0] = segment + 1
            previous, segment = (int(key[-1]), bool(null[-1])), int(segments[-1])
            loss = pa.ListArray.from_arrays(pa.array(n_spans, pa.int32()), pa.array(spans, pa.int64()))
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(first)), pa.array(segments), pa.array((last - first).astype(np.int32)), data.cast(pa.binary()), loss], names=["conv_id", "segment", "n_turns", "data", "loss"])

    return run


def format_conversations(turns: DataFrame, trained_role: str = "assistant", id_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """Segments of formatted conversations: ``conv_id, segment, n_turns, data, loss`` (byte starts and ends by turns)."""
    text = lambda c: F.coalesce(turns[c].cast("string"), F.lit(""))
    rows = turns.select(turns[id_col].cast("long").alias("conv_id"), text(role_col).alias("role"), text(text_col).alias("text"), turns[turn_col].alias("turn"))
    rows = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").select("conv_id", "role", "text")
    return rows.mapInArrow(_format(trained_role), SCHEMA)


def parse(data: bytes) -> list[tuple[bytes, bytes]]:
    """(role, text) of the turns of a formatted segment."""
    return [(unescape(r), unescape(t)) for r, t in _TURN.findall(data)]


def _points(data: bytes) -> int:
    return int(np.count_nonzero((np.frombuffer(data, np.uint8) & 0xC0) != 0x80))


def _digest(batches):
    now = None

    def row():
        return (now["id"], now["n"], now["turns"].hexdigest(), now["chars"], now["loss"].hexdigest(), now["all"])

    def table(rows):
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    for batch in batches:
        rows = []
        for conv, data, loss in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist()):
            if now is None or now["id"] != conv:
                if now is not None:
                    rows.append(row())
                now = {"id": conv, "n": 0, "turns": hashlib.sha256(), "chars": 0, "loss": hashlib.sha256(), "all": 0}
            data = data.as_py()
            for role, text in parse(data):
                now["n"] += 1
                now["turns"].update(role + b"\n" + text + b"\n")
            for lo, hi in zip(loss[::2], loss[1::2]):
                text = unescape(data[lo:hi])
                now["chars"] += _points(text)
                now["loss"].update(text)
            now["all"] += _points(data)
        if rows:
            yield table(rows)
    if now is not None:
        yield table([row()])


def conversation_digests(segments: DataFrame) -> DataFrame:
    """Read segments back: ``conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars``."""
    rows = segments.select("conv_id", "data", "loss", "segment").repartition("conv_id").sortWithinPartitions("conv_id", "segment").select("conv_id", "data", "loss")
    return rows.mapInArrow(_digest, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def written_digests(turns: DataFrame) -> DataFrame:
    """Format, write, read the files back, and digest what they say."""
    return conversation_digests(materialize(format_conversations(turns), "chats"))
