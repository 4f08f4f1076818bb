"""Exact encoding with a byte-level BPE tokenizer of the tokenizers library, which sees each stretch of text once.

The library splits a text into pieces that never cross certain places, so equal
stretches between such places encode alike. Such places are found for many texts at once in
numpy; stretches of up to 15 bytes are looked up by their bytes (two machine words, compared in full)
in a table of two generations of bounded size, and only those that are not there go to the library.

The cuts hold for the splitter of the byte-level pre-tokenizer (letters, numbers and other
signs, each with at most one space before them, contractions, white space). A file with any
other splitter, with a normalizer or with dropout is refused.

Edge cases: null is the empty text; strings of special tokens in a text become those
tokens, as the library does it; texts of any length are cut into windows for memory only.
"""

from __future__ import annotations

import json
import os
from itertools import chain

import numpy as np
import pyarrow as pa

from .common import no_collector

WINDOW = 1 << 20  # bytes that are cut at once
_MOST = 700_000  # stretches of a generation
_LONG = 50_000  # longer stretches that are remembered

# classes of bytes: 1 letter, 2 digit, 4 white space, 8 other printable, 16 apostrophe, 0 anything else
_CLASS = np.zeros(256, np.uint8)
_CLASS[0x21:0x7F] = 8
_CLASS[0x27] = 16
_CLASS[0x30:0x3A] = 2
_CLASS[0x41:0x5B] = _CLASS[0x61:0x7B] = 1
_CLASS[[0x09, 0x0A, 0x0B, 0x0C, 0x0D, 0x20]] = 4
_LEAD = 0xC3  # with the bytes marked here it makes the letters from A with grave to y with diaeresis
_TAIL = np.zeros(256, bool)
_TAIL[0x80:0xC0] = True
_TAIL[[0x97, 0xB7]] = False
_HEAD_OF = np.array([(1 << 8 * i) - 1 for i in range(8)] + [(1 << 64) - 1], np.uint64)


def classes(data: np.ndarray) -> np.ndarray:
    out = _CLASS[data]
    lead = np.flatnonzero(data[:-1] == _LEAD)
    lead = lead[_TAIL[data[lead + 1]]]
    out[lead] = 1
    out[lead + 1] = 1
    return out


def cuts(kind: np.ndarray) -> np.ndarray:
    """Whether no piece of the splitter crosses from the byte before to this byte, as far as the two show it."""
    old, new = kind[:-1], kind[1:]
    out = np.zeros(len(kind), bool)
    # white space after none; a run of letters, of digits or (but for an apostrophe) of signs ends where another class begins
    out[1:] = (new != old) & (old != 0) & (old != 4) & (new != 0) & ((old != 16) | (new == 4)) & ~((old == 8) & (new == 16))
    return out


class _Table:
    """Ids by the bytes of a stretch: open addressing over two words, the second of which holds the length."""

    def __init__(self, most: int, dtype):
        self.most, self.n, self.used = most, 1, 0
        self.shift = np.uint64(64 - max(4, (2 * most).bit_length()))
        self.slots = np.zeros(1 << (64 - int(self.shift)), np.int32)
        self.a, self.b = np.zeros(most + 1, np.uint64), np.zeros(most + 1, np.uint64)
        self.at, self.size = np.zeros(most + 1, np.int64), np.zeros(most + 1, np.int32)
        self.pool = np.zeros(4 * most, dtype)

    def _slot(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        x = a * np.uint64(0x9E3779B97F4A7C15) ^ b * np.uint64(0xD6E8FEB86659FD93)
        x ^= x >> np.uint64(32)
        return ((x * np.uint64(0xA0761D6478BD642F)) >> self.shift).astype(np.int64)

    def find(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The entry of each key, 0 where there is none."""
        slot = self._slot(a, b)
        out = self.slots[slot]
        open_ = np.flatnonzero((out > 0) & ((self.a[out] != a) | (self.b[out] != b)))
        while len(open_):
            slot[open_] = (slot[open_] + 1) & (len(self.slots) - 1)
            e = self.slots[slot[open_]]
            out[open_] = e
            open_ = open_[(e > 0) & ((self.a[e] != a[open_]) | (self.b[e] != b[open_]))]
        return out

    def room(self, n: int) -> bool:
        return self.n + n <= self.most

    def add(self, a: np.ndarray, b: np.ndarray, sizes: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """Entries of new, distinct keys; ids holds theirs one after another."""
        n, total = len(a), len(ids)
        new = np.arange(self.n, self.n + n)
        while self.used + total > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros_like(self.pool)])
        self.pool[self.used : self.used + total] = ids
        self.a[new], self.b[new], self.size[new] = a, b, sizes
        self.at[new] = self.used + np.cumsum(sizes) - sizes
        self.n, self.used = self.n + n, self.used + total
        slot, left = self._slot(a, b), np.arange(n)
        while len(left):
            s = slot[left]
            free = self.slots[s] == 0
            self.slots[s[free]] = new[left[free]]
            lost = self.slots[s] != new[left]
            left = left[lost]
            slot[left] = (slot[left] + 1) & (len(self.slots) - 1)
        return new

    def ids_of(self, entries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        sizes = self.size[entries].astype(np.int64)
        return sizes, gathered(self.pool, self.at[entries], sizes)


def gathered(pool: np.ndarray, at: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """pool[at[0] : at[0] + sizes[0]], pool[at[1] : ...], ... as one."""
    ends = np.cumsum(sizes)
    return pool[np.repeat(at - ends + sizes, sizes) + np.arange(int(ends[-1]) if len(ends) else 0)]


class CachedEncoder:
    """ids of whole texts; ``path`` names a tokenizers file of a byte-level BPE without normalizer."""

    _open: dict[str, "CachedEncoder"] = {}

    @classmethod
    def of(cls, path: str) -> "CachedEncoder":
        """The encoder of this process, so that tasks of one worker share its table."""
        if path not in cls._open:
            cls._open[path] = cls(path)
        return cls._open[path]

    def __init__(self, path: str, most: int = _MOST):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks are what runs side by side
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        told = json.loads(self.library.to_str())
        split = told["pre_tokenizer"] or {}
        if told["normalizer"] or told["model"].get("dropout") or split.get("type") != "ByteLevel" or split.get("add_prefix_space") or not split.get("use_regex", True):
            raise ValueError("not a plain byte-level BPE")
        self.special = [t["content"].encode() for t in told["added_tokens"]]
        self.dtype = np.dtype("<u2" if self.library.get_vocab_size() <= 1 << 16 else "<u4")
        # how the byte-level alphabet writes bytes: visible signs of Latin-1 as they are, the others from 256 on
        seen = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
        self.signs = dict(zip(sorted({*range(256)} - {*seen}), range(256, 512)))
        self.most = most
        self.young, self.old = _Table(most, self.dtype), None
        self.long: dict[bytes, np.ndarray] = {}

    def _ask(self, words: list[bytes], plain: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(sizes, ids) of distinct words; a plain one is a single piece, which the library's model takes as it is."""
        merge, signs = self.library.model.tokenize, self.signs
        out = [[t.id for t in merge(w.decode("latin-1").translate(signs))] if p else None for w, p in zip(words, plain.tolist())]
        rest = [i for i, x in enumerate(out) if x is None]
        for i, e in zip(rest, self.library.encode_batch_fast([words[i].decode() for i in rest], add_special_tokens=False)):
            out[i] = e.ids
        return np.array([len(x) for x in out], np.int64), np.array(list(chain.from_iterable(out)), self.dtype)

    def _entries(self, a, b, word, plain) -> np.ndarray:
        """Entries in the young table; word(i) gives the bytes of key i."""
        found = self.young.find(a, b)
        miss = np.flatnonzero(found == 0)
        if not len(miss):
            return found
        order = miss[np.lexsort((b[miss], a[miss]))]
        first = np.concatenate([[True], (a[order[1:]] != a[order[:-1]]) | (b[order[1:]] != b[order[:-1]])])
        new = order[first]
        if not self.young.room(len(new)):
            self.old, self.young = self.young, _Table(max(self.most, 2 * len(a)), self.dtype)
            return self._entries(a, b, word, plain)
        got = np.zeros(len(new), np.int32)
        if self.old is not None:
            theirs = self.old.find(a[new], b[new])
            known = np.flatnonzero(theirs)
            got[known] = self.young.add(a[new[known]], b[new[known]], *self.old.ids_of(theirs[known]))
        unknown = np.flatnonzero(got == 0)
        if len(unknown):
            keys = new[unknown]
            got[unknown] = self.young.add(a[keys], b[keys], *self._ask([word(i) for i in keys.tolist()], plain[keys]))
        found[order] = got[np.cumsum(first) - 1]
        return found

    def _window(self, data: np.ndarray, kind: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(sizes, ids) of the stretches of data, which has 16 more bytes."""
        raw, size = data.tobytes(), ends - starts
        odd = np.concatenate([[0], np.cumsum((kind == 0) | (kind == 4) | (kind == 16), dtype=np.int32)])
        plain = (odd[ends] - odd[starts] == (data[starts] == 0x20)) & (size > (data[starts] == 0x20))
        short = np.flatnonzero(size <= 15)
        s, n = starts[short], size[short]
        words = np.ndarray((len(data) - 7,), "<u8", data, strides=(1,))
        a = words[s] & _HEAD_OF[np.minimum(n, 8)]
        b = (words[s + 8] & _HEAD_OF[np.maximum(n - 8, 0)]) | (n.astype(np.uint64) << np.uint64(56))
        entries = self._entries(a, b, lambda i: raw[s[i] : s[i] + n[i]], plain[short])
        if len(short) == len(starts):
            return self.young.ids_of(entries)
        big = np.flatnonzero(size > 15)
        names = [raw[i:j] for i, j in zip(starts[big].tolist(), ends[big].tolist())]
        if len(self.long) > _LONG:
            self.long = {}
        new = {w: p for w, p in zip(names, plain[big].tolist()) if w not in self.long}
        known = self.long
        if new:
            sizes, ids = self._ask(list(new), np.fromiter(new.values(), bool, len(new)))
            known = known | dict(zip(new, np.split(ids, np.cumsum(sizes)[:-1]))) if len(new) > _LONG else known
            if known is self.long:
                known.update(zip(new, [x.copy() for x in np.split(ids, np.cumsum(sizes)[:-1])]))
        extra = [known[w] for w in names]
        sizes = np.zeros(len(starts), np.int64)
        sizes[short] = self.young.size[entries]
        sizes[big] = [len(x) for x in extra]
        at = np.zeros(len(starts), np.int64)
        at[short] = self.young.at[entries]
        at[big] = self.young.used + np.cumsum(sizes[big]) - sizes[big]
        return sizes, gathered(np.concatenate([self.young.pool[: self.young.used], *extra]), at, sizes)

    def _without_special(self, data: np.ndarray, begins: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids before each text and in all, ids) of texts that begin at the given places of data, without special strings."""
        total, lo, done, parts = len(data), 0, 0, []
        before = np.zeros(len(begins) + 1, np.int64)
        want = WINDOW
        while lo < total:
            hi = min(total, lo + want)
            part = np.concatenate([data[lo:hi], np.zeros(16, np.uint8)])
            kind = classes(part)
            kind[hi - lo :] = 0
            cut = cuts(kind)[: hi - lo]
            first, last = np.searchsorted(begins, [lo, hi])
            cut[begins[first:last] - lo] = True
            cut[0] = True
            starts = np.flatnonzero(cut)
            if hi < total:  # the last stretch may go on
                if len(starts) == 1:
                    want *= 2
                    continue
                hi = lo + int(starts[-1])
                starts, ends = starts[:-1], starts[1:]
            else:
                ends = np.append(starts[1:], hi - lo)
            want = WINDOW
            sizes, ids = self._window(part, kind, starts, ends)
            sums = np.concatenate([[0], np.cumsum(sizes)])
            first, last = np.searchsorted(begins, [lo, hi])
            before[first:last] = done + sums[np.searchsorted(starts, begins[first:last] - lo)]
            done += int(sums[-1])
            parts.append(ids)
            lo = hi
        before[np.searchsorted(begins, total) :] = done
        return before, np.concatenate(parts) if parts else np.zeros(0, self.dtype)

    def encode_bytes(self, data: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(sizes, ids) of the texts data[bounds[i] : bounds[i + 1]], UTF-8."""
        with no_collector():
            bounds = np.asarray(bounds, np.int64)
            data, bounds = data[bounds[0] : bounds[-1]], bounds - bounds[0]
            raw = memoryview(np.ascontiguousarray(data))
            odd = [i for i in self._may_hold(raw, bounds)]
            sizes, parts, at = [], [], 0
            for i in [*odd, len(bounds) - 1]:
                before, ids = self._without_special(data[bounds[at] : bounds[i]], bounds[at:i] - bounds[at])
                sizes.append(np.diff(before) if i > at else np.zeros(0, np.int64))
                parts.append(ids)
                if i < len(bounds) - 1:
                    ids = np.array(self.library.encode(bytes(raw[bounds[i] : bounds[i + 1]]).decode(), add_special_tokens=False).ids, self.dtype)
                    sizes.append(np.array([len(ids)]))
                    parts.append(ids)
                at = i + 1
            return np.concatenate(sizes), np.concatenate(parts)

    def _may_hold(self, raw: memoryview, bounds: np.ndarray) -> list[int]:
        """Texts with a special string."""
        found = set()
        whole = bytes(raw) if self.special else b""
        for s in self.special:
            at = whole.find(s)
            while at >= 0:
                i = int(np.searchsorted(bounds, at, "right")) - 1
                if at + len(s) <= bounds[i + 1]:
                    found.add(i)
                at = whole.find(s, max(at + 1, int(bounds[i + 1]) - len(s) + 1))
        return sorted(found)

    def encode_column(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(sizes, ids) of a column of strings without nulls."""
        wide = pa.types.is_large_string(column.type)
        bounds = np.frombuffer(column.buffers()[1], np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
        data = column.buffers()[2]
        return self.encode_bytes(np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8), bounds)

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        sizes, ids = self.encode_column(pa.array(texts, pa.large_string()))
        return np.split(ids, np.cumsum(sizes)[:-1]) if len(texts) else []
