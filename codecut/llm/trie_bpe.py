"""BPE by a prefix-sharing traversal of a trie of distinct words.

In a rank-ordered BPE, a sequence of tokens is the encoding of its text exactly if
every token encodes to itself and every two neighbours do as a pair. So the encoding of a prefix is
the encoding of a shorter prefix and one more token, and the last token is all that has to be known of
each prefix. The distinct words of a batch make a trie; a depth-first walk
hands every node the last tokens of its ancestors, finds its own, and so encodes each shared
prefix once. Words' encodings are read back along the last tokens.

The final symbol of a word carries the end-of-word suffix, so it is a symbol of its own.
Normalization and splitting into words are the tokenizer's own, applied once to each
distinct piece of text; pieces end at ASCII white space or where a run of plain letters
ends, which no word crosses. A piece of plain letters is one word, in lower case.

Edge cases: null, empty and white texts encode to no ids; special tokens' strings in a text
become those tokens; symbols without an id are left out, as the library does; repeated rows are each encoded;
caches are bounded and shared by the tasks of a worker.
"""

from __future__ import annotations

import hashlib
import json
import re

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import id_and_text, no_collector, released

_LETTERS = "A-Za-zÀ-ÖØ-öø-ÿ"
#: a run of plain letters whose end is plain; else all up to white space
_PIECE = re.compile(rf"[{_LETTERS}]+(?=[\x00-\x26\x28-@\[-`{{-\x7f]|\Z)|[^ \t\n\r\x0b\x0c]+")
_PLAIN = re.compile(rf"[{_LETTERS}]+")
_MOST = 200_000


class TrieBPE:
    """Encoder and decoder of a tokenizers file with a rank-ordered BPE model."""

    _open: dict[str, "TrieBPE"] = {}

    @classmethod
    def of(cls, path: str) -> "TrieBPE":
        if path not in cls._open:
            cls._open[path] = cls(path)
        return cls._open[path]

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.normalize = library.normalizer.normalize_str if library.normalizer else str
        self.split = library.pre_tokenizer.pre_tokenize_str
        self.suffix = model.get("end_of_word_suffix") or ""
        self.ids: dict[str, int] = model["vocab"]
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.rank = {p: i for i, p in enumerate(pairs)}
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.special_cut = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.strings = {i: s for s, i in self.ids.items()} | {i: s for s, i in self.special.items()}
        self.digits = {i: str(i) for i in self.strings}
        # the longest token that ends in given three symbols, within a word and at its end
        self.reach: tuple[dict[str, int], dict[str, int]] = ({}, {})
        for token in self.ids:
            ends = bool(self.suffix) and token.endswith(self.suffix)
            body = token[: -len(self.suffix)] if ends else token
            for of in (self.reach if not self.suffix else (self.reach[ends],)):
                if len(body) > 2:
                    of[body[-3:]] = max(of.get(body[-3:], 0), len(body))
        self.fits: dict[str | None, dict[str, bool]] = {None: {}}
        self.n_fits = 0
        self.heads: dict[str, str] = {}
        self.words: dict[str, tuple[int, ...]] = {}
        self.pieces: dict[str, tuple[int, str, str] | None] = {}
        # whether plain letters may skip the tokenizer's own splitting: it has to agree on every one of them
        letters = [c for c in map(chr, range(256)) if _PLAIN.fullmatch(c)]
        self.plain = {ord(c): self.split(self.normalize(c))[0][0] for c in letters if len(self.split(self.normalize(c))) == 1}
        self.fast = len(self.plain) == len(letters) and [w for w, _ in self.split(self.normalize("".join(letters)))] == ["".join(letters).translate(self.plain)]

    def symbols(self, token: str) -> list[str]:
        """The characters of a token or word form; the suffix belongs to the last one."""
        if self.suffix and token.endswith(self.suffix) and len(token) > len(self.suffix):
            body = token[: -len(self.suffix)]
            return [*body[:-1], body[-1] + self.suffix]
        return list(token)

    def merged(self, symbols: list[str]) -> list[str]:
        """The plain BPE of a short sequence of symbols, by ranks."""
        parts = list(symbols)
        while len(parts) > 1:
            best = min(range(len(parts) - 1), key=lambda i: self.rank.get((parts[i], parts[i + 1]), 1 << 60))
            pair = (parts[best], parts[best + 1])
            if pair not in self.rank:
                break
            out, i = [], 0
            while i < len(parts):
                if i + 1 < len(parts) and (parts[i], parts[i + 1]) == pair:
                    out.append(parts[i] + parts[i + 1])
                    i += 2
                else:
                    out.append(parts[i])
                    i += 1
            parts = out
        return parts

    def _fits(self, left: str | None, right: str) -> bool:
        """Whether right encodes to itself and, behind left, the two stay as they are."""
        of = self.fits.setdefault(left, {})
        known = of.get(right)
        if known is None:
            if left is None:
                known = self.merged(self.symbols(right)) == [right]
            else:
                known = self._fits(None, right) and self.merged(self.symbols(left) + self.symbols(right)) == [left, right]
            of[right] = known
            self.n_fits += 1
        return known

    def encode_words(self, words: list[str]) -> None:
        """Learn the encodings of new distinct words by one walk over their trie, of which the current path is held."""
        if self.n_fits > 8 * _MOST:
            self.fits, self.n_fits = {None: {}}, 0
        heads = self.heads  # last tokens of short prefixes, kept from walk to walk
        if len(heads) > _MOST:
            heads.clear()
        ids, suffix, fits = self.ids, self.suffix, self.fits
        inner, final = self.reach[0].get, self.reach[1].get
        # last[d] is the last token of the path's first d symbols, after[d] what is known to fit behind it
        last: list[str | None] = [None]
        after: list[dict[str, bool]] = [fits[None]]
        path = ""
        for w in sorted(words):  # the order in which a depth-first walk meets the words of the trie
            end = len(w) - 1  # the final symbol, with its suffix, is a leaf below the path
            shared, most = 0, min(len(last) - 1, end)
            while shared < most and path[shared] == w[shared]:
                shared += 1
            del last[shared + 1 :], after[shared + 1 :]
            path = w
            for depth in range(shared + 1, end + 1):
                prefix = w[:depth]
                token = heads.get(prefix) if depth < 6 else None
                if token is None:
                    for start in range(max(0, depth - inner(prefix[-3:], 2)), depth):
                        token = prefix[start:]
                        if token in ids:
                            known = after[start].get(token)
                            if known or known is None and self._fits(last[start], token):
                                break
                    else:
                        token = prefix[-1:]  # a symbol that the vocabulary lacks
                    if depth < 6:
                        heads[prefix] = token
                last.append(token)
                after.append(fits[token] if token in fits else fits.setdefault(token, {}))
            at = end + 1
            for start in range(max(0, at - final(w[-3:], 2)), at):
                token = w[start:] + suffix
                if token in ids:
                    known = after[start].get(token)
                    if known or known is None and self._fits(last[start], token):
                        break
            else:
                token, start = w[-1:] + suffix, end
            found, at = [ids.get(token)], start
            while at > 0:
                token = last[at]
                found.append(ids.get(token))
                at -= len(token)
            found.reverse()
            self.words[w] = tuple(found) if None not in found else tuple(i for i in found if i is not None)

    def _learn(self, new: set[str]) -> None:
        if len(self.words) > _MOST:
            self.words.clear()
        cut: dict[str, list] = {}
        distinct: set[str] = set()
        plain: dict[str, str] = {}
        if self.fast:
            plain = {p: p.translate(self.plain) for p in filter(_PLAIN.fullmatch, new)}
            distinct.update(plain.values())
        for p in new.difference(plain):
            parts = []
            for piece in self.special_cut.split(p) if self.special_cut else [p]:
                if piece in self.special:
                    parts.append(self.special[piece])
                elif piece:
                    found = [w for w, _ in self.split(self.normalize(piece))]
                    parts += found
                    distinct.update(found)
            cut[p] = parts
        self.encode_words(list(distinct.difference(self.words)))
        made: dict[str, tuple[int, str, str] | None] = {}
        for p, w in plain.items():
            entry = made.get(w)
            if entry is None:
                entry = made[w] = self._entry(self.words[w])
            self.pieces[p] = entry
        for p, parts in cut.items():
            self.pieces[p] = self._entry([i for x in parts for i in ((x,) if isinstance(x, int) else self.words[x])])

    def _entry(self, ids) -> tuple[int, str, str] | None:
        return (len(ids), " ".join([self.digits[i] for i in ids]), " ".join([self.strings[i] for i in ids])) if ids else None

    def encode(self, texts: list[str]) -> list[list[tuple[int, str, str]]]:
        """Per text the (count, ids in decimal, decoded) of its pieces."""
        with no_collector():
            return self._encode(texts)

    def _encode(self, texts: list[str]) -> list[list[tuple[int, str, str]]]:
        cut = [_PIECE.findall(t) for t in texts]
        new = set().union(*cut).difference(self.pieces)
        if len(self.pieces) + len(new) > _MOST:
            self.pieces.clear()
            new = set().union(*cut)
        if new:
            self._learn(new)
        known = self.pieces.__getitem__
        return [list(filter(None, map(known, c))) for c in cut]

    def forget(self) -> None:
        """Drop what belongs to texts; which tokens fit together stays known. Idle workers keep their memory otherwise."""
        self.pieces.clear()
        self.words.clear()
        self.heads.clear()

    def decode(self, ids: list[int]) -> str:
        """As the library decodes where the file has no decoder: the tokens, a space between them."""
        return " ".join(self.strings[i] for i in ids)


def _coder(path: str):
    def code(batches):
        bpe = TrieBPE.of(path)
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                n, ids, texts = [], [], []
                for found in bpe.encode(part.column(1).to_pylist()):
                    n.append(sum(x[0] for x in found))
                    ids.append(hashlib.sha256(" ".join([x[1] for x in found]).encode()).hexdigest())
                    texts.append(hashlib.sha256(" ".join([x[2] for x in found]).encode()).hexdigest())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n, pa.int64()), pa.array(ids), pa.array(texts)], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
        bpe.forget()

    return code


def _id_coder(path: str):
    def code(batches):
        bpe = TrieBPE.of(path)
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                found = bpe.encode(part.column(1).to_pylist())
                ids = [[int(i) for x in f for i in x[1].split(" ")] for f in found]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.list_(pa.int32())), pa.array([" ".join(x[2] for x in f) for f in found])], names=["doc_id", "ids", "decoded"])
        bpe.forget()

    return code


def encoded_digests(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256``."""
    return id_and_text(docs, id_col, text_col).mapInArrow(released(_coder(path)), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode_documents(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, ids, decoded``."""
    return id_and_text(docs, id_col, text_col).mapInArrow(released(_id_coder(path)), "doc_id long, ids array<int>, decoded string")
