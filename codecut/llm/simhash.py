"""Near copies by 64-bit similarity fingerprints.

A text is lower-cased (A to Z), split at ASCII white space and cut into runs of
three words, repeats included; a bit of the fingerprint is set where over half
of the runs' hashes have it. Fingerprints within ``radius`` bits are linked, and
linked documents form a component.

Finding links: 64 bits are cut into blocks. With ``radius`` 3 and six blocks, two
linked fingerprints agree on at least three whole blocks, so every choice of
three blocks is a join key of about 32 bits. Within a key, a search over the
remaining members gives a spanning forest, never all pairs. Keys with more members than
``split_above`` are cut again by the blocks of their remaining bits, so a group
of any size is spread over many keys; nothing is dropped.

Edge cases: null and empty texts have fingerprint 0 and are linked like any other;
fewer than three words form one run; repeated rows and ties share a fingerprint and
a component; null ids get the component of their fingerprint, and never name one
(unless all ids are null: then it is null); an empty table gives an empty result.
"""

from __future__ import annotations

from functools import reduce
from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import connected_components
from ..session import checkpoint
from .common import LOWER, UPPER, boxed, id_and_text, released, unboxed

_FOLD = bytes.maketrans(UPPER.encode(), LOWER.encode())
_BLOCK = 100_000  # hashes that are unpacked into bits at once


def run_hashes(text: bytes, words: int = 3) -> list[int]:
    parts = text.translate(_FOLD).split()
    if len(parts) <= words:
        return [xxhash.xxh64_intdigest(b" ".join(parts), 42)] if parts else []
    joined = b" ".join(parts)
    ends = list(accumulate(len(p) + 1 for p in parts))
    starts = [0, *ends[: len(parts) - words]]
    digest = xxhash.xxh64_intdigest
    return [digest(joined[s : e - 1], 42) for s, e in zip(starts, ends[words - 1 :])]


def fold_bits(hashes: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Fingerprints of consecutive groups of hashes with the given sizes."""
    out = np.zeros(len(sizes), np.uint64)
    full = np.flatnonzero(sizes)
    if not len(full):
        return out
    starts = np.concatenate([[0], np.cumsum(sizes[full])])
    counts = np.zeros((len(full), 64), np.int64)
    big = hashes.astype(">u8").view(np.uint8).reshape(-1, 8)
    for lo in range(0, len(hashes), _BLOCK):
        hi = min(lo + _BLOCK, len(hashes))
        first = np.searchsorted(starts, lo, "right") - 1
        last = np.searchsorted(starts, hi, "left")
        cuts = np.maximum(starts[first:last] - lo, 0)
        counts[first:last] += np.add.reduceat(np.unpackbits(big[lo:hi], axis=1), cuts, axis=0, dtype=np.int64)
    bits = 2 * counts > np.asarray(sizes)[full][:, None]
    out[full] = np.packbits(bits, axis=1).reshape(-1, 8).copy().view(">u8").ravel().astype(np.uint64)
    return out


def _fingerprint_batches(batches):
    for batch in batches:
        for lo in range(0, batch.num_rows, 500):
            part = batch.slice(lo, 500)
            per_doc = [run_hashes(t.encode()) for t in part.column(1).to_pylist()]
            sizes = np.array([len(h) for h in per_doc], np.int64)
            fps = fold_bits(np.array([x for h in per_doc for x in h], np.uint64), sizes)
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(fps.view(np.int64))], names=["doc_id", "text_hash", "fp"])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a document: ``doc_id``, ``text_hash`` (to tell rows of one id apart), ``fp`` (the 64 bits as a long)."""
    rows = id_and_text(docs, id_col, text_col)
    return rows.select("doc_id", "text", F.xxhash64("text").alias("text_hash")).mapInArrow(released(_fingerprint_batches), "doc_id long, text_hash long, fp long")


def block_masks(within: int, blocks: int, keep: int) -> list[int]:
    """Masks of every choice of ``keep`` of ``blocks`` even cuts of the set bits of ``within``."""
    bits = [i for i in range(64) if within >> i & 1]
    cuts = [sum(1 << int(b) for b in part) for part in np.array_split(bits, blocks)]
    return [sum(c) for c in combinations(cuts, keep)]


def _signed(mask: int) -> int:
    mask = int(mask)
    return mask - (1 << 64) if mask >> 63 else mask


def group_forest(fps: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of a spanning forest of the links among fps."""
    left = np.arange(len(fps))
    src, dst = [], []
    while len(left):
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            at = queue.pop()
            near = np.bitwise_count(fps[left] ^ fps[at]) <= radius
            if near.any():
                found = left[near]
                src.append(np.full(len(found), at))
                dst.append(found)
                queue.extend(found)
                left = left[~near]
    if not src:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(src), np.concatenate(dst)


def _linker(radius: int):
    def link(batches):
        held = None
        for batch in _with_end(batches):
            if batch is None:
                part, rest = held, None
            else:
                part = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(4)]
                if held is not None:
                    part = [np.concatenate(x) for x in zip(held, part)]
                differs = np.flatnonzero((part[0] != part[0][-1]) | (part[1] != part[1][-1]))
                cut = differs[-1] + 1 if len(differs) else 0
                part, rest = [x[:cut] for x in part], [x[cut:] for x in part]
            held = rest
            if part is None or not len(part[0]):
                continue
            choice, key, fp, rep = part
            fp = fp.view(np.uint64)
            edge = np.flatnonzero(np.concatenate([[True], (choice[1:] != choice[:-1]) | (key[1:] != key[:-1])]))
            size = np.diff(np.concatenate([edge, [len(fp)]]))
            two = edge[size == 2]
            two = two[np.bitwise_count(fp[two] ^ fp[two + 1]) <= radius]
            src, dst = [rep[two]], [rep[two + 1]]
            for s, n in zip(edge[size > 2], size[size > 2]):
                a, b = group_forest(fp[s : s + n], radius)
                src.append(rep[s + a])
                dst.append(rep[s + b])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(src)), pa.array(np.concatenate(dst))], names=["src", "dst"])

    return link


def _with_end(batches):
    for batch in batches:
        if batch.num_rows:
            yield batch
    yield None


def hamming_links(reps: DataFrame, radius: int = 3, blocks: int = 6, split_above: int = 4096) -> DataFrame:
    """Links that connect all distinct fingerprints within ``radius`` bits.

    reps: ``rep`` (long, distinct), ``fp`` (long, distinct). Output: ``src``, ``dst`` of
    reps; they span the same components as all links do.
    """
    masks = block_masks((1 << 64) - 1, blocks, blocks - radius)
    level = reps.select("rep", "fp", F.lit(0).alias("choice"), F.posexplode(F.array(*[F.lit(_signed(m)) for m in masks])).alias("c", "mask"))
    level = level.select("rep", "fp", F.col("c").cast("long").alias("choice"), "mask", F.col("fp").bitwiseAND(F.col("mask")).alias("key"))
    out = None
    for depth in range(3):
        rows = level
        if depth < 2:
            sizes = level.groupBy("choice", "key").agg(F.count("*").alias("n")).where(F.col("n") > split_above)
            hot = checkpoint(sizes.select("choice", "key"))
            if hot.isEmpty():
                hot = None
            else:
                rows = level.join(hot, ["choice", "key"], "left_anti")
        found = rows.select("choice", "key", "fp", "rep").repartition("choice", "key").sortWithinPartitions("choice", "key", "fp").mapInArrow(released(_linker(radius)), "src long, dst long")
        out = found if out is None else out.union(found)
        if depth == 2 or hot is None:
            break
        level = level.join(hot, ["choice", "key"], "left_semi").select("rep", "fp", "choice", "mask", _finer(masks, blocks, radius, depth))
        level = level.select("rep", "fp", (F.col("choice") * 64 + F.col("c")).alias("choice"), F.col("mask").bitwiseOR(F.col("more")).alias("mask"))
        level = level.select("rep", "fp", "choice", "mask", F.col("fp").bitwiseAND(F.col("mask")).alias("key"))
    return out


def _finer(masks: list[int], blocks: int, radius: int, depth: int):
    """Explode each row into the choices among blocks of the bits that its mask leaves free."""
    if depth == 0:
        nested = [[F.lit(_signed(x)) for x in block_masks(((1 << 64) - 1) & ~m, blocks, blocks - radius)] for m in masks]
        return F.posexplode(F.get(F.array(*[F.array(*row) for row in nested]), F.col("choice").cast("int"))).alias("c", "more")
    free = F.filter(F.array(*[F.lit(_signed(1 << b)) for b in range(64)]), lambda b: F.col("mask").bitwiseAND(b) == 0)
    bound = lambda i: F.floor(F.size(free) * i / blocks).cast("int")
    cuts = [F.aggregate(F.slice(free, bound(i) + 1, bound(i + 1) - bound(i)), F.lit(0).cast("long"), lambda x, y: x.bitwiseOR(y)) for i in range(blocks)]
    unions = [reduce(lambda x, y: x.bitwiseOR(y), c) for c in combinations(cuts, blocks - radius)]
    return F.posexplode(F.array(*unions)).alias("c", "more")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = 3) -> DataFrame:
    """One row a document: ``doc_id, text_hash, fp, part`` (a fingerprint that names the component), ``component_id``, the smallest id reachable by links."""
    each = checkpoint(fingerprints(docs, id_col, text_col))
    reps = checkpoint(each.groupBy("fp").agg(F.min("doc_id").alias("rep")))
    # ids may repeat with other texts, so the nodes are the fingerprints themselves
    parts = connected_components(checkpoint(hamming_links(reps.select(F.col("fp").alias("rep"), "fp"), radius)))
    parts = parts.join(reps.withColumnRenamed("fp", "node"), "node")
    least = parts.groupBy("component").agg(F.min("rep").alias("component_id"))
    linked = parts.join(least, "component").select(F.col("node").alias("fp"), F.col("component").alias("part"), "component_id")
    alone = reps.join(linked, "fp", "left_anti").select("fp", F.col("fp").alias("part"), F.col("rep").alias("component_id"))
    return each.join(linked.union(alone), "fp").select("doc_id", "text_hash", "fp", "part", "component_id")


def one_of_each(docs: DataFrame, found: DataFrame) -> DataFrame:
    """The rows of docs that come first (by id, null last, then by text hash) in their component; of equal rows one.

    found: ``doc_id, text_hash, part`` of every row, by ``near_duplicates`` or ``set_join.similar_documents``.
    """
    last = F.lit((1 << 63) - 1)
    place = [F.coalesce("doc_id", last).alias("k"), F.col("text_hash").alias("h")]
    first = found.groupBy("part").agg(F.min(F.struct(*place)).alias("w")).select("w.k", "w.h")
    again = checkpoint(found.groupBy(*place).agg(F.count("*").alias("n")).where("n > 1").select("k", "h"))
    rows = boxed(docs)
    keyed = rows.select(F.coalesce(F.col("row.doc_id").cast("long"), last).alias("k"), F.xxhash64(F.coalesce(F.col("row.text").cast("string"), F.lit(""))).alias("h"), "row")
    kept = keyed.join(first, ["k", "h"], "left_semi")
    if not again.isEmpty():
        kept = kept.dropDuplicates(["k", "h"])
    return unboxed(kept, docs)


def fingerprint_hex(fp) -> F.Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
