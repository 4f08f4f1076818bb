"""Near copies by the exact Jaccard similarity of word runs.

A text is folded and split as for the fingerprints of ``simhash``; its set is the hashes of its runs
of five words. Texts whose sets have a Jaccard similarity of at least 0.8 are linked, and linked
documents form a component. Nothing is sampled from the answer: it is exact up to collisions of 64-bit hashes.

Finding links: first by the fingerprints of ``simhash`` over the same runs (repeats included), linked within ``radius``
bits by pigeonhole blocks and verified on whole sets. Sets of the wanted similarity often differ in more bits (7 in the
middle, on the tables at hand), so an exact join adds what fingerprints cannot reach: in any one order of all runs, two
such sets share a run among the first n - ceil(similarity n) + 1 of each, and only these are join keys. Any order gives
the same links; runs that are common in a sixteenth of the texts come last, which keeps the groups of a key small.

In each key, members are first compared with one leader, and components that are known are not compared within any
more. After ``turns`` leaders the members of a key meet in tiles, each holding 1,024 parity bits of the whole set: the
bits in which two sets differ are never more than the runs in which they do, so a pair with too many is none. A
pair whose join keys alone show that it cannot be similar goes no further; every other comparison is of the whole sets,
made anew from the texts that need it.

Edge cases: null and empty texts have an empty set and form one component; fewer than five words form
one run; equal sets are one node, so copies are never compared; null ids and repeated rows are kept apart by ``text_hash``.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import connected_components
from ..session import checkpoint
from .common import id_and_text, released
from .simhash import _with_end, fold_bits, hamming_links, run_hashes

_COMMON = 1_000_000  # runs that are ordered by their counts; the others come first, by hash
_BITS = 1024  # parity bits of a set
_TILE = 512  # members of a key that meet as many others in one task
_FEW = 16  # members up to which keys are compared many at once


def named_set(hashes: np.ndarray) -> tuple[int, np.ndarray]:
    """(name of the set, its hashes in ascending order as longs)."""
    runs = np.unique(hashes.view(np.int64))
    return int(np.array(xxhash.xxh64_intdigest(runs.tobytes(), 42), np.uint64).view(np.int64)), runs


def run_set(text: str, words: int) -> tuple[int, np.ndarray]:
    return named_set(np.array(run_hashes(text.encode(), words), np.uint64))


def parity_bits(runs: np.ndarray) -> bytes:
    """A bit for each remainder of the hashes: whether an odd number of them has it."""
    return np.packbits(np.bincount(runs & (_BITS - 1), minlength=_BITS).astype(np.uint8) & 1).tobytes()


def prefix_size(n: int, similarity: float) -> int:
    return n - math.ceil(similarity * n - 1e-9) + 1 if n else 0


def _lists(parts: list[np.ndarray]) -> pa.Array:
    ends = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*parts, np.zeros(0, np.int64)]).astype(np.int64)))


def _whole_sets(words: int):
    def run(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                got = [run_set(t, words) for t in batch.column(0).slice(lo, 500).to_pylist()]
                yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in got], pa.int64()), _lists([x[1] for x in got])], names=["fp", "runs"])

    return run


_EACH = ["doc_id", "text_hash", "fp", "n", "prefix", "sim", "bits"]


def _prefixes(words: int, similarity: float, common):
    def run(batches):
        keys, counts = common.value
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                names, sizes, firsts, bits = [], [], [], []
                hashes = [np.array(run_hashes(t.encode(), words), np.uint64) for t in part.column(1).to_pylist()]
                sims = fold_bits(np.concatenate([*hashes, np.zeros(0, np.uint64)]), np.array([len(h) for h in hashes], np.int64))
                for each in hashes:
                    name, runs = named_set(each)
                    bits.append(parity_bits(runs))
                    take = prefix_size(len(runs), similarity)
                    if len(keys) and len(runs):
                        at = np.minimum(np.searchsorted(keys, runs), len(keys) - 1)
                        known = np.where(keys[at] == runs, counts[at], 0)
                        if known.any():
                            firsts.append(runs[np.argsort(known, kind="stable")[:take]])
                        else:
                            firsts.append(runs[:take])
                    else:
                        firsts.append(runs[:take])
                    names.append(name)
                    sizes.append(len(runs))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(names, pa.int64()), pa.array(sizes, pa.int32()), _lists(firsts), pa.array(sims.view(np.int64)), pa.array(bits, pa.binary())], names=_EACH)

    return run


def _shared(similarity: float):
    """Rows (run, n, fp), sorted, that have a row of the same run within reach of their size."""

    def keep(run, n, fp):
        near = np.zeros(len(run), bool)
        if len(run) > 1:
            fits = (run[1:] == run[:-1]) & (n[:-1] >= similarity * n[1:] - 1e-9)
            near[1:] |= fits
            near[:-1] |= fits
        return pa.RecordBatch.from_arrays([pa.array(x[near]) for x in (run, n, fp)], names=["run", "n", "fp"])

    def go(batches):
        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            part = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(3)]
            if held is not None:
                part = [np.concatenate(x) for x in zip(held, part)]
            cut = int(np.searchsorted(part[0], part[0][-1]))
            held = [x[cut:] for x in part]
            yield keep(*[x[:cut] for x in part])
        if held is not None:
            yield keep(*held)

    return go


def _common_runs(rows: DataFrame, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Runs of over two texts of every sixteenth, with their counts there: they only set an order."""
    some = rows.where(F.pmod(F.xxhash64("text_hash", F.lit(7)), F.lit(16)) == 0).dropDuplicates(["text_hash"]).select("text")
    runs = some.mapInArrow(released(_whole_sets(words)), "fp long, runs array<long>").select(F.explode("runs").alias("run"))
    counts = runs.groupBy("run").agg(F.count("*").alias("n")).where("n > 2").orderBy(F.desc("n"), "run").limit(_COMMON).toArrow()
    keys, n = counts.column(0).to_numpy(), counts.column(1).to_numpy()
    at = np.argsort(keys)
    return keys[at], n[at]


def _named(sets: DataFrame, pairs: DataFrame) -> DataFrame:
    """Only the sets that stand in a pair, found without moving the others where the names are counted to be few."""
    names = checkpoint(pairs.select(F.col("src").alias("fp")).union(pairs.select("dst")).distinct())
    return sets.join(F.broadcast(names) if names.limit(_COMMON + 1).count() <= _COMMON else names, "fp", "left_semi")


def _possible(pairs: DataFrame, firsts: DataFrame, similarity: float) -> DataFrame:
    """The pairs that their prefixes do not rule out.

    Of the two prefixes, the one that ends first in the order has all its shared runs in the other
    prefix, so the sets share at most those and what follows that prefix.
    """
    firsts = _named(firsts.select("fp", "n", "prefix"), pairs)
    one = pairs.join(firsts.select(F.col("fp").alias("src"), F.col("n").alias("n"), F.col("prefix").alias("a")), "src")
    two = one.join(firsts.select(F.col("fp").alias("dst"), F.col("n").alias("m"), F.col("prefix").alias("b")), "dst")
    most = F.size(F.array_intersect("a", "b")) + F.greatest(F.col("n") - F.size("a"), F.col("m") - F.size("b"))
    return two.where(most * (1 + similarity) >= similarity * (F.col("n") + F.col("m")) - 1e-9).select("src", "dst")


def _alike(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs (src, dst) whose whole sets are similar."""
    one = pairs.join(sets.select(F.col("fp").alias("src"), F.col("runs").alias("a")), "src")
    two = one.join(sets.select(F.col("fp").alias("dst"), F.col("runs").alias("b")), "dst")
    both = two.select("src", "dst", (F.size("a") + F.size("b")).alias("n"), F.size(F.array_intersect("a", "b")).alias("i"))
    return both.where(F.col("i") >= similarity * (F.col("n") - F.col("i")) - 1e-9).select("src", "dst")


def _fits(similarity: float):
    return F.least("n", "m") >= similarity * F.greatest("n", "m") - 1e-9


def _reachable(similarity: float):
    """``src, dst, n, m`` of the members of a tile that are of two components and that sizes and parity bits do not rule out.

    Rows (run, a, b, side, n, fp, c, bits), sorted by tile (run, a, b); members of chunk a have side 0 and, in a
    tile of two chunks, meet only those of side 1.
    """

    def near(x, i, j):
        n, m = x["n"][i], x["n"][j]
        ok = (x["c"][i] != x["c"][j]) & ((x["a"][i] == x["b"][i]) | (x["side"][i] != x["side"][j])) & (np.minimum(n, m) >= similarity * np.maximum(n, m) - 1e-9)
        i, j = i[ok], j[ok]
        apart = np.bitwise_count(x["bits"][i] ^ x["bits"][j]).sum(1, dtype=np.int64)
        ok = apart * (1 + similarity) <= (1 - similarity) * (x["n"][i] + x["n"][j]) + 1e-6
        return i[ok], j[ok]

    def go(batches):
        names = ("run", "a", "b", "side", "n", "fp", "c")
        held = None
        for batch in _with_end(batches):
            x, rest = held, None
            if batch is not None:
                x = {c: batch.column(k).to_numpy(zero_copy_only=False).astype(np.int64) for k, c in enumerate(names)}
                x["bits"] = np.frombuffer(b"".join(batch.column(len(names)).to_pylist()), np.uint64).reshape(batch.num_rows, -1)
                if held is not None:
                    x = {c: np.concatenate([held[c], v]) for c, v in x.items()}
                differs = np.flatnonzero((x["run"] != x["run"][-1]) | (x["a"] != x["a"][-1]) | (x["b"] != x["b"][-1]))
                cut = differs[-1] + 1 if len(differs) else 0
                x, rest = {c: v[:cut] for c, v in x.items()}, {c: v[cut:] for c, v in x.items()}
            held = rest
            if x is None or not len(x["run"]):
                continue
            new = np.concatenate([[True], (x["run"][1:] != x["run"][:-1]) | (x["a"][1:] != x["a"][:-1]) | (x["b"][1:] != x["b"][:-1])])
            edge = np.flatnonzero(new)
            size = np.diff(np.append(edge, len(new)))
            few = np.flatnonzero((size <= _FEW)[np.cumsum(new) - 1])
            group = np.cumsum(new)[few]
            found = []
            for d in range(1, min(_FEW, len(few))):
                at = np.flatnonzero(group[d:] == group[:-d])
                found.append(near(x, few[at], few[at + d]))
            for lo, k in zip(edge[size > _FEW], size[size > _FEW]):
                for at in range(0, k, 64):
                    i = np.arange(at, min(at + 64, k))
                    j = np.arange(at + 1, k)
                    one, two = np.nonzero(i[:, None] < j[None, :])
                    found.append(near(x, lo + i[one], lo + j[two]))
            i, j = (np.concatenate([*[f[k] for f in found], np.zeros(0, np.int64)]).astype(np.int64) for k in (0, 1))
            f, g = x["fp"][i], x["fp"][j]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(f, g)), pa.array(np.maximum(f, g)), pa.array(x["n"][i]), pa.array(x["n"][j])], names=["src", "dst", "n", "m"])

    return go


def _meetings(opened: DataFrame, mixed: DataFrame, firsts: DataFrame, similarity: float, tile: int = _TILE) -> DataFrame:
    """``src, dst, n, m`` for every key in which two sets meet that may be similar.

    mixed: ``run, k`` (its members). A key of more than ``tile`` members is cut into chunks, and each two chunks meet in a task of their own.
    """
    rows = opened.select("run", "n", "fp", "c").join(mixed.select("run", F.ceil(F.col("k") / tile).cast("int").alias("chunks")), "run").join(firsts.select("fp", "bits"), "fp")
    rows = rows.withColumn("r", F.pmod(F.xxhash64("fp", F.lit(9)), "chunks").cast("int")).withColumn("q", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    tiles = rows.select("run", F.least("r", "q").alias("a"), F.greatest("r", "q").alias("b"), (F.col("r") > F.col("q")).cast("int").alias("side"), "n", "fp", "c", "bits")
    return tiles.repartition("run", "a", "b").sortWithinPartitions("run", "a", "b").mapInArrow(released(_reachable(similarity)), "src long, dst long, n long, m long")


def fingerprint_pairs(each: DataFrame, radius: int, blocks: int) -> DataFrame:
    """``src, dst`` of sets whose fingerprints are linked within radius bits (a forest of these links), or equal."""
    sets = each.groupBy("fp").agg(F.min("sim").alias("sim"))
    reps = checkpoint(sets.groupBy("sim").agg(F.min("fp").alias("rep")))
    same = sets.join(reps, "sim").where("fp <> rep").select(F.col("rep").alias("src"), F.col("fp").alias("dst"))
    far = hamming_links(reps.select("rep", F.col("sim").alias("fp")), radius, blocks)
    pairs = same.union(far.select("src", "dst"))
    return pairs.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()


def similar_links(shared: DataFrame, firsts: DataFrame, whole, similarity: float, turns: int = 2, candidates: DataFrame | None = None) -> DataFrame | None:
    """``node, component`` of the sets that are linked, or None.

    shared: ``run, n, fp``; firsts: ``fp, n, prefix, bits``; whole: gives ``fp, runs`` of a table of ``fp``;
    candidates: pairs ``src, dst`` that are verified first.
    """
    weight = shared.groupBy("fp").agg(F.count("*").alias("w"))
    opened = checkpoint(shared.join(weight, "fp").select("run", "n", "fp", (F.col("w") / F.col("n")).alias("w"), F.col("fp").alias("c")))
    links = tried = parts = None

    def verified(pairs: DataFrame) -> DataFrame | None:
        if pairs.isEmpty():
            return None
        sets = whole(pairs.select(F.col("src").alias("fp")).union(pairs.select("dst")).distinct())
        found = checkpoint(_alike(pairs, sets, similarity))
        return None if found.isEmpty() else found

    def named(opened: DataFrame, parts: DataFrame) -> DataFrame:
        to = parts.withColumnRenamed("node", "fp")
        return checkpoint(opened.select("run", "n", "fp", "w").join(to, "fp", "left").select("run", "n", "fp", "w", F.coalesce("component", "fp").alias("c")))

    if candidates is not None:
        tried = checkpoint(candidates)
        links = verified(checkpoint(_possible(tried, firsts, similarity)))
        if links is not None:
            parts = checkpoint(connected_components(links))
            opened = named(opened, parts)
    for turn in range(turns + 1):
        # a key with one component has nothing left to compare
        mixed = opened.groupBy("run").agg(F.count("*").alias("k"), F.min("c").alias("lo"), F.max("c").alias("hi"), F.max(F.struct("w", "fp", "n", "c") if turn == 0 else F.struct(F.xxhash64("fp", F.lit(turn)).alias("w"), "fp", "n", "c")).alias("l")).where("lo < hi")
        if turn < turns:
            lead = mixed.select("run", F.col("l.fp").alias("other"), F.col("l.n").alias("m"), F.col("l.c").alias("d"))
            pairs = opened.join(lead, "run").where((F.col("c") != F.col("d")) & _fits(similarity))
            pairs = pairs.select(F.least("fp", "other").alias("src"), F.greatest("fp", "other").alias("dst")).distinct()
        else:
            # here a pair meets in every run that its prefixes share, so the meetings alone rule most pairs out
            met = _meetings(opened, mixed, firsts, similarity).groupBy("src", "dst").agg(F.count("*").alias("i"), F.first("n").alias("n"), F.first("m").alias("m"))
            left = lambda c: F.ceil(similarity * F.col(c) - 1e-9) - 1  # noqa: E731  what follows a prefix
            pairs = met.where((F.col("i") + F.greatest(left("n"), left("m"))) * (1 + similarity) >= similarity * (F.col("n") + F.col("m")) - 1e-9).select("src", "dst")
        if tried is not None:
            pairs = pairs.join(tried, ["src", "dst"], "left_anti")
        pairs = checkpoint(pairs)
        if pairs.isEmpty():
            if turn < turns and not mixed.isEmpty():
                continue
            break
        tried = pairs if tried is None else tried.union(pairs)
        found = verified(checkpoint(_possible(pairs, firsts, similarity)) if turn < turns else pairs)
        if found is None:
            continue
        links = found if links is None else links.union(found)
        parts = checkpoint(connected_components(links))
        if turn < turns:
            opened = named(opened, parts)
    return parts


def similar_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, similarity: float = 0.8, turns: int = 2, radius: int = 4, blocks: int = 7) -> DataFrame:
    """One row a document: ``doc_id, text_hash, fp`` (names its set), ``part`` (names the component).

    radius, blocks: of the fingerprints, whose links are verified first; the answer is exact with any.
    """
    rows = id_and_text(docs, id_col, text_col).select("doc_id", "text", F.xxhash64("text").alias("text_hash"))
    common = rows.sparkSession.sparkContext.broadcast(_common_runs(rows, words))
    each = checkpoint(rows.mapInArrow(released(_prefixes(words, similarity, common)), "doc_id long, text_hash long, fp long, n int, prefix array<long>, sim long, bits binary"))
    keys = each.select("fp", "n", "prefix").dropDuplicates(["fp"]).select(F.explode("prefix").alias("run"), "n", "fp")
    shared = checkpoint(keys.repartition("run").sortWithinPartitions("run", "n", "fp").mapInArrow(released(_shared(similarity)), "run long, n int, fp long"))
    firsts = checkpoint(each.join(shared.select("fp").distinct(), "fp", "left_semi").select("fp", "n", "prefix", "bits").dropDuplicates(["fp"]))

    def whole(names: DataFrame) -> DataFrame:
        wanted = checkpoint(each.join(names, "fp", "left_semi").groupBy("fp").agg(F.min("text_hash").alias("text_hash")).select("text_hash"))
        small = wanted.limit(_COMMON + 1).count() <= _COMMON
        texts = rows.select("text_hash", "text").join(F.broadcast(wanted) if small else wanted, "text_hash", "left_semi").select("text")
        return checkpoint(texts.mapInArrow(released(_whole_sets(words)), "fp long, runs array<long>").dropDuplicates(["fp"]))

    parts = similar_links(shared, firsts, whole, similarity, turns, fingerprint_pairs(each, radius, blocks))
    found = each.select("doc_id", "text_hash", "fp")
    if parts is None:
        return found.withColumn("part", F.col("fp"))
    return found.join(parts.withColumnRenamed("node", "fp"), "fp", "left").select("doc_id", "text_hash", "fp", F.coalesce("component", "fp").alias("part"))
