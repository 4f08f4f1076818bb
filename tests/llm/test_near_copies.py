"""The stage of near copies: fingerprints first, and no square of a large group of copies after them."""

import numpy as np
import pytest

import corpus_pipeline
from codecut.llm import set_join


def edited(rng, base, n):
    copy = list(base)
    for at in rng.integers(0, len(base), n):
        copy[at] = f"edit{rng.integers(1 << 40)}"
    return " ".join(copy)


def test_stage_links_by_fingerprints_first(spark, monkeypatch):
    """the stage left out the fingerprints and their blocks."""
    rng = np.random.default_rng(3)
    base = [f"w{x}" for x in rng.integers(0, 5000, 400)]
    docs = spark.createDataFrame([(i, edited(rng, base, i % 3)) for i in range(12)], "doc_id long, text string")
    seen = {}
    plain = set_join.similar_links

    def links(shared, firsts, whole, similarity, turns=2, candidates=None):
        seen["candidates"] = candidates and candidates.count()
        return plain(shared, firsts, whole, similarity, turns, candidates)

    monkeypatch.setattr(set_join, "similar_links", links)
    assert [r["doc_id"] for r in corpus_pipeline.near_duplicates(spark, docs, None).collect()] == [0]
    assert seen["candidates"]


@pytest.mark.parametrize("tile", [7, 512])
def test_large_group_of_near_copies_meets_in_few_pairs(spark, tile):
    """All pairs of a key that are similar, and few of the others, whatever the tiles."""
    rng = np.random.default_rng(4)
    base = [f"w{x}" for x in rng.integers(0, 5000, 150)]
    sets = {}
    for i in range(90):
        name, runs = set_join.run_set(edited(rng, base, i % 9), 5)
        sets[name] = runs
    rows = [(run, len(r), f, f) for f, r in sets.items() for run in (1, 2)] + [(3, len(r), f, f) for f, r in list(sets.items())[:5]]
    opened = spark.createDataFrame(rows, "run long, n int, fp long, c long")
    mixed = spark.createDataFrame([(1, len(sets)), (2, len(sets)), (3, 5)], "run long, k long")
    firsts = spark.createDataFrame([(f, bytearray(set_join.parity_bits(r))) for f, r in sets.items()], "fp long, bits binary")
    met = [(r["src"], r["dst"]) for r in set_join._meetings(opened, mixed, firsts, 0.8, tile).collect()]
    of = {f: set(r.tolist()) for f, r in sets.items()}
    names = sorted(sets)
    alike = {(a, b) for a in names for b in names if a < b and 5 * len(of[a] & of[b]) >= 4 * len(of[a] | of[b])}
    assert alike <= set(met) and max(met.count(p) for p in set(met)) <= 3
    assert all(met.count(p) >= 2 for p in alike)
    assert len(set(met)) < len(alike) + 0.1 * len(names) ** 2 / 2


def test_parity_bits_bound_the_difference():
    rng = np.random.default_rng(5)
    for n in (0, 1, 40, 3000):
        a = np.unique(rng.integers(-(2**63), 2**63 - 1, n))
        b = np.unique(np.concatenate([a[: n // 2], rng.integers(-(2**63), 2**63 - 1, n // 3)]))
        x, y = (np.frombuffer(set_join.parity_bits(s), np.uint64) for s in (a, b))
        assert np.bitwise_count(x ^ y).sum() <= len(np.setxor1d(a, b))
