"""Blocks of the graph of codes: equal to its matrix, and made without the bits of all codes."""

import tracemalloc

import numpy as np
import pytest

from codecut.operators.spectral import blocked_code_weights, code_weights


@pytest.mark.parametrize("bits", [64, 100])
def test_blocks_equal_the_matrix(spark, bits):
    rng = np.random.default_rng(bits)
    codes = rng.integers(-(2**63), 2**63 - 1, 90) if bits == 64 else np.stack([rng.integers(-(2**63), 2**63 - 1, 90), rng.integers(0, 1 << 36, 90)], 1)
    degrees = rng.integers(1, 50, 90).astype(float)
    full = code_weights(codes, degrees, bits, 0.5, 1.5)
    b = blocked_code_weights(spark, codes, degrees, bits, 0.5, 1.5, block=17)
    x, rank = rng.normal(size=(90, 3)), rng.permutation(90)
    assert np.allclose(b.times(x), full @ x) and np.allclose(b.strengths(), full.sum(1))
    assert np.allclose(b.to_earlier(rank), (full * (rank[None, :] < rank[:, None])).sum(1))


def test_a_block_takes_no_more_than_its_rows(spark):
    n = 200_000
    codes = np.random.default_rng(0).integers(-(2**63), 2**63 - 1, n)
    b = blocked_code_weights(spark, codes, np.ones(n), 64)
    payload = b.payload.value
    tracemalloc.start()
    b.rows(payload, 0, 2)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 40e6  # the bits of all codes alone are 102 MB


def test_documents_of_many_codes_are_not_refused(spark, sf, monkeypatch):
    """the query stopped at 100,000 codes."""
    from pyspark.sql import functions as F

    from codecut.plans import pipeline, queries_method

    class Asked(Exception):
        pass

    class Kept(pipeline.CodeGraphClustering):
        def _fit(self, dataset):
            raise Asked(self.settings)

    monkeypatch.setattr(queries_method, "CodeGraphClustering", Kept)
    with pytest.raises(Asked) as asked:
        queries_method.pipeline_documents(spark, sf)
    degrees = spark.range(100_001).select(F.col("id").alias("code"), F.lit(0).alias("site_id"), (F.col("id") % 3 + 1).alias("degree"))
    codes, counts = pipeline.graph_vertices(degrees, asked.value.args[0])
    assert len(set(codes.tolist())) == 100_001 and counts.sum() == sum(i % 3 + 1 for i in range(100_001)) and counts[0] == 3
