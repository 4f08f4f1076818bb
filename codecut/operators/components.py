"""Connected components of a distributed edge table."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import checkpoint


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node of its part) for the graph with the given edges."""
    nodes, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    u, v = ends[: len(a)], ends[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[u], label[v])
        new = label.copy()
        np.minimum.at(new, label[u], low)
        np.minimum.at(new, label[v], low)
        while True:
            jumped = new[new]
            if np.array_equal(jumped, new):
                break
            new = jumped
        if np.array_equal(new, label):
            return nodes, nodes[label]
        label = new


def _contract(batches):
    """Replace the edges that a task holds by a star for each part, block by block."""
    held: list[tuple[np.ndarray, np.ndarray]] = []
    count = 0

    def flush():
        a, b = (np.concatenate(x) for x in zip(*held))
        node, root = forest(a, b)
        keep = node != root
        return node[keep], root[keep]

    for batch in batches:
        if batch.num_rows:
            held.append((batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)))
            count += batch.num_rows
        if count > 2_000_000:
            star = flush()
            held, count = [star], len(star[0])
    if held:
        node, root = flush()
        yield pa.RecordBatch.from_arrays([pa.array(node, pa.int64()), pa.array(root, pa.int64())], names=["src", "dst"])


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 40, few: int = 200_000) -> DataFrame:
    """Label every node that has an edge with the smallest node it can reach.

    Input: two integer columns; direction, repeats, loops and nulls do not matter.
    Output: ``node``, ``component`` (long), one row for each node with an edge to another node.

    Each task first replaces its edges by stars. Then alternating rounds hook every
    larger neighbour, then every smaller one, to the smallest neighbour, which
    converges in a logarithmic number of rounds. Minima combine before the shuffle,
    and the join back to a hot node has one row on the other side, so that the
    adaptive skew join can split it. Each round is checkpointed. Where at most ``few`` edges are left
    (counted), one task settles them at once.
    """
    e = edges.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))
    e = e.where("src <> dst").mapInArrow(_contract, "src long, dst long").distinct()
    e = checkpoint(e)
    seen = None
    if e.limit(few + 1).count() <= few:
        e = checkpoint(e.coalesce(1).mapInArrow(_contract, "src long, dst long"))
        max_rounds = 0
    for _ in range(max_rounds):
        both = e.union(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        low = both.groupBy("src").agg(F.min("dst").alias("m")).select("src", F.least("src", "m").alias("m"))
        large = both.where("dst > src").join(low, "src").select(F.col("dst").alias("src"), F.col("m").alias("dst")).where("src <> dst").distinct()
        down = large.select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst"))
        least = down.groupBy("src").agg(F.min("dst").alias("m"))
        small = down.join(least, "src").select(F.col("dst").alias("n"), "m").union(least.select(F.col("src").alias("n"), "m"))
        e = checkpoint(small.where("n <> m").select(F.col("n").alias("src"), F.col("m").alias("dst")).distinct())
        state = e.agg(F.count("*"), F.sum(F.xxhash64("src", "dst").cast("decimal(38,0)"))).first()
        if state == seen:
            break
        seen = state
    else:
        if max_rounds:
            raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = e.select(F.col("dst").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return e.select(F.col("src").alias("node"), F.col("dst").alias("component")).union(roots)
