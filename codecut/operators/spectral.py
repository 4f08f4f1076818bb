"""Normalized cut of a weighted graph by spectral methods."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.bits import unpack_array


def code_weights(codes: np.ndarray, degrees: np.ndarray, n_bits: int, alpha: float = 1.0, p: float = 1.0, rows: slice | None = None) -> np.ndarray:
    """Dense weights (rows of them): products of degrees over differing bits, zero on the diagonal."""
    signs = unpack_array(codes, n_bits)
    part = signs if rows is None else signs[rows]
    distance = (n_bits - part @ signs.T) / 2
    d = np.asarray(degrees, float) ** alpha
    w = (d if rows is None else d[rows])[:, None] * d[None, :]
    with np.errstate(divide="ignore"):
        return np.where(distance > 0, w / np.maximum(distance, 1) ** p, 0.0)


def spectral_embed(w: np.ndarray, k: int, kind: str = "symmetric") -> np.ndarray:
    """(K, k) embedding: symmetric (rows normalized), random_walk, or unnormalized (the ratio cut)."""
    d = np.maximum(w.sum(1), 1e-300)
    if kind == "unnormalized":
        _, v = np.linalg.eigh(np.diag(d) - w)
        return v[:, :k]
    root = 1 / np.sqrt(d)
    _, v = np.linalg.eigh(root[:, None] * w * root[None, :])
    v = v[:, ::-1][:, :k]
    if kind == "random_walk":
        return v * root[:, None]
    if kind != "symmetric":
        raise ValueError(kind)
    return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)


def kmeans(x: np.ndarray, k: int, seed: int = 0, restarts: int = 20, weights: np.ndarray | None = None, rounds: int = 100) -> tuple[np.ndarray, np.ndarray, float]:
    """(labels, centers, error) of the best of several weighted runs with distance-squared seeding."""
    w = np.ones(len(x)) if weights is None else np.asarray(weights, float)
    k, best = min(k, len(x)), None
    rng = np.random.default_rng(seed)
    norms = (x * x).sum(1)
    square = lambda c: np.maximum(norms[:, None] - 2 * x @ c.T + (c * c).sum(1)[None, :], 0)
    for _ in range(restarts):
        centers = [x[rng.choice(len(x), p=w / w.sum())]]
        near = square(np.array(centers))[:, 0]
        while len(centers) < k:
            p = near * w
            centers.append(x[rng.choice(len(x), p=p / p.sum() if p.sum() > 0 else w / w.sum())])
            near = np.minimum(near, square(centers[-1][None, :])[:, 0])
        c, labels = np.array(centers), None
        for _ in range(rounds):
            d = square(c)
            new = d.argmin(1)
            if labels is not None and np.array_equal(new, labels):
                break
            labels = new
            total = np.bincount(labels, w, minlength=k)
            sums = np.stack([np.bincount(labels, w * x[:, j], minlength=k) for j in range(x.shape[1])], 1)
            full = total > 0
            c[full] = sums[full] / total[full][:, None]
            for e in np.flatnonzero(~full):
                c[e] = x[int((d.min(1) * w).argmax())]
        error = float((square(c).min(1) * w).sum())
        if best is None or error < best[2] - 1e-12:
            best = (labels, c, error)
    return best


def spectral_labels(w: np.ndarray, k: int, seed: int = 0, restarts: int = 20, kind: str = "symmetric") -> np.ndarray:
    """Labels of the vertices. At most k vertices are a cluster each; a graph without edges too."""
    if len(w) <= k:
        return np.arange(len(w))
    return kmeans(spectral_embed(w, k, kind), k, seed, restarts)[0]


def cut_value(w: np.ndarray, labels: np.ndarray, volume: str = "degree") -> float:
    """Half the sum over clusters of the weight that leaves one over its volume (degree sum, or vertices)."""
    d, out = w.sum(1), 0.0
    for c in np.unique(labels):
        inside = labels == c
        vol = d[inside].sum() if volume == "degree" else inside.sum()
        if vol > 0:
            out += w[inside][:, ~inside].sum() / vol
    return 0.5 * float(out)


def ncut_bisect(w: np.ndarray, k: int) -> np.ndarray:
    """k parts by repeated bisection: the part whose best sweep of its second eigenvector cuts least is split."""
    labels = np.zeros(len(w), int)

    def split(at: np.ndarray):
        if len(at) < 2:
            return None
        sub = w[np.ix_(at, at)]
        d = np.maximum(sub.sum(1), 1e-300)
        root = 1 / np.sqrt(d)
        _, v = np.linalg.eigh(root[:, None] * sub * root[None, :])
        order = np.argsort(v[:, -2] * root, kind="stable")
        s, ds = sub[np.ix_(order, order)], d[order]
        inner = np.cumsum(2 * np.tril(s, -1).sum(1) + np.diag(s))
        vol = np.cumsum(ds)
        cut = vol - inner
        value = (cut[:-1] / vol[:-1] + cut[:-1] / (vol[-1] - vol[:-1])) / 2
        at_cut = int(value.argmin())
        return float(value[at_cut]), at[order[at_cut + 1 :]]

    found = {0: split(np.arange(len(w)))}
    for new in range(1, k):
        open_ = {c: s for c, s in found.items() if s}
        if not open_:
            break
        c = min(open_, key=lambda x: open_[x][0])
        labels[open_[c][1]] = new
        for x in (c, new):
            found[x] = split(np.flatnonzero(labels == x))
    return labels


def leading_vectors(step, n: int, k: int, products: int, seed: int = 0, most: int = 600, tolerance: float = 1e-6, most_bytes: int = 400 << 20, first: tuple[np.ndarray, np.ndarray] | None = None) -> np.ndarray:
    """(n, k) vectors of the largest values of a symmetric map that is only known by its products; see ``leading_block``."""
    return leading_block(step, n, k, products, seed, most, tolerance, most_bytes, first)[:, :k]


def leading_block(step, n: int, k: int, products: int, seed: int = 0, most: int = 600, tolerance: float = 1e-6, most_bytes: int = 400 << 20, first: tuple[np.ndarray, np.ndarray] | None = None) -> np.ndarray:
    """k leading vectors and the few that were carried besides them.

    A block Krylov space is spanned by a few products, its best vectors begin the next one; at most
    about ``most`` vectors, or ``most_bytes`` of them, are held, once. Of the images only their parts along the space and the size of the
    rest are kept, which gives the vectors and their residuals; when those are below ``tolerance`` of the largest value for all k, no
    further product is made. ``first`` are vectors to begin with, and their images.
    """
    m = min(n, k + 4) if first is None else first[0].shape[1]
    most = max(2 * m, min(most, most_bytes // (8 * n)))
    if first is None:
        q, known = np.linalg.qr(np.random.default_rng(seed).normal(size=(n, m)))[0], None
    else:
        q, r = np.linalg.qr(first[0])
        known = first[1] @ np.linalg.pinv(r)
    while products > 0:
        rounds = max(1, min(products, most // m, n // m))
        span, small = np.empty((n, rounds * m)), np.zeros((rounds * m, rounds * m))
        for r in range(rounds):
            lo, hi = r * m, r * m + m
            span[:, lo:hi] = q
            image, known = step(q) if known is None else known, None
            along = span[:, :hi].T @ image
            small[:hi, lo:hi] = along
            small[lo:hi, :hi] = along.T
            image -= span[:, :hi] @ along
            image -= span[:, :hi] @ (span[:, :hi].T @ image)
            q, rest = np.linalg.qr(image)
            q = np.linalg.qr(q - span[:, :hi] @ (span[:, :hi].T @ q))[0]
            products -= 1
            value, v = np.linalg.eigh((small[:hi, :hi] + small[:hi, :hi].T) / 2)
            if np.linalg.norm(rest @ v[lo:hi, ::-1][:, :k], axis=0).max() <= tolerance * np.abs(value).max():
                products = 0
                break
        q, _ = np.linalg.qr(span[:, :hi] @ v[:, ::-1][:, :m])
    return q


class Tiles:
    """Weights between some rows and others: ``operand(payload, lo, hi)`` prepares rows (a tuple of arrays), ``weights(a, b, lo, left)`` meets two of these."""

    def __init__(self, operand, weights):
        self.operand, self.weights = operand, weights

    def __call__(self, payload, lo, hi, left=0, right=None):
        right = len(payload[0]) if right is None else right
        return self.weights(self.operand(payload, lo, hi), self.operand(payload, left, right), lo, left)


class BlockedWeights:
    """A symmetric matrix of weights that is never held: blocks of its rows are made anew in each product.

    ``rows(payload, lo, hi)`` gives rows lo to hi. What is broadcast is the payload (once) and the vectors of
    a product; a task holds at most ``block`` rows, and no more than ``most_bytes`` of them, at once.
    With ``scale`` the matrix is that of ``rows`` with rows and columns multiplied by it, which is never done to a block.
    With ``tiled``, ``rows(payload, lo, hi, left, right)`` gives some columns of them, and products go by tiles that stay in a core's cache.
    With ``tiles``, products of more than ``halved_above`` rows make the weights of two rows once, for both of them.
    """

    def __init__(self, spark: SparkSession, n: int, payload, rows, block: int = 1024, most_bytes: int = 64 << 20, scale: np.ndarray | None = None, tiled: bool = False, tiles: Tiles | None = None, halved_above: int = 20_000):
        block = max(1, min(block, most_bytes // (8 * n)))
        self.spark, self.n, self.rows, self.tiled = spark, n, rows, tiled
        self.tiles = tiles if n > halved_above else None
        self.scale = np.ones(n) if scale is None else scale
        self.payload = spark.sparkContext.broadcast(payload)
        cuts = [(i, min(i + block, n)) for i in range(0, n, block)]
        self.blocks = spark.createDataFrame(cuts, "lo int, hi int").repartition(min(len(cuts), 8 * spark.sparkContext.defaultParallelism))

    def _each(self, shared_value, fn, tiles=None) -> np.ndarray:
        shared, payload, rows = self.spark.sparkContext.broadcast(shared_value), self.payload, self.rows

        def run(batches):
            for b in batches:
                for lo, hi in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                    out = tiles(payload.value, shared.value, lo, hi) if tiles else fn(rows(payload.value, lo, hi), shared.value, lo, hi)
                    out = np.ascontiguousarray(out, float)
                    yield pa.RecordBatch.from_arrays([pa.array([lo], pa.int32()), pa.array([out.tobytes()], pa.binary())], names=["lo", "data"])

        parts = self.blocks.mapInArrow(run, "lo int, data binary").collect()
        shared.unpersist()
        return np.concatenate([np.frombuffer(r["data"]) for r in sorted(parts, key=lambda r: r["lo"])])

    def _halved(self, x: np.ndarray, most_bytes: int = 64 << 20) -> np.ndarray:
        """The product by parts of rows: a task meets two of them and gives what each gets from the other.

        The pairs of parts go round in turns, all of them the same work; as many turns are a job as send ``most_bytes`` to the driver.
        """
        spark, n, tiles, payload, m = self.spark, self.n, self.tiles, self.payload, x.shape[1]
        parts = 2 * min(32, max(2, spark.sparkContext.defaultParallelism))
        cuts = [n * i // parts for i in range(parts + 1)]
        shared, out = spark.sparkContext.broadcast(x), np.zeros(x.shape)

        def meet(i, j, y):
            a, b = (tiles.operand(payload.value, cuts[p], cuts[p + 1]) for p in (i, j))
            mine, theirs = np.zeros((len(a[0]), m)), np.zeros((len(b[0]), m))
            ya, yb = (np.ascontiguousarray(y[cuts[p] : cuts[p + 1]], a[0].dtype) for p in (i, j))
            for left in range(0, len(theirs), 1024):
                here = tuple(c[left : left + 1024] for c in b)
                for top in range(0, len(mine), 256):
                    w = tiles.weights(tuple(c[top : top + 256] for c in a), here, cuts[i] + top, cuts[j] + left)
                    mine[top : top + 256] += w @ yb[left : left + 1024]
                    if i != j:
                        theirs[left : left + 1024] += w.T @ ya[top : top + 256]
            return [(i, mine), (j, theirs)] if i != j else [(i, mine)]

        pairs = [(i, (i + turn) % parts) for turn in range(parts // 2 + 1) for i in range(parts if turn < parts // 2 else parts // 2)]
        each = parts * max(1, most_bytes // (16 * n * m))
        for lo in range(0, len(pairs), each):
            some = pairs[lo : lo + each]

            def run(batches, some=some):
                for b in batches:
                    for t in b.column(0).to_pylist():
                        got = meet(*some[t], shared.value)
                        yield pa.RecordBatch.from_arrays([pa.array([p for p, _ in got], pa.int32()), pa.array([v.tobytes() for _, v in got], pa.binary())], names=["part", "data"])

            for r in spark.range(0, len(some), 1, len(some)).mapInArrow(run, "part int, data binary").collect():
                out[cuts[r["part"]] : cuts[r["part"] + 1]] += np.frombuffer(r["data"]).reshape(-1, m)
        shared.unpersist()
        return out

    def times(self, x: np.ndarray) -> np.ndarray:
        n, rows = self.n, self.rows
        if self.tiles:
            return self.scale[:, None] * self._halved(self.scale[:, None] * x)

        def tiles(payload, y, lo, hi):
            out = np.zeros((hi - lo, y.shape[1]))
            for top in range(lo, hi, 256):
                for left in range(0, n, 512):
                    end, right = min(top + 256, hi), min(left + 512, n)
                    out[top - lo : end - lo] += rows(payload, top, end, left, right) @ y[left:right]
            return out

        return self.scale[:, None] * self._each(self.scale[:, None] * x, lambda w, y, lo, hi: w @ y, tiles if self.tiled else None).reshape(x.shape)

    def to_earlier(self, rank: np.ndarray) -> np.ndarray:
        """Of each row the weight to rows of smaller rank."""
        return self.scale * self._each((rank, self.scale), lambda w, r, lo, hi: (w * (r[0][None, :] < r[0][lo:hi, None])) @ r[1])

    def strengths(self) -> np.ndarray:
        return self.times(np.ones((self.n, 1)))[:, 0]

    def embed(self, k: int, kind: str = "symmetric", iterations: int = 30, seed: int = 0, normed: bool = True, start: np.ndarray | None = None) -> np.ndarray:
        """(n, k) leading vectors by ``iterations`` products; kinds as in ``spectral_embed``.

        One product gives the strengths and the first images, those of ``start`` (times the root of the strengths, where vectors are
        scaled by it) or of random vectors.
        """
        y = np.random.default_rng(seed).normal(size=(self.n, min(self.n, k + 4))) if start is None else start
        image = self.times(np.column_stack([np.ones(self.n), y]))
        d, image = np.maximum(image[:, 0], 1e-300), image[:, 1:]
        if kind == "unnormalized":
            top = 2 * d.max()
            step = lambda q: (top - d)[:, None] * q + self.times(q)
            first = y, (top - d)[:, None] * y + image
        elif kind in ("symmetric", "random_walk"):
            root = 1 / np.sqrt(d)
            # the shift by the identity makes the wanted eigenvalues the largest in size
            step = lambda q: root[:, None] * self.times(root[:, None] * q) + q
            first = y / root[:, None], root[:, None] * image + y / root[:, None]
        else:
            raise ValueError(kind)
        e = leading_vectors(step, self.n, k, iterations, seed, first=first)
        if kind == "random_walk":
            return e * root[:, None]
        return e / np.maximum(np.linalg.norm(e, axis=1, keepdims=True), 1e-12) if kind == "symmetric" and normed else e

    def cut_value(self, labels: np.ndarray) -> float:
        kinds, of = np.unique(labels, return_inverse=True)
        to = self.times(np.eye(len(kinds))[of])
        volume = np.bincount(of, to.sum(1))
        inside = np.bincount(of, to[np.arange(self.n), of])
        return 0.5 * float(((volume - inside)[volume > 0] / volume[volume > 0]).sum())

    def sweep(self, seed: int = 0, iterations: int = 60) -> tuple[float, np.ndarray] | None:
        """(cut value, which rows are on the far side) of the best sweep of the second vector."""
        if self.n < 2:
            return None
        d = np.maximum(self.strengths(), 1e-300)
        order = np.argsort(self.embed(2, seed=seed, iterations=iterations, normed=False)[:, 1] / np.sqrt(d), kind="stable")
        rank = np.empty(self.n, int)
        rank[order] = np.arange(self.n)
        inner = np.cumsum(2 * self.to_earlier(rank)[order])
        vol = np.cumsum(d[order])
        value = ((vol - inner)[:-1] / vol[:-1] + (vol - inner)[:-1] / (vol[-1] - vol[:-1])) / 2
        at = int(value.argmin())
        return float(value[at]), order[at + 1 :]


def blocked_code_weights(spark: SparkSession, codes: np.ndarray, degrees: np.ndarray, n_bits: int, alpha: float = 1.0, p: float = 1.0, block: int = 1024, halved_above: int = 20_000) -> BlockedWeights:
    """The graph of codes: the payload is a code a vertex and a weight a distance; vertices are bounded by the caller."""
    by_distance = np.concatenate([[0.0], np.arange(1, n_bits + 1) ** -float(p)])
    words = np.asarray(codes, np.int64).reshape(len(codes), -1).T.copy().view(np.uint64)

    def rows(payload, lo, hi):
        words, by_distance = payload
        distance = np.bitwise_count(words[0][lo:hi, None] ^ words[0][None, :])
        for more in words[1:]:
            distance = distance.astype(np.int32) + np.bitwise_count(more[lo:hi, None] ^ more[None, :])
        return by_distance[distance]

    def operand(payload, lo, hi):
        signs = unpack_array(payload[0][:, lo:hi].T.view(np.int64), n_bits).astype(np.float32)
        ones = np.ones((hi - lo, 1), np.float32)
        return np.hstack([signs / -2, n_bits / 2 * ones]), np.hstack([signs, ones])

    def weights(a, b, lo, left):
        w = a[0] @ b[1].T  # distances: halves and wholes, exact in single precision
        if w.min(initial=1) <= 0:
            w[w <= 0] = np.inf
        np.reciprocal(w, out=w)
        return w if p == 1 else np.power(w, p, out=w)

    return BlockedWeights(spark, len(codes), (words, by_distance), rows, block, scale=np.asarray(degrees, float) ** alpha, tiles=Tiles(operand, weights), halved_above=halved_above)


def block_subspace_iteration(spark: SparkSession, codes: np.ndarray, degrees: np.ndarray, n_bits: int, k: int, iterations: int = 30, block: int = 1024, seed: int = 0, alpha: float = 1.0, p: float = 1.0, kind: str = "symmetric") -> np.ndarray:
    """The embedding of the graph of codes without its matrix."""
    return blocked_code_weights(spark, codes, degrees, n_bits, alpha, p, block).embed(k, kind, iterations, seed)


def blocked_bisect(part, n: int, k: int, seed: int = 0) -> np.ndarray:
    """k parts by repeated bisection; ``part(rows)`` gives the BlockedWeights among some rows."""
    labels = np.zeros(n, int)

    def split(at: np.ndarray):
        found = part(at).sweep(seed) if len(at) > 1 else None
        return found and (found[0], at[found[1]])

    found = {0: split(np.arange(n))}
    for new in range(1, k):
        open_ = {c: s for c, s in found.items() if s}
        if not open_:
            break
        c = min(open_, key=lambda x: open_[x][0])
        labels[open_[c][1]] = new
        for x in (c, new):
            found[x] = split(np.flatnonzero(labels == x))
    return labels


def power_iteration_labels(edges: DataFrame, k: int, iterations: int = 20) -> DataFrame:
    """``code, cluster`` by the library's power iteration on sparse edges(src, dst, weight)."""
    from pyspark.ml.clustering import PowerIterationClustering

    names = edges.select(F.col("src").alias("code")).union(edges.select("dst")).distinct()
    ids = names.select("code", (F.row_number().over(Window.orderBy("code")) - 1).cast("long").alias("id"))
    numbered = edges.join(ids.select(F.col("code").alias("src"), F.col("id").alias("a")), "src").join(ids.select(F.col("code").alias("dst"), F.col("id").alias("b")), "dst")
    pic = PowerIterationClustering(k=k, maxIter=iterations, initMode="degree", srcCol="a", dstCol="b", weightCol="weight")
    return pic.assignClusters(numbered.select("a", "b", F.col("weight").cast("double").alias("weight"))).join(ids, "id").select("code", "cluster")
