"""Quality classifier: document evidence combined with hierarchical empirical Bayes.

Document evidence is the logit of a logistic regression over hashed words, word heads and
shape marks. Sites (hosts, and paths under them) have their own rates of good documents: counts
of labels are grouped by host and by path, a site's rate is shrunk toward its parent's (path to
host, host to the whole) by a strength that the spread among sites tells (method of
moments), so that sparse sites stay near the prior. The two logits add up.

Scale: site counts combine before the shuffle; there is one row a site with labels, joined
by broadcast if they are counted to be at most ``broadcast_rows``, else by key, where a host that
holds a third of all documents meets one row and the adaptive join splits it. The regression is fitted on at most ``sample_rows`` labelled
documents (those with the smallest hash of their id; 20,000 by default) and has ``2**bits`` weights; site counts use every label.

Edge cases: null and empty texts have shape marks only; null hosts or paths are a site of their own;
repeated labels of a document count once, the worst; unknown ids are ignored; with no labels, or
labels of one kind, the evidence is 0 and all documents get the prior (0.5 without labels).
"""

from __future__ import annotations

import math
import re
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import checkpoint
from .common import id_and_text

_WORD = re.compile(r"[^\W_]+")
_SIGN = re.compile(r"[#*$%&|<>]")


def features(text: str, bits: int, cache: dict[str, tuple[int, ...]]) -> np.ndarray:
    """Sorted distinct hashed features of a text."""
    words = _WORD.findall(text.lower())
    distinct = set(words)
    found: set[int] = set()
    mask = (1 << bits) - 1
    for w in distinct:
        hit = cache.get(w)
        if hit is None:
            if len(cache) > 300_000:
                cache.clear()
            hit = cache[w] = (zlib.crc32(w.encode()) & mask, zlib.crc32(b"^" + w[:5].encode()) & mask)
        found.update(hit)
    n = max(1, len(words))
    lines = [x for x in text.split("\n") if x.strip()]
    n_signs = len(_SIGN.findall(text))
    marks = (
        ("size", min(12, int(math.log2(n + 1)))),
        ("signs", min(10, int(20 * n_signs / n))),
        ("same", int(10 * len(distinct) / n)),
        ("lines", int(10 * len(set(lines)) / max(1, len(lines)))),
        ("pairs", int(10 * len(set(zip(words, words[1:]))) / n)),
        ("signed", n_signs > 0.05 * n),
        ("again", n > 5 and len(set(zip(words, words[1:], words[2:]))) < 0.8 * (n - 2)),
    )
    found.update(zlib.crc32(f"#{k}:{v}".encode()) & mask for k, v in marks)
    return np.array(sorted(found), np.int32)


def _feature_batches(bits: int):
    def run(batches):
        cache: dict[str, tuple[int, ...]] = {}
        for batch in batches:
            rows = [features(t, bits, cache) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.int32()))], names=["doc_id", "f"])

    return run


def telling(rows: list[np.ndarray], good: np.ndarray, bits: int, least: int = 3, z: float = 3.0) -> np.ndarray:
    """Which features occur in at least ``least`` documents whose rate of good ones is ``z`` standard errors off the whole's."""
    idx, y = np.concatenate(rows), np.repeat(good, [len(r) for r in rows])
    n, g = np.bincount(idx, minlength=1 << bits), np.bincount(idx, y, minlength=1 << bits)
    p = good.mean()
    return (n >= least) & (np.abs(g - n * p) >= z * np.sqrt(n * p * (1 - p)))


def fit_logistic(rows: list[np.ndarray], good: np.ndarray, bits: int, epochs: int = 15, rate: float = 0.1, decay: float = 1e-4, seed: int = 7) -> tuple[np.ndarray, float]:
    """Weights and intercept by adaptive gradient steps over seeded batches."""
    w, h = np.zeros((1 << bits) + 1), np.full((1 << bits) + 1, 1e-6)
    share = min(max(good.mean(), 1e-3), 1 - 1e-3)
    b, hb = math.log(share / (1 - share)), 1e-6
    rng = np.random.default_rng(seed)
    sizes = np.array([len(r) for r in rows])
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for lo in range(0, len(order), 64):
            at = order[lo : lo + 64]
            idx = np.concatenate([rows[i] for i in at])
            cut = np.concatenate([[0], np.cumsum(sizes[at])[:-1]])
            z = np.add.reduceat(w[idx], cut) + b
            g = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - good[at]
            used, inv = np.unique(idx, return_inverse=True)
            step = np.bincount(inv, np.repeat(g, sizes[at])) / len(at) + decay * w[used]
            h[used] += step**2
            w[used] -= rate * step / np.sqrt(h[used])
            gb = g.mean()
            hb += gb * gb
            b -= rate * gb / math.sqrt(hb)
    return w.astype(np.float32), float(b)


@dataclass(frozen=True)
class TextModel:
    weights: np.ndarray
    intercept: float
    bits: int
    prior: float


def label_rows(labels: DataFrame) -> DataFrame:
    """``doc_id, good``: 1 if quality is 1 and toxic is not; the worst of repeated labels."""
    bad = (F.coalesce(F.col("quality"), F.lit(1)) == 0) | (F.coalesce(F.col("toxic"), F.lit(0)) == 1)
    known = labels.where("doc_id is not null and (quality is not null or toxic is not null)")
    return known.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min((~bad).cast("int")).alias("good"))


def fit_text_model(docs: DataFrame, labels: DataFrame, sample_rows: int = 20_000, bits: int = 18) -> TextModel:
    chosen = label_rows(labels).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    text = id_and_text(docs).join(F.broadcast(chosen), "doc_id")  # bounded by sample_rows
    sample = text.select("doc_id", "text").mapInArrow(_feature_batches(bits), "doc_id long, f array<int>").join(F.broadcast(chosen), "doc_id")
    table = sample.orderBy("doc_id").select("f", "good").toArrow()
    good = table.column("good").to_numpy().astype(float)
    if not len(good) or good.min() == good.max():
        return TextModel(np.zeros(1 << bits, np.float32), 0.0, bits, float(good.mean()) if len(good) else 0.5)
    rows = [np.asarray(x.values) for x in table.column("f")]
    use = telling(rows, good, bits)
    rows = [np.append(r[use[r]], 1 << bits) for r in rows]  # the last place is there for every document
    weights, intercept = fit_logistic(rows, good, bits)
    intercept, weights = intercept + float(weights[-1]), weights[:-1]
    share = float(good.mean())
    # the intercept's part of the prior goes to the sites' side
    return TextModel(weights, intercept - math.log(share / (1 - share)), bits, share)


def _scorer(model, bits: int):
    def run(batches):
        w, b = model.value
        cache: dict[str, tuple[int, ...]] = {}
        for batch in batches:
            z = [float(w[features(t, bits, cache)].sum()) + b for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), batch.column(3), pa.array(z, pa.float64())], names=["doc_id", "host", "path", "evidence"])

    return run


def _strength(sites: DataFrame, parent: str) -> float:
    """Pseudo-counts that fit the spread of the sites' rates around their parents' (moments of a beta-binomial)."""
    p, n = F.col(parent), F.col("n")
    r = sites.agg(F.sum((F.col("g") - n * p) ** 2 - n * p * (1 - p)).alias("extra"), F.sum(p * (1 - p) * n * (n - 1)).alias("scale")).first()
    if not r["scale"] or r["extra"] is None or r["extra"] <= 0:
        return 1e6
    rho = min(r["extra"] / r["scale"], 0.999)
    return min(1e6, max(0.5, 1 / rho - 1))


def site_posteriors(labelled: DataFrame, prior: float) -> DataFrame:
    """labelled: ``host, path, good``. ``host, path, host_rate, site_rate, n``; path null stands for the host itself."""
    paths = labelled.groupBy("host", "path").agg(F.count("*").alias("n"), F.sum("good").alias("g"))
    hosts = paths.groupBy("host").agg(F.sum("n").alias("n"), F.sum("g").alias("g")).withColumn("p0", F.lit(prior))
    k = _strength(hosts, "p0")
    hosts = hosts.select("host", ((F.col("g") + k * prior) / (F.col("n") + k)).alias("host_rate"))
    paths = paths.join(hosts, "host")
    k = _strength(paths, "host_rate")
    return paths.select("host", "path", "host_rate", ((F.col("g") + k * F.col("host_rate")) / (F.col("n") + k)).alias("site_rate"), "n")


def classify(docs: DataFrame, labels: DataFrame, host: str = "source", path: str = "lang", sample_rows: int = 20_000, bits: int = 18, threshold: float = 0.5, broadcast_rows: int = 500_000) -> DataFrame:
    """``doc_id, evidence, site_rate, score, kept`` for every row of docs."""
    model = fit_text_model(docs, labels, sample_rows, bits)
    name = lambda c: F.coalesce(docs[c].cast("string"), F.lit(""))
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.coalesce(docs["text"].cast("string"), F.lit("")).alias("text"), name(host).alias("host"), name(path).alias("path"))
    prior = min(max(model.prior, 1e-4), 1 - 1e-4)
    labelled = rows.select("doc_id", "host", "path").join(label_rows(labels), "doc_id")
    sites = site_posteriors(labelled, prior)
    hosts = sites.groupBy("host").agg(F.first("host_rate").alias("parent"))
    shared = docs.sparkSession.sparkContext.broadcast((model.weights, model.intercept))  # 2**bits numbers
    scored = rows.mapInArrow(_scorer(shared, bits), "doc_id long, host string, path string, evidence double")
    both = scored.join(_light(sites.select("host", "path", "site_rate"), broadcast_rows), ["host", "path"], "left").join(_light(hosts, broadcast_rows), "host", "left")
    rate = F.coalesce("site_rate", "parent", F.lit(prior))
    rate = F.least(F.greatest(rate, F.lit(1e-4)), F.lit(1 - 1e-4))
    score = 1 / (1 + F.exp(-(F.col("evidence") + F.log(rate / (1 - rate)))))
    return both.select("doc_id", "evidence", rate.alias("site_rate"), score.alias("score"), (score >= threshold).alias("kept"))


def _light(sites: DataFrame, most: int) -> DataFrame:
    """A broadcast of sites where they are counted to be at most ``most``; a join by key (split where skewed) beyond."""
    sites = checkpoint(sites)
    return F.broadcast(sites) if sites.limit(most + 1).count() <= most else sites


def page_sites(pages: DataFrame) -> DataFrame:
    """``page_id, host, path`` (the first step of the path) of page urls; null where a url has none."""
    return pages.select("page_id", F.lower(F.regexp_extract("url", r"^[a-z]+://([^/?#]*)", 1)).alias("host"), F.regexp_extract("url", r"^[a-z]+://[^/?#]*/([^/?#]*)", 1).alias("path"))
