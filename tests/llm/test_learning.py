"""The learned text operators against plain recomputation."""

import math
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from codecut.llm import decision_list as dl
from codecut.llm import empirical_bayes as eb

SPACE = r"[\x20\x09-\x0D]+"


def features_of(text, flagged):
    """The statistics of FEATURES, word by word."""
    text = text or ""
    words = [w for w in re.split(SPACE, text) if w]
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    runs = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    again = {j for i in range(len(words) - 2) if runs[tuple(words[i : i + 3])] > 1 for j in (i, i + 1, i + 2)}
    n = max(1, len(words))
    heads = {f for f in flagged if len(f) == 5}
    flags = sum((p := w.lower().strip(dl._EDGES)) in flagged or p[:5] in heads for w in words)
    shape = (sum(map(len, words)) / n, len(re.findall(r"[#*$%&|<>]", text)) / n, (len(lines) - len(set(lines))) / max(1, len(lines)), len(again) / n, len(set(words)) / n, len(words) / max(1, len(lines)), float(flags))
    return len(words), len(again), shape


def verdict(text, model):
    n, again, shape = features_of(text, set(model.flagged))
    if n < 50 or 100 * again > 50 * n:
        return False
    return not any(all((shape[dl.FEATURES.index(c.feature)] >= c.cut) == c.above for c in rule) for rule in model.rules)


@pytest.fixture(scope="module")
def given(spark):
    big = "/root/testdata/sf0.01"
    return spark.read.parquet(f"{big}/documents.parquet"), spark.read.parquet(f"{big}/labels.parquet")


def test_verdicts_word_by_word(spark, given):
    docs, labels = given
    model = dl.learn(docs, labels)
    assert model.rules and model.flagged
    got = {r["doc_id"]: r["kept"] for r in dl.judge(docs, model).collect()}
    assert got == {r["doc_id"]: verdict(r["text"], model) for r in docs.collect()}


def test_held_out_third_is_not_fitted(given):
    """Labels of the held-out third can stop a rule, but neither words nor cuts come from them."""
    docs, labels = given
    held = F.pmod(F.xxhash64("doc_id"), F.lit(3)) == 0
    turned = labels.withColumn("toxic", F.when(held, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    words = lambda l: dl.flagged_words(dl.labelled_sample(docs, l, 20_000).withColumn("held_out", held).where("not held_out"))
    assert words(labels) == words(turned)
    assert len(dl.learn(docs, turned).rules) <= len(dl.learn(docs, labels).rules)


def drawn(n, seed):
    draw, out = random.Random(seed), []
    for _ in range(n):
        x = tuple(round(draw.random() * 8) / 8 for _ in dl.FEATURES)
        bad = x[1] >= 0.75 and x[3] < 0.5 or x[6] >= 0.875
        out.append((int(bad if draw.random() < 0.97 else not bad), x))
    return out


def test_first_condition_is_the_best_of_all():
    rows = drawn(400, 1)
    cuts = dl.candidate_cuts(rows, 64)
    rule = dl._grow(rows, cuts, 1, 3)
    pos = sum(b for b, _ in rows)
    best = -math.inf
    for i in range(len(dl.FEATURES)):
        for c in cuts[i]:
            for above in (True, False):
                inside = [b for b, x in rows if (x[i] >= c) == above]
                p, n = sum(inside), len(inside)
                if p >= 3:
                    best = max(best, p * (math.log2((p + 0.01) / (n + 0.01)) - math.log2(pos / len(rows))))
    (c,) = rule
    inside = [b for b, x in rows if (x[dl.FEATURES.index(c.feature)] >= c.cut) == c.above]
    assert abs(sum(inside) * (math.log2((sum(inside) + 0.01) / (len(inside) + 0.01)) - math.log2(pos / len(rows))) - best) < 1e-6


def test_covering_finds_the_planted_rules():
    grow, held, fresh = drawn(3000, 2), drawn(1500, 3), drawn(2000, 4)
    rules = dl.cover(grow, held, min_precision=0.8)
    said = [any(dl._holds(r, x) for r in rules) for _, x in fresh]
    true = [x[1] >= 0.75 and x[3] < 0.5 or x[6] >= 0.875 for _, x in fresh]
    assert sum(a == b for a, b in zip(said, true)) > 0.97 * len(fresh)
    assert dl.cover([(1, x) for _, x in grow], held) == dl.cover([(0, x) for _, x in grow], held) == dl.cover([], []) == []
    # a rule that holds in the grown part by chance alone is not taken
    noise = random.Random(5)
    assert dl.cover([(int(noise.random() < 0.3), x) for _, x in grow[:300]], [(0, x) for _, x in held]) == []


def posterior(rows, prior):
    """(host, path) -> rate, from (host, path, good), by the moments written out."""

    def strength(groups):
        extra = sum((g - n * p) ** 2 - n * p * (1 - p) for n, g, p in groups)
        scale = sum(p * (1 - p) * n * (n - 1) for n, g, p in groups)
        if not scale or extra <= 0:
            return 1e6
        return min(1e6, max(0.5, 1 / min(extra / scale, 0.999) - 1))

    hosts, paths = {}, {}
    for h, p, g in rows:
        for of, k in ((hosts, h), (paths, (h, p))):
            n, s = of.get(k, (0, 0))
            of[k] = (n + 1, s + g)
    k = strength([(n, g, prior) for n, g in hosts.values()])
    host_rate = {h: (g + k * prior) / (n + k) for h, (n, g) in hosts.items()}
    k = strength([(n, g, host_rate[h]) for (h, _), (n, g) in paths.items()])
    return host_rate, {(h, p): (g + k * host_rate[h]) / (n + k) for (h, p), (n, g) in paths.items()}


def test_evidence_and_posteriors_written_out(spark, given):
    docs, labels = given
    odd = spark.createDataFrame([(90_001, None, None, None), (90_002, "", "new host", "xx"), (90_003, "only a few words", "src0", "zz")], "doc_id long, text string, source string, lang string")
    docs = docs.select("doc_id", "text", "source", "lang").union(odd)
    labels = labels.select("doc_id", "quality", "toxic").union(spark.createDataFrame([(1, 0, 0), (1, 1, 0), (None, 0, 1), (777_777, 0, 0)], "doc_id long, quality int, toxic int"))
    found = {r["doc_id"]: r for r in eb.classify(docs, labels).collect()}
    model = eb.fit_text_model(docs, labels)
    good = {}
    for r in labels.collect():
        if r["doc_id"] is not None:
            bad = r["quality"] == 0 or r["toxic"] == 1
            good[r["doc_id"]] = min(good.get(r["doc_id"], 1), int(not bad))
    rows = docs.collect()
    prior = min(max(model.prior, 1e-4), 1 - 1e-4)
    hosts, sites = posterior([(r["source"] or "", r["lang"] or "", good[r["doc_id"]]) for r in rows if r["doc_id"] in good], prior)
    assert len(found) == len(rows)
    for r in rows:
        got, where = found[r["doc_id"]], (r["source"] or "", r["lang"] or "")
        evidence = math.fsum(model.weights[i] for i in eb.features(r["text"] or "", model.bits, {})) + model.intercept
        rate = sites.get(where, hosts.get(where[0], prior))
        rate = min(max(rate, 1e-4), 1 - 1e-4)
        score = 1 / (1 + math.exp(-(evidence + math.log(rate / (1 - rate)))))
        assert abs(got["evidence"] - evidence) < 1e-3 and abs(got["site_rate"] - rate) < 1e-9 and abs(got["score"] - score) < 1e-3
        assert got["kept"] == (got["score"] >= 0.5)


def test_logistic_weights_separate_planted_features():
    rng = np.random.default_rng(3)
    rows, good = [], []
    for _ in range(600):
        y = rng.random() < 0.6
        rows.append(np.unique(np.concatenate([rng.integers(10, 200, 8), [1 if y else 2]])))
        good.append(float(y))
    w, b = eb.fit_logistic(rows, np.array(good), 8)
    assert all((w[r].sum() + b > 0) == bool(y) for r, y in zip(rows, good))
    use = eb.telling(rows, np.array(good), 8)
    assert use[1] and use[2] and use.sum() < 12


def test_sites_of_pages(spark):
    rows = [(1, "https://A.example/x/y?z"), (2, "http://b.example"), (3, "http://b.example/"), (4, None), (5, "no url"), (6, "ftp://c.example:8/q#f")]
    got = {r["page_id"]: (r["host"], r["path"]) for r in eb.page_sites(spark.createDataFrame(rows, "page_id long, url string")).collect()}
    assert got == {1: ("a.example", "x"), 2: ("b.example", ""), 3: ("b.example", ""), 4: (None, None), 5: ("", ""), 6: ("c.example:8", "q")}
