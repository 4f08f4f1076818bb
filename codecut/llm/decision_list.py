"""Learned decision lists over text statistics, in DataFrame functions only.

``text_statistics`` measures every whole text. ``learn`` runs sequential covering on
the statistics of labelled documents: a rule grows one threshold at a time from
counts between cuts, is pruned against a held-out third and taken if it is precise there too, its
documents are taken out, and the next rule is grown. The list comes out as an ordered
conditional expression that runs inside the scan.

Scale: statistics are row-local, without any shuffle, whatever the source or group of copies.
The model is fitted on at most ``sample_rows`` labelled documents (those with
the smallest hash of their id, 20,000 by default), so the sample's ids may be broadcast and its seven statistics a row held by the driver; everything else
covers all rows. The word list has at most ``max_words`` entries.

Edge cases: null and empty texts have no words and no lines with a word: all
statistics are 0 and the base rule rejects them; repeated rows are judged alike; labels that are null,
of unknown ids, or repeated (the worst one counts) do no harm; without labels, or where all
labels agree, the list is empty and only the base rule rejects.
"""

from __future__ import annotations

import math
from bisect import bisect_right
from collections import Counter
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import checkpoint
from .common import computed, quoted

SYMBOLS = "#*$%&|<>"
_EDGES = ".,;:!?\"'()[]{}*&$%#|<>-_/"
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
FEATURES = ("word_length", "symbol_share", "dup_line_share", "repeat_share", "distinct_share", "line_words", "flagged_words")


def _plain(word: Column) -> Column:
    """A word in lower case without marks at its ends."""
    return F.trim(F.lower(word), F.lit(_EDGES))


def text_statistics(docs: DataFrame, flagged: list[str] = (), id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id``, the columns of BASE (long) and those of FEATURES (double), besides the columns in keep."""
    t = F.coalesce(docs[text_col].cast("string"), F.lit(""))
    df = docs.select(docs[id_col].cast("long").alias("doc_id"), *keep, t.alias("_t"))
    lines = F.filter(F.split("_t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    df = computed(df, F.array_remove(F.split("_t", r"[\x20\x09-\x0D]+"), "").alias("_w"), lines.alias("_l"))
    chars = F.aggregate("_w", F.lit(0), lambda x, w: x + F.length(w))
    df = df.select("doc_id", *keep, "_w", "_l", chars.alias("_c"), F.regexp_count("_t", F.lit(f"[{SYMBOLS}]")).alias("_s"))
    runs = F.transform(F.sequence(F.lit(1), F.size("_w") - 2), lambda i: F.struct(F.xxhash64(F.slice("_w", i, 3)).alias("h"), i.alias("i")))
    df = computed(df, F.sort_array(F.when(F.size("_w") >= 3, runs).otherwise(F.array().cast("array<struct<h:bigint,i:int>>"))).alias("_r"))
    # equal runs stand side by side in the sorted array; each of a pair covers three words
    m = F.greatest(F.size("_r") - 1, F.lit(0))
    pairs = F.zip_with(F.slice("_r", F.lit(1), m), F.slice("_r", F.lit(2), m), lambda x, y: F.when(x["h"] == y["h"], F.struct(x["i"].alias("i"), y["i"].alias("j"))))
    three = lambda i: [i, i + 1, i + 2]
    covered = F.size(F.array_distinct(F.flatten(F.transform(F.filter(pairs, lambda p: p.isNotNull()), lambda p: F.array(*three(p["i"]), *three(p["j"]))))))
    n = F.size("_w")
    flag = F.lit(0)
    if flagged:
        heads = [f for f in flagged if len(f) == 5]
        flag = F.size(F.filter(F.transform("_w", _plain), lambda w: w.isin(list(flagged)) | F.substring(w, 1, 5).isin(heads)))
    one = lambda x: F.greatest(x, F.lit(1))
    df = df.select("doc_id", *keep, n.cast("long").alias("n_words"), F.col("_c").cast("long").alias("word_chars"), F.col("_s").cast("long").alias("n_symbols"), (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"), covered.cast("long").alias("n_repeat_words"), F.size(F.array_distinct("_w")).alias("_d"), F.size("_l").alias("_n"), flag.cast("double").alias("flagged_words"))
    return df.select("doc_id", *keep, *BASE, (F.col("word_chars") / one(F.col("n_words"))).alias("word_length"), (F.col("n_symbols") / one(F.col("n_words"))).alias("symbol_share"), (F.col("n_dup_lines") / one(F.col("_n"))).alias("dup_line_share"), (F.col("n_repeat_words") / one(F.col("n_words"))).alias("repeat_share"), (F.col("_d") / one(F.col("n_words"))).alias("distinct_share"), (F.col("n_words") / one(F.col("_n"))).alias("line_words"), "flagged_words")


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


@dataclass(frozen=True)
class Condition:
    feature: str
    above: bool
    cut: float

    def column(self) -> Column:
        return F.col(self.feature) >= self.cut if self.above else F.col(self.feature) < self.cut

    def __str__(self) -> str:
        return f"{self.feature} {'>=' if self.above else '<'} {self.cut:.6g}"


@dataclass
class DecisionList:
    rules: list[tuple[Condition, ...]] = field(default_factory=list)
    flagged: list[str] = field(default_factory=list)

    def keeps(self) -> Column:
        """The ordered conditional expression: the first rule that holds rejects, else the document is kept."""
        out = None
        for rule in self.rules:
            test = _all(rule)
            out = F.when(test, False) if out is None else out.when(test, False)
        return F.lit(True) if out is None else out.otherwise(True)

    def __str__(self) -> str:
        return "\n".join(["reject if " + " and ".join(map(str, r)) for r in self.rules] + ["else keep"])


def _all(rule: tuple[Condition, ...]) -> Column:
    test = F.lit(True)
    for c in rule:
        test = test & c.column()
    return test


def labelled_sample(docs: DataFrame, labels: DataFrame, sample_rows: int) -> DataFrame:
    """``doc_id``, ``text``, ``bad``, ``toxic`` of at most sample_rows labelled documents."""
    known = labels.where("doc_id is not null and (quality is not null or toxic is not null)")
    bad = F.greatest((F.coalesce(F.col("quality"), F.lit(1)) == 0).cast("int"), (F.coalesce(F.col("toxic"), F.lit(0)) == 1).cast("int"))
    each = known.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(bad).alias("bad"), F.max((F.coalesce(F.col("toxic"), F.lit(0)) == 1).cast("int")).alias("toxic"))
    chosen = each.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    text = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"))
    return text.join(F.broadcast(chosen), "doc_id")  # bounded by sample_rows


def flagged_words(sample: DataFrame, max_words: int = 200, least_docs: int = 8, purity: float = 0.85) -> list[str]:
    """Words, or first five letters of words, that hardly occur but in toxic documents."""
    words = computed(sample.select("doc_id", "toxic", "text"), F.array_distinct(F.transform(F.split(F.coalesce("text", F.lit("")), r"[\x20\x09-\x0D]+"), _plain)).alias("w"))
    both = F.array_distinct(F.flatten(F.transform("w", lambda w: F.array(w, F.substring(w, 1, 5)))))
    terms = words.select("toxic", F.explode(both).alias("w"))
    counts = terms.where(F.length("w") >= 4).groupBy("w").agg(F.count("*").alias("n"), F.sum("toxic").alias("t"))
    found = counts.where((F.col("t") >= least_docs) & (F.col("t") / (F.col("n") + 1) >= purity)).orderBy(F.desc("t"), "w").limit(max_words)
    return sorted(r["w"] for r in found.collect())


def learn(docs: DataFrame, labels: DataFrame, sample_rows: int = 20_000, max_rules: int = 12, max_conditions: int = 3, bins: int = 64, min_precision: float = 0.9, max_words: int = 200) -> DecisionList:
    """Fit a decision list that rejects documents of quality 0 or toxic ones.

    The words, the cuts and the rules come from two thirds of the sample; the held-out third only
    prunes a rule and says whether it is taken.
    """
    held = F.pmod(F.xxhash64("doc_id"), F.lit(3)) == 0
    sample = checkpoint(labelled_sample(docs, labels, sample_rows).withColumn("held_out", held))
    found = DecisionList(flagged=flagged_words(sample.where("not held_out"), max_words))
    stats = text_statistics(sample, found.flagged, keep=("bad", "held_out")).where(~base_failed())
    rows = stats.select("bad", "held_out", *FEATURES).collect()  # at most sample_rows
    found.rules = cover([(r[0], r[2:]) for r in rows if not r[1]], [(r[0], r[2:]) for r in rows if r[1]], max_rules, max_conditions, bins, min_precision)
    return found


Row = tuple[int, tuple[float, ...]]


def candidate_cuts(grow: list[Row], bins: int) -> list[list[float]]:
    """For each feature the values at even shares of the good and of the bad rows (for flagged words also 1)."""
    out = []
    for i, f in enumerate(FEATURES):
        cuts = {1.0} if f == "flagged_words" else set()
        for kind in (0, 1):
            values = sorted(x[i] for bad, x in grow if bad == kind)
            cuts |= {values[min(len(values) - 1, len(values) * j // bins)] for j in range(1, bins)} if values else set()
        out.append(sorted(cuts))
    return out


def cover(grow: list[Row], held: list[Row], max_rules: int = 12, max_conditions: int = 3, bins: int = 64, min_precision: float = 0.9) -> list[tuple[Condition, ...]]:
    """Sequential covering of the bad rows: grow a rule, prune it on the held-out rows, take it if it is precise there, go on without its rows."""
    total = sum(bad for bad, _ in grow)
    if not total or total == len(grow):
        return []
    cuts, least, rules = candidate_cuts(grow, bins), max(3, total // 500), []
    for _ in range(max_rules):
        rule = _grow(grow, cuts, max_conditions, least)
        if not rule:
            break
        rule = _tightest(_prune(held, rule))
        hits = [bad for bad, x in held if _holds(rule, x)]
        mine = [bad for bad, x in grow if _holds(rule, x)]
        if min(sum(hits) - min_precision * len(hits), sum(mine) - min_precision * len(mine)) < 0 or sum(hits) < max(1, least // 2):
            break
        rules.append(rule)
        grow, held = [r for r in grow if not _holds(rule, r[1])], [r for r in held if not _holds(rule, r[1])]
    return rules


def _holds(rule: tuple[Condition, ...], x: tuple[float, ...]) -> bool:
    return all((x[FEATURES.index(c.feature)] >= c.cut) == c.above for c in rule)


def gain(p: int, q: int, pos: int, neg: int) -> float:
    """What a condition that keeps p of pos bad and q of neg good rows tells, weighted by p."""
    return p * (math.log2((p + 0.01) / (p + q + 0.01)) - math.log2(pos / (pos + neg)))


def _grow(rows: list[Row], cuts: list[list[float]], max_conditions: int, least: int) -> tuple[Condition, ...]:
    rule: list[Condition] = []
    for _ in range(max_conditions):
        pos = sum(bad for bad, _ in rows)
        neg = len(rows) - pos
        if not pos or not neg:
            break
        best = None
        for i, f in enumerate(FEATURES):
            per = Counter((bisect_right(cuts[i], x[i]), bad) for bad, x in rows)
            p = q = 0
            for k in range(len(cuts[i]), 0, -1):  # at or above cut k-1
                p, q = p + per[k, 1], q + per[k, 0]
                for above, x, y in ((True, p, q), (False, pos - p, neg - q)):
                    if x >= least and (best is None or gain(x, y, pos, neg) > best[0] + 1e-9):
                        best = (gain(x, y, pos, neg), Condition(f, above, float(cuts[i][k - 1])), y)
        if best is None or best[0] <= 0:
            break
        rule.append(best[1])
        rows = [r for r in rows if _holds((best[1],), r[1])]
        if best[2] == 0:
            break
    return tuple(rule)


def _tightest(rule: tuple[Condition, ...]) -> tuple[Condition, ...]:
    """Of conditions on one side of one feature only the tightest."""
    best: dict[tuple[str, bool], Condition] = {}
    for c in rule:
        old = best.get((c.feature, c.above))
        if old is None or (c.cut > old.cut if c.above else c.cut < old.cut):
            best[c.feature, c.above] = c
    return tuple(best.values())


def _prune(held: list[Row], rule: tuple[Condition, ...]) -> tuple[Condition, ...]:
    """Drop last conditions while that raises (hits - misses) / (hits + misses) on the held-out rows."""
    heads = [rule[:i] for i in range(1, len(rule) + 1)]

    def value(head):
        hits = [bad for bad, x in held if _holds(head, x)]
        return (2 * sum(hits) - len(hits)) / max(1, len(hits))

    return max(heads, key=lambda h: (value(h), len(h)))


def judge(docs: DataFrame, model: DecisionList, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id``, BASE, ``base_failed``, ``kept`` for every document."""
    stats = text_statistics(docs, model.flagged, id_col, text_col)
    return stats.withColumn("base_failed", base_failed()).select("doc_id", *BASE, "base_failed", (~F.col("base_failed") & model.keeps()).alias("kept"), "flagged_words")


def kept_documents(docs: DataFrame, model: DecisionList) -> DataFrame:
    """The rows of docs that are kept, with docs' own columns."""
    names = docs.columns
    inner = {c: f"_in_{i}" for i, c in enumerate(names)}
    renamed = docs.select(*[F.col(quoted(c)).alias(inner[c]) for c in names])
    stats = text_statistics(renamed, model.flagged, inner["doc_id"], inner["text"], keep=tuple(inner.values()))
    return stats.where(~base_failed() & model.keeps()).select(*[F.col(inner[c]).alias(c) for c in names])
