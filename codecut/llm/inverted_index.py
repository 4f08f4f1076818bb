"""Distributed positional inverted index for benchmark decontamination, in DataFrame functions only.

Texts are lower-cased (A to Z) and cut into words: runs of digits, ASCII letters and non-ASCII characters.
``build_index`` does that once and writes, in the shared folder, the words of each document by position, in blocks of
``block`` words that also hold the ``overlap`` words after them. All lists are read from there: document frequencies of test terms,
``postings`` (document, position) of terms, and the words that a match is held against. A phrase's lists are intersected
from its rarest terms on, by start position (position less the term's offset in the phrase);
what is left is compared word by word with its block, so that phrase matches are exact. Proximity
matches follow the lists of an item's rarest terms, ordered by position.

Scale: no row holds more than a block, however long a text is, and texts are not shuffled whole: all blocks are, once,
to meet their candidates, and the lists of the probing terms. Frequencies combine before the shuffle. What comes of the phrases (a benchmark) is the small side: it is
broadcast only after its rows and bytes are counted, and joined by shuffle beyond that. A
term that a third of the documents hold is no phrase's probe unless all its terms are as common; its
list is then spread by document and start, not by term.

Edge cases: null text and text without words match nothing (n_words 0); an item with fewer words than a window is one window, without any
word none; a null item id counts as an item with an empty name; documents are told apart by a number that they get when the
index is written, so repeated rows and ids are each reported; items count once per item id; empty tables give no hits.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import checkpoint, materialize
from .common import ascii_lower, boxed, computed, unboxed

_GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(ascii_lower(F.coalesce(text.cast("string"), F.lit(""))), _GAP), "")


@dataclass(frozen=True)
class PositionalIndex:
    """Stored words by position: ``doc, doc_id, text_hash, n_words, at, words``; words, joined by spaces (which no word holds), begin at position ``at``."""

    blocks: DataFrame
    block: int
    overlap: int

    def documents(self) -> DataFrame:
        """``doc, doc_id, text_hash, n_words`` of every document."""
        return self.blocks.where("at = 0").select("doc", "doc_id", "text_hash", "n_words")

    def postings(self, terms: DataFrame | None = None, broadcast_rows: int = 1_000_000) -> DataFrame:
        """``doc``, ``n_words``, ``term``, ``pos`` (from 0) of all words, or of those in terms(term, ...)."""
        each = self.blocks.where("n_words > 0").select("doc", "n_words", "at", F.posexplode(F.split("words", " ")).alias("i", "term")).where(F.col("i") < self.block)
        each = each.select("doc", "n_words", "term", (F.col("at") + F.col("i")).alias("pos"))
        return each if terms is None else each.join(_small(terms, broadcast_rows), "term")


def build_index(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block: int = 1024, overlap: int = 63) -> PositionalIndex:
    """Tokenize docs once and store the index; phrases of up to overlap + 1 words can be asked of it."""
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text"))
    numbered = rows.select(F.monotonically_increasing_id().alias("doc"), "doc_id", F.xxhash64("text").alias("text_hash"), "text")
    tokens = computed(numbered, words_of(F.col("text")).alias("w"))
    starts = F.sequence(F.lit(0), F.greatest(F.size("w") - 1, F.lit(0)), F.lit(block))
    blocks = tokens.select("doc", "doc_id", "text_hash", F.size("w").cast("long").alias("n_words"), "w", F.explode(starts).alias("at"))
    stored = blocks.select("doc", "doc_id", "text_hash", "n_words", "at", F.array_join(F.slice("w", F.col("at") + 1, block + overlap), " ").alias("words"))
    return PositionalIndex(materialize(stored, "positional-index"), block, overlap)


def _small(df: DataFrame, broadcast_rows: int, broadcast_bytes: int = 64 << 20) -> DataFrame:
    """df (stored, so that counting is cheap) with a broadcast hint if it has at most so many rows and bytes."""
    size = F.sum(F.octet_length(F.to_json(F.struct(*df.columns))))
    n, held = df.limit(broadcast_rows + 1).agg(F.count("*"), F.coalesce(size, F.lit(0))).first()
    return F.broadcast(df) if n <= broadcast_rows and held <= broadcast_bytes else df


def phrase_windows(items: DataFrame, width: int, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """``item_id`` (string), ``words`` of every window of width words; a shorter item is one window."""
    item = computed(items.select(F.coalesce(items[id_col].cast("string"), F.lit("")).alias("item_id"), items[text_col].alias("text")), words_of(F.col("text")).alias("w")).where(F.size("w") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.size("w") - width + 1, F.lit(1)))
    return item.select("item_id", "w", F.explode(starts).alias("s")).select("item_id", F.slice("w", F.col("s"), width).alias("words")).distinct()


def term_frequencies(index: PositionalIndex, terms: DataFrame, broadcast_rows: int = 1_000_000) -> DataFrame:
    """``term``, ``df`` (its occurrences in all documents) of the distinct terms(term) that occur; stored."""
    vocabulary = checkpoint(terms.select("term").distinct())
    # counted in every task, then summed
    return checkpoint(index.postings(vocabulary, broadcast_rows).groupBy("term").agg(F.count("*").alias("df")))


def probes(phrases: DataFrame, frequencies: DataFrame, n: int, broadcast_rows: int = 1_000_000) -> DataFrame:
    """The n rarest (term, offset) of each phrase(pid, words); ties by place."""
    terms = phrases.select("pid", F.size("words").alias("len"), F.posexplode("words").alias("off", "term"))
    order = Window.partitionBy("pid").orderBy(F.coalesce("df", F.lit(0)), "off")
    # a common term is in many phrases: the frequencies go to the terms, not the terms to one task
    ranked = terms.join(_small(frequencies, broadcast_rows), "term", "left").withColumn("rank", F.row_number().over(order))
    return ranked.where(F.col("rank") <= n).select("pid", "len", "term", "off", F.least("len", F.lit(n)).alias("need"))


def phrase_matches(index: PositionalIndex, phrases: DataFrame, n_probes: int = 2, broadcast_rows: int = 1_000_000) -> DataFrame:
    """``doc``, ``start``, ``pid``, ``len`` of all exact occurrences of phrases(pid, words); pid tells phrases apart."""
    longest = phrases.agg(F.max(F.size("words"))).first()[0] or 0
    if longest > index.overlap + 1:
        raise ValueError(f"this index answers phrases of up to {index.overlap + 1} words, not {longest}")
    frequencies = term_frequencies(index, phrases.select(F.explode("words").alias("term")), broadcast_rows)
    probe = checkpoint(probes(phrases, frequencies, n_probes, broadcast_rows))
    start = F.col("pos") - F.col("off")
    lists = index.postings(probe, broadcast_rows).where((start >= 0) & (start + F.col("len") <= F.col("n_words")))
    starts = lists.groupBy("doc", start.alias("start"), "pid").agg(F.count("*").alias("n"), F.first("need").alias("need")).where("n = need")
    at = (F.col("start") - F.col("start") % index.block).alias("at")
    wanted = starts.join(_small(phrases, broadcast_rows), "pid").groupBy("doc", at).agg(F.collect_list(F.struct("start", "pid", F.col("words").alias("want"))).alias("maybe"))
    both = computed(index.blocks.select("doc", "at", "words").join(wanted, ["doc", "at"]), F.split("words", " ").alias("w"))
    exact = F.filter("maybe", lambda m: F.slice("w", m["start"] - F.col("at") + 1, F.size(m["want"])) == m["want"])
    return both.select("doc", F.inline(F.transform(exact, lambda m: F.struct(m["start"].alias("start"), m["pid"].alias("pid"), F.size(m["want"]).alias("len")))))


def proximity_matches(index: PositionalIndex, groups: DataFrame, slop: int, broadcast_rows: int = 1_000_000) -> DataFrame:
    """Spans of at most ``slop`` words that hold all terms of a group, in any order: ``doc``, ``gid``, ``start``, ``end``.

    groups: ``gid``, ``terms`` (distinct). Each span ends at a posting and starts at the latest one that completes it. A
    document's lists of a group are walked in one window ordered by position, so cost follows the postings.
    """
    each = checkpoint(groups.select("gid", F.size("terms").alias("need"), F.posexplode("terms").alias("which", "term")))
    lists = index.postings(each, broadcast_rows).select("doc", "gid", "need", "which", "pos")
    most = each.agg(F.max("need")).first()[0] or 1
    before = Window.partitionBy("doc", "gid").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    last = F.array(*[F.max(F.when(F.col("which") == i, F.col("pos"))).over(before) for i in range(most)])
    seen = lists.select("doc", "gid", "need", "pos", last.alias("last")).withColumn("last", F.slice("last", F.lit(1), F.col("need")))
    whole = seen.where(~F.exists("last", lambda x: x.isNull())).select("doc", "gid", F.array_min("last").alias("start"), F.col("pos").alias("end"))
    return whole.where(F.col("end") - F.col("start") < slop)


def near_items(docs: DataFrame, items: DataFrame, n_terms: int = 4, slop: int = 16, broadcast_rows: int = 1_000_000) -> DataFrame:
    """``doc, doc_id, item_id, n_spans, first_start``: documents that hold the n_terms rarest distinct terms of an item (all, if it
    has fewer; ties by term) within slop words. Repeated rows of an item are one item with the words of all."""
    index = build_index(docs)
    words = items.select(F.coalesce(items["item_id"].cast("string"), F.lit("")).alias("gid"), words_of(items["text"]).alias("w"))
    terms = checkpoint(words.select("gid", F.explode("w").alias("term")).distinct())
    ranked = terms.join(_small(term_frequencies(index, terms, broadcast_rows), broadcast_rows), "term", "left")
    ranked = ranked.withColumn("rank", F.row_number().over(Window.partitionBy("gid").orderBy(F.coalesce("df", F.lit(0)), "term")))
    groups = ranked.where(F.col("rank") <= n_terms).groupBy("gid").agg(F.collect_list("term").alias("terms"))
    spans = proximity_matches(index, groups, slop, broadcast_rows).groupBy("doc", "gid").agg(F.count("*").alias("n_spans"), F.min("start").alias("first_start"))
    return spans.join(index.documents(), "doc").select("doc", "doc_id", F.col("gid").alias("item_id"), "n_spans", "first_start")


def decontaminate(docs: DataFrame, items: DataFrame, width: int = 10, id_col: str = "doc_id", text_col: str = "text", broadcast_rows: int = 1_000_000, block: int = 1024) -> DataFrame:
    """One row a document: ``doc_id, text_hash, n_words, n_hit, n_items, items, contaminated``; items is the sorted list of ids."""
    windows = phrase_windows(items, width).groupBy("words").agg(F.sort_array(F.collect_set("item_id")).alias("ids"))
    phrases = checkpoint(windows.select(F.monotonically_increasing_id().alias("pid"), "words", "ids"))
    index = build_index(docs, id_col, text_col, block, width - 1)
    found = checkpoint(phrase_matches(index, phrases.select("pid", "words"), broadcast_rows=broadcast_rows))
    covered = found.select("doc", F.explode(F.sequence(F.col("start"), F.col("start") + F.col("len") - 1)).alias("pos")).distinct()
    hit = covered.groupBy("doc").agg(F.count("*").alias("n_hit"))
    named = found.select("doc", "pid").distinct().join(_small(phrases.select("pid", "ids"), broadcast_rows), "pid")
    listed = named.groupBy("doc").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))).alias("items"))
    out = index.documents().join(hit.join(listed, "doc"), "doc", "left")
    n_hit, names = F.coalesce("n_hit", F.lit(0).cast("long")), F.coalesce("items", F.array().cast("array<string>"))
    return out.select("doc_id", "text_hash", "n_words", n_hit.alias("n_hit"), F.size(names).cast("long").alias("n_items"), names.alias("items"), (n_hit > 0).alias("contaminated"))


def clean_documents(docs: DataFrame, items: DataFrame, width: int = 10) -> DataFrame:
    """The rows of docs without any occurrence of a window of the items."""
    hit = decontaminate(docs, items, width).where("contaminated").select("doc_id", "text_hash").distinct()
    keyed = boxed(docs).select("row", F.col("row.doc_id").cast("long").alias("k"), F.xxhash64(F.col("row.text").cast("string")).alias("h"))
    return unboxed(keyed.join(hit, F.col("k").eqNullSafe(F.col("doc_id")) & (F.col("h") == F.col("text_hash")), "left_anti"), docs)
