"""Token counts from an exact length histogram.

Documents are counted by encoded length (partial counts before the shuffle); from then
on everything works on the histogram, which has one row for each length that
occurs. Suffix sums give, for a context limit L: how many documents are longer, how
many tokens remain when each document is cut at L, and quantiles. Suffix sums are
taken in two steps, in buckets of lengths and over buckets, so no task takes the whole histogram.

Edge cases: null and empty texts have length 0; repeated rows count each; an empty
table gives an empty histogram.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import id_and_text
from .tokens import CachedEncoder


def _counter(path: str):
    def count(batches):
        encoder = CachedEncoder.of(path)
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(encoder.encode_column(part.column(1))[0], pa.int64())], names=["doc_id", "n_tokens"])

    return count


def token_counts(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    return id_and_text(docs, id_col, text_col).mapInArrow(_counter(path), "doc_id long, n_tokens long")


def length_histogram(counts: DataFrame, n_col: str = "n_tokens") -> DataFrame:
    return counts.groupBy(F.col(n_col).alias("n_tokens")).agg(F.count("*").alias("n_docs"))


def with_suffix_sums(histogram: DataFrame, bucket: int = 512) -> DataFrame:
    """Per length L that occurs, taken as a context limit.

    ``n_docs`` of this length, ``docs_longer`` than L, ``tokens_longer`` (of those), ``docs_total``,
    ``tokens_total``, ``tokens_kept`` (every document cut at L), ``tokens_cut``, ``share_whole`` (of documents that
    fit): the smallest L with share_whole >= q is the q-quantile of the lengths.
    """
    h = histogram.select("n_tokens", "n_docs", (F.col("n_tokens") * F.col("n_docs")).alias("t"), F.floor(F.col("n_tokens") / bucket).alias("b"))
    sums = h.groupBy("b").agg(F.sum("n_docs").alias("bn"), F.sum("t").alias("bt"))
    after = Window.partitionBy(F.lit(0)).orderBy(F.desc("b")).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy(F.lit(0))
    zero = lambda c: F.coalesce(c, F.lit(0))
    sums = sums.select("b", zero(F.sum("bn").over(after)).alias("an"), zero(F.sum("bt").over(after)).alias("at"), F.sum("bn").over(whole).alias("docs_total"), F.sum("bt").over(whole).alias("tokens_total"))
    inner = Window.partitionBy("b").orderBy(F.desc("n_tokens")).rowsBetween(Window.unboundedPreceding, -1)
    out = h.join(sums, "b").select("n_tokens", "n_docs", (F.col("an") + zero(F.sum("n_docs").over(inner))).alias("docs_longer"), (F.col("at") + zero(F.sum("t").over(inner))).alias("tokens_longer"), "docs_total", "tokens_total")
    cut = F.col("tokens_longer") - F.col("n_tokens") * F.col("docs_longer")
    return out.select("*", (F.col("tokens_total") - cut).alias("tokens_kept"), cut.alias("tokens_cut"), ((F.col("docs_total") - F.col("docs_longer")) / F.col("docs_total")).alias("share_whole"))


def at_limit(histogram: DataFrame, limits: list[int]) -> DataFrame:
    """``context_limit, docs_cut, tokens_kept`` for any limits (their number is small), straight from the histogram."""
    limit = histogram.select(F.explode(F.array(*[F.lit(x).cast("long") for x in limits])).alias("context_limit"), "n_tokens", "n_docs")
    return limit.groupBy("context_limit").agg(F.sum(F.when(F.col("n_tokens") > F.col("context_limit"), F.col("n_docs")).otherwise(0)).alias("docs_cut"), F.sum(F.least("n_tokens", "context_limit") * F.col("n_docs")).alias("tokens_kept"))


def quantiles(histogram: DataFrame, shares: list[float]) -> DataFrame:
    """``share, n_tokens``: the smallest length that at least this share of documents do not exceed."""
    sums = with_suffix_sums(histogram).select("n_tokens", (F.col("docs_total") - F.col("docs_longer")).alias("within"), "docs_total")
    each = sums.select(F.explode(F.array(*[F.lit(float(s)) for s in shares])).alias("share"), "n_tokens", "within", "docs_total")
    return each.where(F.col("within") >= F.col("share") * F.col("docs_total")).groupBy("share").agg(F.min("n_tokens").alias("n_tokens"))
