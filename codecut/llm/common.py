"""What the text operators share."""

from __future__ import annotations

import ctypes
import gc
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def id_and_text(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the two columns that count, so that no other column can clash; null text is empty."""
    return docs.select(docs[id_col].cast("long").alias("doc_id"), F.coalesce(docs[text_col].cast("string"), F.lit("")).alias("text"))


def boxed(df: DataFrame) -> DataFrame:
    """All columns in one column ``row``, so that no name of theirs can clash with what a stage adds."""
    return df.select(F.struct(*[F.col(quoted(c)) for c in df.columns]).alias("row"))


def unboxed(df: DataFrame, like: DataFrame) -> DataFrame:
    """The columns of ``row``, as ``like`` has them."""
    return df.select(*[F.col(f"row.{quoted(c)}").alias(c) for c in like.columns])


def quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"


def ascii_lower(text: Column) -> Column:
    """Lower-case A to Z and nothing else."""
    return F.translate(text, UPPER, LOWER)


def computed(df: DataFrame, *columns: Column) -> DataFrame:
    """df with more columns, each computed once a row.

    A plain projection may be merged into the next one, and then a lambda there
    evaluates the whole expression for every element; a generator is not merged.
    """
    return df.select("*", F.inline(F.array(F.struct(*columns))))


@contextmanager
def no_collector():
    """Without the cycle collector, for code that makes many containers and no cycles."""
    on = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        if on:
            gc.enable()


def released(run):
    """A batch function that gives freed memory back to the system when its task ends: workers wait for other tasks with what they hold."""

    def wrapped(batches):
        import pyarrow as pa

        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):  # another C library
                pass

    return wrapped
