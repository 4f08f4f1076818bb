"""The corpus pipeline: quality rules, near copies, repeated passages, benchmark passages, tokens.

Each stage takes (spark, docs, sf_dir); docs is what the stage before it kept, read
from Parquet. All but the last return the columns of documents.
"""

from __future__ import annotations

import public_tokenizers

from codecut.llm.decision_list import kept_documents, learn
from codecut.llm.inverted_index import clean_documents
from codecut.llm.set_join import similar_documents
from codecut.llm.simhash import one_of_each
from codecut.llm.suffix_family import without_repeats
from codecut.llm.trie_bpe import encode_documents
from codecut.session import checkpoint, materialize, read_table, ship_package

ORACLE_SQL = None


def quality_rules(spark, docs, sf_dir):
    """Documents that the base rule or the learned list rejects go."""
    return kept_documents(docs, learn(docs, read_table(ship_package(spark), sf_dir, "labels")))


def near_duplicates(spark, docs, sf_dir):
    """Of each group of near copies (Jaccard similarity of five-word runs of 0.8 or more; by fingerprints, then exactly) the document with the smallest id stays."""
    ship_package(spark)
    return one_of_each(docs, checkpoint(similar_documents(docs)))


def repeated_passages(spark, docs, sf_dir):
    """Passages that also start earlier are cut out of the texts."""
    ship_package(spark)
    return without_repeats(docs)


def benchmark_passages(spark, docs, sf_dir):
    """Documents that hold a window of a benchmark item go."""
    return clean_documents(docs, read_table(ship_package(spark), sf_dir, "benchmark"))


def tokens(spark, docs, sf_dir):
    """``doc_id, ids, decoded`` of each document left."""
    ship_package(spark)
    return encode_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("benchmark_passages", benchmark_passages),
    ("tokens", tokens),
]


def run(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialize(docs, name)
    return docs
