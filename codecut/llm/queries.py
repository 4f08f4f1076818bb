"""Registered queries of the text operators, and their SQL where SQL can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import read_table


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decision_list import judge, learn

    docs = read_table(spark, sf_dir, "documents")
    return judge(docs, learn(docs, read_table(spark, sf_dir, "labels"))).drop("flagged_words")


def quality_base_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decision_list import BASE, base_failed, text_statistics

    return text_statistics(read_table(spark, sf_dir, "documents")).select("doc_id", *BASE, base_failed().alias("base_failed"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .simhash import fingerprint_hex, near_duplicates

    return near_duplicates(read_table(spark, sf_dir, "documents")).select("doc_id", fingerprint_hex(F.col("fp")).alias("fingerprint"), "component_id")


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .inverted_index import decontaminate

    found = decontaminate(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")


def benchmark_proximity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that hold the four rarest words of a benchmark item within sixteen words."""
    from .inverted_index import near_items

    return near_items(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark")).drop("doc")


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .sharding import even_tree, grow, shard_documents

    tree = even_tree(16)
    placed = shard_documents(read_table(spark, sf_dir, "documents"), tree, grow(tree, 16))
    return placed.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_family import remove_repeats

    return remove_repeats(read_table(spark, sf_dir, "documents")).withColumnRenamed("kept", "kept_sha256")


def _tokenizer(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op2_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_store import read_tokens, write_tokens

    return read_tokens(write_tokens(read_table(spark, sf_dir, "documents"), _tokenizer("byte_bpe_50k.json"), end_id=2))


def op3_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .chat_format import written_digests

    turns = read_table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
    said = "\\### Assistant: </turn> ok"
    more = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    return written_digests(turns.select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text").union(more))


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .empirical_bayes import classify

    return classify(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op6_trie_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .trie_bpe import encoded_digests

    return encoded_digests(read_table(spark, sf_dir, "documents"), _tokenizer("word_bpe_49k.json"))


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..session import checkpoint
    from .length_histogram import length_histogram, token_counts, with_suffix_sums

    return with_suffix_sums(checkpoint(length_histogram(token_counts(read_table(spark, sf_dir, "documents"), _tokenizer("byte_bpe_50k.json")))))


def shard_placement(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op10 without the checksum, which the other engine lacks."""
    return op10_sharding(spark, sf_dir).drop("text_crc32")


QUERIES = {
    q.__name__: q
    for q in (
        op1_suffix_dedup, op2_token_files, op3_chat_format, op4_quality_classifier, op5_quality_rules, op6_trie_bpe,
        op7_simhash, op8_decontamination, op9_token_counts, op10_sharding, quality_base_statistics, shard_placement, benchmark_proximity,
    )
}

_WORDS = r"list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '')"
_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_TERMS = rf"regexp_extract_all({_LOWER}, '[0-9a-z\x{{80}}-\x{{10FFFF}}]+')"

_BASE_SQL = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, {_WORDS} AS w FROM documents),
l AS (SELECT doc_id, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d),
g AS (SELECT doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM d)),
r AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS j FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM g) WHERE c > 1) GROUP BY doc_id),
s AS (SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
  CAST(len(regexp_extract_all(text, '[#*$%&|<>]')) AS BIGINT) AS n_symbols, CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, coalesce(r.n, 0) AS n_repeat_words
  FROM d JOIN l USING (doc_id) LEFT JOIN r USING (doc_id))
SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM s"""

_CHAT_SQL = """
WITH t AS (SELECT CAST(conv_id AS BIGINT) AS conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\\### Assistant: </turn> ok')
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(17 + length(replace(replace(replace(role, '\\', '\\\\'), '<|', '<\\|'), '|>', '|\\>')) + length(replace(replace(replace(text, '\\', '\\\\'), '<|', '<\\|'), '|>', '|\\>'))) AS BIGINT) AS formatted_chars
FROM t GROUP BY conv_id"""

_LEAK_SQL = f"""
WITH d AS (SELECT doc_id, {_TERMS} AS w FROM documents), b AS (SELECT CAST(item_id AS VARCHAR) AS item_id, {_TERMS} AS w FROM benchmark),
v AS (SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(w[s:s + least(len(w), 10) - 1], ' ') AS g FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS s FROM b WHERE len(w) > 0)),
k AS (SELECT DISTINCT n FROM v), x AS (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS s FROM d, k),
m AS (SELECT doc_id, s, x.n, item_id FROM x JOIN v ON v.n = x.n AND v.g = array_to_string(w[s:s + x.n - 1], ' ')),
h AS (SELECT doc_id, count(DISTINCT j) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS j FROM m) GROUP BY doc_id),
i AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT doc_id, item_id FROM m) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN i USING (doc_id)"""


_NEAR_SQL = f"""
WITH d AS (SELECT row_number() OVER () AS doc, doc_id, {_TERMS} AS w FROM documents), b AS (SELECT DISTINCT CAST(item_id AS VARCHAR) AS item_id, unnest({_TERMS}) AS term FROM benchmark),
p AS (SELECT doc, doc_id, unnest(w) AS term, unnest(range(len(w))) AS pos FROM d), f AS (SELECT term, count(*) AS df FROM p GROUP BY term),
r AS (SELECT item_id, term, row_number() OVER (PARTITION BY item_id ORDER BY coalesce(df, 0), term) AS k FROM b LEFT JOIN f USING (term) QUALIFY k <= 4),
n AS (SELECT item_id, count(*) AS need FROM r GROUP BY item_id),
l AS (SELECT doc, doc_id, item_id, term, pos FROM p JOIN r USING (term)),
s AS (SELECT e.doc, e.doc_id, e.item_id, e.pos, o.term, max(o.pos) AS last FROM l e JOIN l o ON e.doc = o.doc AND e.item_id = o.item_id AND o.pos <= e.pos AND o.pos > e.pos - 16 GROUP BY ALL),
x AS (SELECT doc, doc_id, item_id, pos, min(last) AS start, count(*) AS held FROM s GROUP BY ALL)
SELECT doc_id, item_id, count(*) AS n_spans, CAST(min(start) AS INTEGER) AS first_start FROM x JOIN n USING (item_id) WHERE held = need GROUP BY doc, doc_id, item_id"""


def _place_sql(node) -> str:
    if not node.children:
        return str(node.shard)
    if len(node.children) == 1:
        return _place_sql(node.children[0])
    draw = lambda c: f"(-ln((CAST('0x' || substr(md5(k || '|{c.name}'), 1, 12) AS BIGINT) + 0.5) / 281474976710656.0::DOUBLE) / {c.weight})"
    draws = [draw(c) for c in node.children]
    cases = [f"WHEN list_position([{', '.join(draws)}], list_min([{', '.join(draws)}])) = {i + 1} THEN {_place_sql(c)}" for i, c in enumerate(node.children)]
    return f"CASE {' '.join(cases)} END"


def _shard_sql() -> str:
    from .sharding import even_tree, grow

    tree = even_tree(16)
    return f"""
WITH r AS (SELECT doc_id, coalesce(CAST(doc_id AS VARCHAR), 'null') AS k, CAST(strlen(coalesce(text, '')) + 1 AS BIGINT) AS size FROM documents),
p AS (SELECT doc_id, size, CAST({_place_sql(tree)} AS INTEGER) AS shard, CAST({_place_sql(grow(tree, 16))} AS INTEGER) AS grown_shard,
  CAST('0x' || substr(md5(k || '|bin'), 1, 8) AS BIGINT) % 1024 AS bin FROM r)
SELECT doc_id, size, 'key' AS law, shard, row_number() OVER (PARTITION BY shard ORDER BY bin, doc_id) - 1 AS slot, grown_shard FROM p"""


ORACLE_SQL: dict[str, str] = {
    "benchmark_proximity": _NEAR_SQL,
    "op3_chat_format": _CHAT_SQL,
    "op8_decontamination": _LEAK_SQL,
    "quality_base_statistics": _BASE_SQL,
    "shard_placement": _shard_sql(),
}
