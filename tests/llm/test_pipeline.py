"""All stages of the pipeline against plain recomputation, on a table of odd rows with clashing columns."""

from collections import Counter

import public_tokenizers
import pytest
import xxhash

import corpus_pipeline
from codecut.llm import decision_list, inverted_index, simhash, suffix_family
from codecut.llm.simhash import run_hashes

from test_learning import verdict
from test_operators import PASSAGE, ODD

CLASH = ["_k", "_h", "_t", "_id", "_x", "_key", "_hash", "_kept", "k", "h", "t", "fp", "row", "new", "part", "doc_id`s"]
SHAPE = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c.replace('`', '``')}` string" for c in CLASH)


def signed(text):
    x = xxhash.xxh64_intdigest((text or "").encode(), 42)
    return x - (1 << 64) if x >> 63 else x


def whole(rows):
    return Counter(tuple(r) for r in rows)


@pytest.fixture(scope="module")
def items(spark, sf):
    return [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]


@pytest.fixture(scope="module")
def folder(spark, sf, items, tmp_path_factory):
    out = str(tmp_path_factory.mktemp("stages"))
    texts = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    told = lambda tag: " ".join(f"{tag}{i} word{i * 7 % 900} of {i * i % 1300} more" for i in range(300))
    texts += [(20_000 + (i or 0) if i is not None else None, t) for i, t in ODD]
    texts += [(30_000, told("a")), (30_001, told("a")), (30_002, told("a").replace("a7 ", "other ")), (30_003, told("b") + " " + PASSAGE), (30_003, told("c") + " " + PASSAGE)]
    texts += [(30_003, told("c") + " " + PASSAGE), (None, told("d")), (None, told("d")), (30_004, told("e") + " " + items[0][1] + " " + told("f"))]
    texts += [(30_005, "".join(f"long{i * i % 99991} text{i} " for i in range(70_000)) + told("g") + PASSAGE)]  # over a MiB
    rows = [(i, t, "en", "s", None if t is None else len(t), *[f"{c}{n}" for c in CLASH]) for n, (i, t) in enumerate(texts)]
    rows += rows[-8:-5]  # rows that repeat in all columns
    spark.createDataFrame(rows, SHAPE).repartition(5).write.parquet(f"{out}/documents.parquet")
    for t in ("benchmark", "labels"):
        spark.read.parquet(f"{sf}/{t}.parquet").write.parquet(f"{out}/{t}.parquet")
    return out


def plain_rules(rows, model):
    return [r for r in rows if verdict(r["text"], model)]


def plain_one_of_each(rows):
    sets = [frozenset(run_hashes((r["text"] or "").encode(), 5)) for r in rows]
    parent = list(range(len(rows)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    holders = {}
    for i, s in enumerate(sets):
        for x in s or {None}:
            holders.setdefault(x, []).append(i)
    seen = set()
    for of in holders.values():
        for a in of:
            for b in of:
                if a < b and (a, b) not in seen:
                    seen.add((a, b))
                    if sets[a] == sets[b] or 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                        parent[root(a)] = root(b)
    best = {}
    for i, r in enumerate(rows):
        place = (r["doc_id"] is None, r["doc_id"] or 0, signed(r["text"]))
        if root(i) not in best or place < best[root(i)][0]:
            best[root(i)] = (place, r)
    return [r for _, r in best.values()]


def plain_without_repeats(rows, width=100):
    """Rows that repeat (id and text) are judged once, and all get that result."""
    seen, left = set(), {}
    for i, t in sorted({(r["doc_id"], r["text"] or "") for r in rows}, key=lambda x: (x[0] is not None, x[0] or 0, signed(x[1]))):
        b = t.encode()
        gone = bytearray(len(b))
        for p in range(len(b) - width + 1):
            w = hash(b[p : p + width])
            if w in seen:
                gone[p : p + width] = b"\1" * width
            else:
                seen.add(w)
        if any(gone):
            left[i, t] = bytes(x for x, g in zip(b, gone) if not g).decode("utf-8", "ignore")
    out = []
    for r in rows:
        text = left.get((r["doc_id"], r["text"] or ""))
        out.append(tuple(r) if text is None else tuple(text if c == "text" else len(text) if c == "n_chars" else r[c] for c in r.__fields__))
    return Counter(out)


def words(text):
    import re

    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate({c: c + 32 for c in range(65, 91)}))


def plain_clean(rows, items):
    windows = set()
    for _, t in items:
        w = words(t)
        windows |= {tuple(w[i : i + 10]) for i in range(max(1, len(w) - 9))} if w else set()
    sizes = {len(w) for w in windows}
    hit = lambda w: any(tuple(w[i : i + n]) in windows for n in sizes for i in range(len(w) - n + 1))
    return [r for r in rows if not hit(words(r["text"]))]


def test_stages(spark, folder, items):
    from tokenizers import Tokenizer

    docs = spark.read.parquet(f"{folder}/documents.parquet")
    labels = spark.read.parquet(f"{folder}/labels.parquet")
    rows = docs.collect()
    names = docs.columns
    at = lambda i: corpus_pipeline.STAGES[i][1]

    one = at(0)(spark, docs, folder)
    assert one.columns == names
    want = plain_rules(rows, decision_list.learn(docs, labels))
    assert whole(one.collect()) == whole(want) and 20 < len(want) < len(rows)

    two = at(1)(spark, one, folder)
    assert two.columns == names
    left = plain_one_of_each(want)
    got = two.collect()
    # of rows with equal id and text any may stand for them
    cut = lambda rs: Counter((r["doc_id"], r["text"]) for r in rs)
    assert cut(got) == cut(left) and len(left) < len(want) and not whole(got) - whole(want)

    two = spark.createDataFrame(got, docs.schema).repartition(3)
    three = at(2)(spark, two, folder)
    assert three.columns == names
    assert whole(three.collect()) == plain_without_repeats(got)
    assert any(r["text"] != t for r, t in zip(sorted(three.collect(), key=str), sorted(t["text"] for t in got)))

    got = three.collect()
    three = spark.createDataFrame(got, docs.schema)
    four = at(3)(spark, three, folder)
    assert four.columns == names
    assert whole(four.collect()) == whole(plain_clean(got, items))

    got = four.collect()
    library = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    library.no_truncation()
    library.no_padding()
    want = Counter()
    for r in got:
        ids = library.encode(r["text"] or "", add_special_tokens=False).ids
        want[r["doc_id"], tuple(ids), library.decode(ids, skip_special_tokens=False)] += 1
    five = at(4)(spark, spark.createDataFrame(got, docs.schema), folder).collect()
    assert Counter((r["doc_id"], tuple(r["ids"]), r["decoded"]) for r in five) == want


def test_stages_on_every_odd_row(spark, folder, items):
    """Later stages also see the rows that the first one rejects."""
    docs = spark.read.parquet(f"{folder}/documents.parquet").where("length(text) < 100000 or text is null")
    rows = docs.collect()
    assert whole(suffix_family.without_repeats(docs).collect()) == plain_without_repeats(rows)
    extra = spark.createDataFrame([(None, "nothing"), (901, None), (902, "..."), (903, "a b c")], "item_id long, text string")
    more = spark.read.parquet(f"{folder}/benchmark.parquet").select("item_id", "text").union(extra)
    assert whole(inverted_index.clean_documents(docs, more).collect()) == whole(plain_clean(rows, items + [tuple(r) for r in extra.collect()]))
    kept = corpus_pipeline.near_duplicates(spark, docs, folder).collect()
    assert Counter((r["doc_id"], r["text"]) for r in kept) == Counter((r["doc_id"], r["text"]) for r in plain_one_of_each(rows))
    by_bits = simhash.one_of_each(docs, simhash.near_duplicates(docs)).collect()
    assert len({r["text"] for r in by_bits}) == len(by_bits) and not whole(by_bits) - whole(rows)


def test_empty_tables(spark, folder, tmp_path):
    for t in ("documents", "benchmark", "labels"):
        spark.read.parquet(f"{folder}/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    empty = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, empty, str(tmp_path))
        assert out.count() == 0, name
        if name != "tokens":
            assert out.columns == empty.columns
    full = spark.read.parquet(f"{folder}/documents.parquet").where("doc_id < 60")
    assert corpus_pipeline.quality_rules(spark, full, str(tmp_path)).count() <= full.count()
    assert corpus_pipeline.benchmark_passages(spark, full, str(tmp_path)).count() == full.count()


def test_run_is_the_stages_in_turn(spark, folder):
    out = corpus_pipeline.run(spark, folder)
    assert out.columns == ["doc_id", "ids", "decoded"]
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, folder)
    assert Counter((r["doc_id"], tuple(r["ids"])) for r in out.collect()) == Counter((r["doc_id"], tuple(r["ids"])) for r in docs.collect())
