import hashlib
import re

import pytest
from pyspark.sql import functions as F

from redgraph.llm import decontamination as dec

WORD = re.compile("[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+")


def words(text):
    return WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))


def brute(docs, items, window=10):
    out = {}
    wins = [(i, tuple(w[j : j + min(window, len(w))])) for i, w in ((i, words(t)) for i, t in items) if w for j in range(len(w) - min(window, len(w)) + 1)]
    for d, t in docs:
        w, hit, found = words(t), set(), set()
        for i, g in wins:
            for p in range(len(w) - len(g) + 1):
                if tuple(w[p : p + len(g)]) == g:
                    hit |= set(range(p, p + len(g)))
                    found.add(str(i))
        out[d] = (len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest())
    return out


DOCS = [
    (1, "a b c d e f g h i j k l m n o p"), (2, "x A b C-d e, f g h i j y a b c d e f g h i j k"), (3, None), (4, ""), (5, "Tiny item here; tiny ITEM here"), (6, "é ü ß " * 9), (7, "q " * 3000 + "a b c d e f g h i j k l"),
    (8, "a a a a a a a a a a a a a a a"), (9, "!?"),
]
ITEMS = [(1, "a b c d e f g h i j k l"), (2, "tiny item here"), (3, None), (4, "..."), (5, "a a a a a a a a a a a"), (6, "é ü ß é ü ß é ü ß é ü ß"), (7, "a b c d e f g h i j k l"), (8, "b c d e f g h i j k l m n o p q r s t u v w"), (9, "tiny")]


@pytest.mark.parametrize("block_bytes", [1 << 20, 100])
def test_equals_brute_force(spark, block_bytes):
    docs = spark.createDataFrame(DOCS, "doc_id long, text string").withColumn("items", F.lit("clash"))
    bench = spark.createDataFrame(ITEMS, "item_id long, text string")
    got = dec.match_benchmark(docs, bench, block_bytes=block_bytes).collect()
    want = brute(DOCS, ITEMS)
    assert {r.doc_id: (r.n_words, r.n_hit, len(r["items"]), hashlib.sha256(",".join(r["items"]).encode()).hexdigest()) for r in got} == want
    clean = dec.remove_contaminated(docs, bench, block_bytes=block_bytes)
    assert clean.columns == docs.columns
    assert sorted(r.doc_id for r in clean.collect()) == sorted(d for d, x in want.items() if x[1] == 0)


def test_longest_matches_and_locations(spark):
    docs = spark.createDataFrame([(1, "z z b c d e f g h i j k l m z a b c d e f g h i j k")], "doc_id long, text string")
    bench = spark.createDataFrame([(5, "a b c d e f g h i j k l m")], "item_id long, text string")
    spans = sorted((s.doc_word, s.length, s.item_word) for s in dec.match_benchmark(docs, bench).first().spans)
    assert spans == [(2, 12, 1), (15, 11, 0)]


def longest(docs, items, window=10):
    """All matches of a window or more that cannot be extended, by looking at every pair of places."""
    out = set()
    for d, t in docs:
        w = words(t)
        for i, u in items:
            v = words(u)
            for a in range(len(w)):
                for b in range(len(v)):
                    if a and b and w[a - 1] == v[b - 1]:
                        continue
                    n = 0
                    while a + n < len(w) and b + n < len(v) and w[a + n] == v[b + n]:
                        n += 1
                    if n and n >= min(window, len(v)):
                        out.add((d, str(i), b, a, n))
    return out


@pytest.mark.parametrize("block_bytes", [1 << 20, 100])
def test_every_suffix_has_its_longest_matches(spark, block_bytes):
    head = "a b c d e f g h i j"
    docs = [*DOCS, (10, f"{head} p q r s"), (11, f"y {head} p q r s x {head} x y t u v {head}"), (12, f"{head} x")]
    items = [*ITEMS, (10, f"{head} p q r s"), (11, f"{head} x y z t u"), (12, f"o {head} x y t {head} p")]
    got = dec.match_benchmark(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), block_bytes=block_bytes).collect()
    assert sorted((r.doc_id, s.item_id, s.item_word, s.doc_word, s.length) for r in got for s in r.spans) == sorted(longest(docs, items))


def test_empty_tables(spark):
    docs, bench = spark.createDataFrame(DOCS, "doc_id long, text string"), spark.createDataFrame(ITEMS, "item_id long, text string")
    assert dec.match_benchmark(docs.where(F.lit(False)), bench).count() == 0
    assert dec.match_benchmark(docs, bench.where(F.lit(False))).where("n_hit > 0").count() == 0
    assert dec.remove_contaminated(docs, bench.where(F.lit(False))).count() == len(DOCS)


def test_table_equals_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").limit(40).collect()
    bench = spark.read.parquet(f"{sf}/benchmark.parquet").select("item_id", "text").collect()
    got = {r.doc_id: (r.n_words, r.n_hit, r.n_items, r.items_sha256) for r in dec.op1_decontamination(spark, sf).collect()}
    want = brute(docs, bench)
    assert {d: got[d] for d in want} == want


def test_blocks_keep_repeated_and_null_ids_apart(spark):
    item = " ".join(f"b{i}" for i in range(12))
    docs = spark.createDataFrame([(1, item), (1, "one two three"), (1, item), (None, "x y"), (None, "z " + item)], "doc_id long, text string")
    bench = spark.createDataFrame([("a", item), ("b", "c " * 12)], "item_id string, text string")
    rows = lambda **k: sorted(((r.doc_id or 0, r.n_words, r.n_hit, r["items"]) for r in dec.match_benchmark(docs, bench, **k).collect()))
    want = [(0, 2, 0, []), (0, 13, 12, ["a"]), (1, 3, 0, []), (1, 12, 12, ["a"]), (1, 12, 12, ["a"])]
    assert rows() == want and rows(block_bytes=1) == want
