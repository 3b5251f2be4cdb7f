import re

import pytest
import xxhash
from pyspark.sql import functions as F

from redgraph.llm import simhash


def fingerprint(text, k=3):
    words = re.findall("[^\\x20\\x09-\\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    grams = [" ".join(words[i : i + k]) for i in range(len(words) - k + 1)] or [" ".join(words)]
    hs = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def groups(fps, bits=2):
    """Smallest id reachable over links, by brute force."""
    root = list(range(len(fps)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i][1] ^ fps[j][1]).bit_count() <= bits:
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return {fps[i][0]: fps[find(i)][0] for i in range(len(fps))}


@pytest.mark.parametrize("pairs", [48, 3])
def test_equals_brute_force(spark, sf, monkeypatch, pairs):
    monkeypatch.setattr(simhash, "PAIRS", pairs)
    rows = sorted(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect())
    fps = [(r[0], fingerprint(r[1])) for r in rows]
    want = groups(fps)
    got = simhash.op7_simhash(spark, sf).collect()
    assert {(r.doc_id, r.fingerprint, r.component_id) for r in got} == {(i, f"{f:016x}", want[i]) for i, f in fps}
    assert len(got) == len(rows)


@pytest.mark.parametrize("pairs", [48, 2])
@pytest.mark.parametrize("bits", [0, 1, 2])
def test_links_connect_what_is_near(spark, monkeypatch, pairs, bits):
    import random

    monkeypatch.setattr(simhash, "PAIRS", pairs)
    rng = random.Random(bits)
    fps = {0, 1 << 63, (1 << 64) - 1}
    for _ in range(6):
        x = rng.getrandbits(64)
        for _ in range(25):
            fps.add(x)
            x ^= sum(1 << b for b in rng.sample(range(64), rng.choice([1, 2, 3])))
    fps = sorted(fps)
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    df = spark.createDataFrame([(i, f) for i, f in enumerate(signed)], "doc_id long, fp long")
    got = {r.fp: r.component for r in simhash.near_groups(df, max_bits=bits).collect()}
    want = groups(list(enumerate(fps)), bits)
    assert {i: got[f] for i, f in enumerate(signed)} == want


def test_nulls_empty_ties_and_clashing_columns(spark):
    rows = [(1, None, "x", 5), (2, "", "y", None), (None, "  \n", None, 1), (4, "a b c d", "z", 2), (4, "a b c d", "z", 2), (3, "A B\tC  D", "q", 9), (7, "w" * 70000, None, 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, fp string, component long")
    out = simhash.near_duplicates(docs).collect()
    assert sorted((r.doc_id if r.doc_id is not None else -1, r.component) for r in out) == [(-1, 1), (1, 1), (2, 1), (3, 3), (4, 3), (4, 3), (7, 7)]
    kept = simhash.keep_one_of_each(docs)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect()) == [1, 3, 7]
    empty = docs.where(F.lit(False))
    assert simhash.near_duplicates(empty).count() == 0
    assert simhash.keep_one_of_each(empty).count() == 0


def test_hash_of_any_length():
    import numpy as np

    data = np.random.default_rng(0).integers(0, 256, 4000, dtype=np.uint8)
    ends = np.array(list(range(0, 140)) + [511, 512, 513, 900]) + 7
    starts = np.full(len(ends), 7)
    assert simhash.xxh64_spans(data, starts, ends).tolist() == [xxhash.xxh64_intdigest(data[7:e].tobytes(), 42) for e in ends.tolist()]
