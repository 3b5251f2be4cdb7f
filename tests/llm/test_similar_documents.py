import random
import re

import pytest
from pyspark.sql import functions as F

from redgraph.llm import similar_documents as sd


def shingles(text, k=5):
    words = re.findall("[^\\x20\\x09-\\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    return {tuple(words[i : i + k]) for i in range(len(words) - k + 1)} or ({tuple(words)} if words else set())


def roots(rows, similarity=0.8):
    """Groups over all pairs: index of the first row that each row is joined to."""
    sets = [shingles(t) for t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    pairs = 0
    for i in range(len(rows)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both >= similarity * (len(sets[i]) + len(sets[j]) - both):
                pairs += 1
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return [find(i) for i in range(len(rows))], pairs


def planted(seed, many, words=200):
    """Texts of random words and copies of them that change a few words in a run."""
    rng = random.Random(seed)
    out = []
    for _ in range(many):
        base = [f"w{rng.randrange(5000)}" for _ in range(words)]
        out.append(" ".join(base))
        for k in range(rng.randrange(4)):
            copy = list(base)
            for _ in range(rng.choice([1, 2, 3])):
                at = rng.randrange(words - 4)
                copy[at : at + rng.choice([1, 3])] = [f"x{rng.randrange(10**6)}"]
            out.append(" ".join(copy))
    return out


@pytest.mark.parametrize("pairs", [8, 3])
def test_finds_the_pairs_of_brute_force(spark, monkeypatch, pairs):
    monkeypatch.setattr(sd, "PAIRS", pairs)
    texts = planted(1, 60) + planted(2, 3, 6)
    want, linked = roots(texts)
    assert linked > 40
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {}
    for r in sd.similar_groups(docs).collect():
        got.setdefault(r.root, []).append(r["__id"])
    groups = {min(v): sorted(v) for v in got.values()}
    expected = {}
    for i, r in enumerate(want):
        expected.setdefault(r, []).append(i)
    assert all(len({want[i] for i in g}) == 1 for g in groups.values()), "a link below the similarity"
    lost = len(groups) - len(expected)
    assert lost <= 0.05 * (len(texts) - len(expected)), f"{lost} links lost"
    assert sorted(r.doc_id for r in sd.keep_one_of_each(docs).collect()) == sorted(groups)


def test_odd_rows(spark):
    rows = [(1, None, "x", 5), (2, "", "y", None), (None, "  \n", None, 1), (4, "a b c d", "z", 2), (4, "a b c d", "z", 2), (3, "A B\tC  D", "q", 9), (7, "w" * 70000, None, 0), (8, "w" * 70000, None, 0), (None, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, key string, root long")
    kept = sd.keep_one_of_each(docs)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect()) == [1, 3, 7]
    empty = docs.where(F.lit(False))
    assert sd.keep_one_of_each(empty).count() == 0


def test_one_large_group_stays_linear(spark):
    rng = random.Random(5)
    base = [f"w{i}" for i in range(300)]
    texts = []
    for i in range(400):
        copy = list(base)
        copy[rng.randrange(300)] = f"x{i}"
        texts.append(" ".join(copy))
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert [r.doc_id for r in sd.keep_one_of_each(docs).collect()] == [0]
