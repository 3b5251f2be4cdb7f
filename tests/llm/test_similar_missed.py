"""Pairs that share no band are found too: the last pass of the near-copy stage misses none."""

import numpy as np
import pyarrow as pa
import pytest
import test_similar_documents as ts

from redgraph.llm import similar_documents as sd


def test_one_band_finds_all_pairs(spark):
    """With a single band most links lay in no cell and were left out."""
    texts = ts.planted(5, 60) + ts.planted(6, 12, 30)
    want, linked = ts.roots(texts)
    assert linked > 40
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    groups: dict[int, set[int]] = {}
    for r in sd.similar_groups(docs, recall=0.0).collect():
        groups.setdefault(r.root, set()).add(r["__id"])
    whole: dict[int, set[int]] = {}
    for k, root in enumerate(want):
        whole.setdefault(root, set()).add(k)
    assert sorted(map(sorted, groups.values())) == sorted(map(sorted, whole.values()))


def test_sets_alike_enough_share_their_heads():
    rng = np.random.default_rng(3)
    for _ in range(3000):
        pool = rng.choice(10**6, 60, replace=False)
        a = np.unique(pool[: rng.integers(1, 40)])
        b = np.unique(np.concatenate([a[rng.random(len(a)) < 0.95], pool[40 : 40 + rng.integers(0, 6)]]))
        both = len(np.intersect1d(a, b))
        if len(b) and both >= 0.8 * (len(a) + len(b) - both):
            (p, q), share = sd.head_counts(np.array([len(a), len(b)]), 0.8)
            assert len(np.intersect1d(a[:p], b[:q])) >= min(*share, np.ceil(0.8 * max(len(a), len(b)) - 1e-9))
    assert sd.head_counts(np.array([0, 1, 5, 10, 100]), 0.8)[0].tolist() == [0, 1, 2, 4, 33]


@pytest.mark.parametrize("size", [1, 2, 3, 7, 100])
def test_only_cells_of_several_stay_whatever_the_batches(size):
    rng = np.random.default_rng(size)
    cell = np.sort(rng.integers(0, 40, 60))
    many = np.bincount(cell)
    table = pa.table({"cell": cell, "key": np.arange(60), "old": np.zeros(60, bool)})
    found = [x for b in sd._shared(iter(table.to_batches(max_chunksize=size))) for x in b.column("key").to_pylist()]
    assert found == [k for k in range(60) if many[cell[k]] > 1]
