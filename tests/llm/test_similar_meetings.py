"""The second pass of the near-duplicate stage: no pair is a row, and what leaves a meeting is a forest."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_similar_documents import planted, roots

from redgraph.llm import similar_documents as sd
from redgraph.session import staged


def _nodes(spark, texts):
    rows = spark.createDataFrame(list(enumerate(texts)), "__id long, text string").withColumn("__text", F.xxhash64("text"))
    prints = staged(sd._prints(rows, 5).withColumn("key", F.col("__text")), "test-prints")
    nodes = prints.groupBy("key").agg(F.min("lo").alias("lo"), F.min("hi").alias("hi"), F.min("n").alias("n"), F.min("__id").alias("rep"))
    return rows, staged(nodes.withColumn("root", F.col("key")), "test-nodes")


def _large_group(many, words=120):
    rng = random.Random(11)
    base = [f"w{i}" for i in range(words)]
    out = []
    for i in range(many):
        copy = list(base)
        for k in range(rng.randrange(1, 6)):
            copy[rng.randrange(words)] = f"x{i}-{k}"
        out.append(" ".join(copy))
    return out


def _components(keys, pairs):
    root = {k: k for k in keys}

    def of(k):
        while root[k] != k:
            k = root[k]
        return k

    for a, b in pairs:
        x, y = sorted((of(a), of(b)))
        root[y] = x
    return {k: of(k) for k in keys}


@pytest.mark.parametrize("pairs, meet", [(8, 256), (2, 5)])
def test_rows_do_not_grow_with_the_square_of_a_group(spark, monkeypatch, pairs, meet):
    """Without the first pass nothing is joined yet: all pairs of a group meet, but a text has one row a cell and depth."""
    monkeypatch.setattr(sd, "PAIRS", pairs)
    monkeypatch.setattr(sd, "MEET", meet)
    made = {}
    for many in (60, 240):
        rows, nodes = _nodes(spark, _large_group(many))
        found = staged(sd.meetings(nodes.drop("rep"), 0.8), "test-meetings")
        made[many] = found.count()
        assert found.groupBy("unit").count().agg(F.max("count")).first()[0] <= max(meet, 4 * 60) + 1
        links = [(r.a, r.b) for r in sd._joined(found, sd._texts(rows, nodes, found.select("key")), 5, 0.8).collect()]
        keys = [r.key for r in nodes.collect()]
        pairs_ = sd.candidates(nodes.drop("rep"), 0.8)
        all_links = [(r.a, r.b) for r in sd._verified(pairs_, sd._texts(rows, nodes, nodes.select("key")), 5, 0.8).collect()]
        assert _components(keys, links) == _components(keys, all_links)
        assert len(links) <= made[many]
    assert made[240] <= 4 * 1.5 * made[60] + 240


def test_a_meeting_joins_what_brute_force_joins():
    texts = planted(4, 12, 80)
    import pyarrow as pa

    from redgraph.llm.bytetext import chunks

    sets, prints = [], []
    for chunk in chunks(pa.array(texts)):
        h, edge = sd.shingle_sets(chunk, 5)
        sets += [h[i:j] for i, j in zip(edge, edge[1:], strict=False)]
        prints.append(sd.wide_fingerprints(h, edge))
    fp = np.concatenate(prints)
    unit = {"lo": fp[:, 0], "hi": fp[:, 1], "n": np.array([len(s) for s in sets]), "root": np.arange(len(texts)), "role": np.zeros(len(texts), np.int64)}
    links = sd._joins(unit, sets, sd._reach(0.8), 0.8)
    want, _ = roots(texts)
    got = _components(range(len(texts)), links)
    assert [got[i] for i in range(len(texts))] == want
    assert len(links) == len(texts) - len(set(want))
    # texts of one root are not linked again
    assert not sd._joins(unit | {"root": np.zeros(len(texts), np.int64)}, sets, sd._reach(0.8), 0.8)
