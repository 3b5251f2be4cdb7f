"""Exact de-duplication, mixing and sharding: brute force, odd inputs, and no Python on executors."""

import hashlib
import zlib
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from redgraph.llm import exact_dedup, mixing, sharding

ODD = [(1, None, "b", 1), (2, "", None, 2), (2, "", None, 2), (None, "x y", "a", 3), (5, "x y", "a", 4), (6, "z " * 40000, "a", 5), (7, "x y", "", 6), (8, "é ü", "é", 7)]
KIND = "doc_id long, text string, source string, size int"


def odd(spark):
    return spark.createDataFrame(ODD, KIND)


# exact de-duplication --------------------------------------------------------------------------


def weak(text):
    return F.substring(F.sha2(text, 256), 1, 1)  # sixteen digests: nearly every hit is false


@pytest.mark.parametrize("digest", [exact_dedup.sha, weak])
@pytest.mark.parametrize("files_per_batch", [None, 1])
def test_dedup_equals_brute_force(spark, sf, tmp_path, digest, files_per_batch):
    path = str(tmp_path / "docs.parquet")
    spark.read.parquet(f"{sf}/documents.parquet").repartition(3).write.parquet(path)
    texts = dict(spark.read.parquet(path).select("doc_id", "text").collect())
    groups = defaultdict(list)
    for i, t in texts.items():
        groups[t].append(i)
    want = {i: (max(groups[t]), len(groups[t]), i == max(groups[t])) for i, t in texts.items()}
    got = exact_dedup.exact_groups(spark, path, digest=digest, files_per_batch=files_per_batch)
    assert {r.doc_id: (r.keep_id, r.group_size, r.kept) for r in got.collect()} == want
    assert "Python" not in got._jdf.queryExecution().toString()


def test_dedup_of_odd_rows(spark, tmp_path):
    path = str(tmp_path / "docs.parquet")
    odd(spark).repartition(2).write.parquet(path)
    got = exact_dedup.exact_groups(spark, path).collect()
    by = defaultdict(list)
    for r in got:
        by[r.digest].append(r)
    empty = by[hashlib.sha256(b"").hexdigest()]
    assert len(got) == len(ODD) and len(empty) == 3 and sum(r.kept for r in empty) == 1 and {r.keep_id for r in empty} == {2}
    assert {r.keep_id for r in by[hashlib.sha256(b"x y").hexdigest()]} == {7}
    assert all(sum(r.kept for r in rows) == 1 for rows in by.values())


def test_dedup_goes_on_from_its_state_and_takes_empty_tables(spark, tmp_path):
    path, place = str(tmp_path / "docs.parquet"), str(tmp_path / "log")
    spark.createDataFrame([(1, "a"), (2, "b")], "doc_id long, text string").coalesce(1).write.parquet(path)
    first = exact_dedup.seen_digests(spark, path, checkpoint=place)
    assert sorted((r.group_size, r.keep.id) for r in first.collect()) == [(1, 1), (1, 2)]
    spark.createDataFrame([(3, "a")], "doc_id long, text string").coalesce(1).write.mode("append").parquet(path)
    again = exact_dedup.seen_digests(spark, path, checkpoint=place)
    assert sorted((r.group_size, r.keep.id) for r in again.collect()) == [(1, 2), (2, 3)]
    none = str(tmp_path / "none.parquet")
    odd(spark).where(F.lit(False)).write.parquet(none)
    assert exact_dedup.exact_groups(spark, none).count() == 0


# mixing ----------------------------------------------------------------------------------------


def targets(sizes, weights=(5, 2, 1), share=1.5, most=2.0):
    """Deal by weight, stop sources at their limit, deal the excess again."""
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[k % len(weights)] for k, s in enumerate(names)}
    total = share * sum(sizes.values())
    out, open_ = {}, set(names)
    while open_:
        level = (total - sum(out.values())) / sum(w[s] for s in open_)
        over = {s for s in open_ if level * w[s] > most * sizes[s]}
        if not over:
            return out | {s: level * w[s] for s in open_}
        out |= {s: most * sizes[s] for s in over}
        open_ -= over
    return out


def test_mix_reaches_targets(spark, sf):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = {r.doc_id: r for r in mixing.mix_plan(docs).collect()}
    source = dict(docs.select("doc_id", "source").collect())
    sizes = Counter()
    for i, r in rows.items():
        sizes[source[i]] += r["size"]
    want = targets(sizes)
    taken = Counter()
    for i, r in rows.items():
        assert r.source_size == sizes[source[i]] and abs(r.target - want[source[i]]) < 1e-6 * r.target and r.taken <= 2 * r["size"]
        taken[source[i]] += r.taken
    largest = defaultdict(int)
    for i, r in rows.items():
        largest[source[i]] = max(largest[source[i]], r["size"])
    assert all(abs(taken[s] - want[s]) <= 1.5 * largest[s] for s in want)
    again = {r.doc_id: r.taken for r in mixing.mix_plan(docs.repartition(5)).collect()}
    assert again == {i: r.taken for i, r in rows.items()}
    plan = mixing.mix_plan(docs)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_mixed_corpus_and_odd_rows(spark):
    plan = mixing.mix_plan(odd(spark)).collect()
    assert len(plan) == len(ODD) and all(r.taken <= 2 * r["size"] for r in plan)
    mixed = mixing.mix(odd(spark))
    assert mixed.columns == odd(spark).columns
    assert Counter((r.doc_id, r.text) for r in mixed.collect()) == Counter({k: v for k, v in Counter([(r.doc_id, t) for r in plan for t in [next(x[1] for x in ODD if x[0] == r.doc_id)] * r.copies]).items()})
    assert mixing.mix_plan(odd(spark).where(F.lit(False))).count() == 0
    assert mixing.mix(odd(spark).where("doc_id IN (1, 2)")).count() == 0  # no words at all


# sharding --------------------------------------------------------------------------------------


def test_every_shard_matches_the_mixture(spark):
    path = "/root/testdata/sf0.01"
    rows = sharding.op3_sharding(spark, path).collect()
    texts = dict(spark.read.parquet(f"{path}/documents.parquet").select("doc_id", "text").collect())
    assert all(r["size"] == len(texts[r.doc_id].encode()) + 1 and r.text_crc32 == zlib.crc32(texts[r.doc_id].encode()) for r in rows)
    by = defaultdict(list)
    for r in rows:
        by[r.shard].append(r)
    sizes = [len(x) for x in by.values()]
    assert sorted(by) == list(range(16)) and max(sizes) - min(sizes) <= 1
    assert all(sorted(r.slot for r in x) == list(range(len(x))) for x in by.values())
    whole = Counter(r.source for r in rows)
    for x in by.values():
        part = Counter(r.source for r in x)
        assert all(abs(part[s] - n * len(x) / len(rows)) <= 2 for s, n in whole.items())


@pytest.mark.parametrize("bucket_rows", [1 << 16, 1, 1 / 64])
def test_places_do_not_depend_on_buckets_or_partitions(spark, sf, monkeypatch, bucket_rows):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "source")
    want = {(r.doc_id, r.shard, r.slot) for r in sharding.shard_rows(docs).collect()}
    monkeypatch.setattr(sharding, "BUCKET_ROWS", bucket_rows)
    assert {(r.doc_id, r.shard, r.slot) for r in sharding.shard_rows(docs.repartition(5)).collect()} == want


def test_shards_of_odd_rows(spark):
    got = sharding.shard_rows(odd(spark), shards=3)
    assert got.columns == [*odd(spark).columns, "shard", "slot"]
    assert sorted((r.shard, r.slot) for r in got.collect()) == [(0, 0), (0, 1), (0, 2), (1, 0), (1, 1), (1, 2), (2, 0), (2, 1)]
    assert sharding.shard_rows(odd(spark).where(F.lit(False))).count() == 0
