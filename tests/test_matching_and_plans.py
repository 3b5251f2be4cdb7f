"""Matching, order stitching and the plan of a round of ranks."""

import random

import pytest
from pyspark.sql import functions as F

from redgraph.functions.reduce import MIN
from redgraph.operators import algorithms as al
from redgraph.operators import mailbox
from redgraph.operators.graph import PropertyGraph
from redgraph.session import fixed, scoped
from redgraph.sources import tables


def test_matching_equals_brute_force(spark):
    rng = random.Random(3)
    edges = {(rng.randrange(9), rng.randrange(9)) for _ in range(35)}
    edges = {(a, b) for a, b in edges if a != b}
    g = PropertyGraph(spark.createDataFrame([(a, b, 1) for a, b in edges], "src long, dst long, w long"))
    n = range(9)
    want = {(a, b, c, d) for a in n for b in n for c in n for d in n if len({a, b, c, d}) == 4 and {(a, b), (b, c), (c, a), (c, d)} <= edges}
    pattern = [("a", "b"), ("b", "c"), ("c", "a"), ("c", "d")]
    assert {tuple(r) for r in al.match_pattern(g, pattern).collect()} == want
    some = {m for m in want if not any((m["abcd".index(x)], m["abcd".index(y)]) in edges for x in "abcd" for y in "abcd" if x != y and (x, y) not in pattern)}
    assert {tuple(r) for r in al.match_pattern(g, pattern, induced=True).collect()} == some
    with pytest.raises(ValueError):
        al.match_pattern(g, [("a", "b"), ("c", "d")])


def test_next_of_the_whole_order_over_ranges(spark):
    rows = [((k * 7919) % 500 // 2, k, f"v{k}") for k in range(500)]
    df = spark.createDataFrame(rows, "t long, k long, v string")
    order = sorted(rows)
    want = {a[1]: b[2] for a, b in zip(order, order[1:], strict=False)}
    got = {r.k: r.nxt for r in tables.followed(df, ["t", "k"], "v", "nxt").collect()}
    assert got == want | {order[-1][1]: None}
    assert tables.followed(df.where(F.lit(False)), ["t", "k"], "v", "nxt").count() == 0


def test_a_round_of_ranks_ships_shares_only(spark, sf):
    g = tables.graph(spark, sf, "cust_supp")
    e, v, n, parts = al._shares(g)
    with scoped(spark, fixed(parts)):
        acc = al._received(e, v.withColumn("rank", F.lit(1.0)), F.col("rank") / F.col("outdeg"))
        plan = v.join(acc, F.col("id") == F.col("to"), "left")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1, plan


def test_diamonds_are_counted_without_listing_them(spark):
    rng = random.Random(5)
    edges = [(rng.randrange(12), rng.randrange(12), 1) for _ in range(70)] + [(3, 3, 1), (0, 1, 1), (0, 1, 2)]
    g = PropertyGraph(spark.createDataFrame(edges, "src long, dst long, w long"))
    listed = al.match_pattern(g, [("a", "b"), ("a", "c"), ("b", "d"), ("c", "d")], ordered=[("b", "c")]).groupBy("a").count()
    want = {r.a: r["count"] for r in listed.collect()}
    for per_row in (4096, 2):  # a hub's list in several rows
        counted = al.diamonds(g, per_row)
        assert {r.id: r.matches for r in counted.collect()} == want
        assert counted._jdf.queryExecution().analyzed().toString().count("Join Inner") == 1, "only the step to the middles' targets"


def test_blocks_of_all_queues_travel_at_once(spark, monkeypatch):
    rng = random.Random(6)
    mail = [(rng.randrange(3), k % 4, k, rng.randrange(1000)) for k in (rng.randrange(400) for _ in range(3000))]
    state = [(k % 4, k, rng.choice([None, rng.randrange(1000)])) for k in range(300)]
    m = spark.createDataFrame(mail, "from_part int, to_part int, dst long, val long")
    st = spark.createDataFrame(state, "part int, id long, val long")
    want = {tuple(r) for r in mailbox.sync_batched(m, st, MIN, 4).collect()}
    jobs = []
    monkeypatch.setattr("redgraph.session.cut", lambda df: jobs.append(df) or df.checkpoint())
    got = mailbox.sync_chunks(m, st, MIN, 4, 7)
    assert sorted(tuple(r) for r in got.collect()) == sorted(want)
    assert len(jobs) <= 1, "no job for each block"
    assert mailbox.sync_chunks(m.limit(0), st, MIN, 4, 7).count() == len(state)


def test_pairs_within_a_time_are_counted_in_blocks(spark, tmp_path, monkeypatch):
    rng = random.Random(7)
    rows = [(k, rng.randrange(25), rng.randrange(0, 20_000) * 500_000 + rng.randrange(2) * 3) for k in range(700)] + [(900, None, 5), (901, 3, None)]
    e = spark.createDataFrame(rows, "event_id long, user_id long, t long")
    e.select("event_id", "user_id", F.expr("timestamp_ntz '2024-01-01 00:00:00' + make_dt_interval(0, 0, 0, t / 1000000)").alias("ts")).write.parquet(f"{tmp_path}/events.parquet")
    want = {}
    for _, u, a in rows:
        for _, v, b in rows:
            if None not in (u, v, a, b) and u != v and a < b <= a + 60_000_000:
                want[u, v] = want.get((u, v), 0) + 1
    for name, size in (("_USERS", 7), ("_EVENTS", 20), ("_PAIRS", 5)):
        monkeypatch.setattr(tables, name, size)
    found = tables.within(spark, str(tmp_path), 60)
    assert {(r.src, r.dst): r.n for r in found.collect()} == want
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()


def test_pairs_within_a_time_are_not_exchanged(spark, tmp_path, monkeypatch):
    """The result has a row for nearly all pairs of users: an exchange of their counts wrote them all to disk."""
    rows = [(k, k % 40, k) for k in range(400)]
    e = spark.createDataFrame(rows, "event_id long, user_id long, t long")
    e.select("event_id", "user_id", F.expr("timestamp_ntz '2024-01-01 00:00:00' + make_dt_interval(0, 0, 0, t)").alias("ts")).write.parquet(f"{tmp_path}/events.parquet")
    monkeypatch.setattr(tables, "_USERS", 9)
    found = tables.within(spark, str(tmp_path), 3600)
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate" not in plan[: plan.index("RepartitionByExpression")]
    assert found.count() == found.select("src", "dst").distinct().count() == 40 * 39
    assert found.groupBy().sum("n").first()[0] == sum(a % 40 != b % 40 for a in range(400) for b in range(a + 1, 400))
