"""Modes, counters and plans of the round loop."""

import itertools
import random

import exact
import pytest

from redgraph.functions.reduce import SUM
from redgraph.operators import algorithms as al
from redgraph.operators import baselines, superstep
from redgraph.operators import partition as pt
from redgraph.operators.graph import PropertyGraph
from redgraph.sources.tables import graph

EDGES = [(0, 1, 4), (0, 2, 1), (2, 1, 2), (1, 3, 5), (3, 4, 3)]
MODES = [("uncombined", None), ("plain", None), ("short_circuit", None), ("pulse", None), ("bounded_pulse", 2)]


def as_graph(spark, edges, vertices=None):
    e = spark.createDataFrame(edges, "src long, dst long, w long")
    return PropertyGraph(e, spark.createDataFrame([(v,) for v in vertices], "id long") if vertices is not None else None)


def values(r):
    return {x.id: x.val for x in r.df.collect()}


@pytest.mark.parametrize("mode,k", MODES)
def test_hand_sized_graph(spark, mode, k):
    g = as_graph(spark, EDGES, range(6))
    r = al.sssp(g, 0, mode=mode, parts=2, max_local_rounds=k)
    assert values(r) == {0: 0, 1: 3, 2: 1, 3: 8, 4: 11}
    if mode == "short_circuit":
        assert (len(r.rounds), r.total("generated"), r.total("local"), r.total("remote_raw"), r.total("queued"), r.total("accepted")) == (5, 7, 5, 2, 2, 7)
    if mode == "pulse":
        assert (len(r.rounds), r.total("local_rounds"), r.total("generated"), r.total("local"), r.total("remote_raw"), r.total("queued"), r.total("accepted")) == (2, 5, 6, 4, 2, 1, 5)
    assert r.total("generated") == r.total("local") + r.total("remote_raw")
    if mode in ("plain", "pulse"):
        assert values(al.wcc(g, mode=mode, parts=2)) == {0: 0, 1: 0, 2: 0, 3: 0, 4: 0, 5: 5}
        assert values(al.bfs(g, 0, mode=mode, parts=2)) == {0: 0, 1: 1, 2: 1, 3: 2, 4: 3}


def test_modes_and_owners_agree_with_exact_answers(spark):
    rng = random.Random(1)
    edges = [(rng.randrange(25), rng.randrange(25), rng.randrange(0, 3)) for _ in range(60)]
    edges += [(7, 7, 3), (1, 2, 5), (1, 2, 1)]  # a loop and parallel edges
    g = as_graph(spark, edges, range(28))
    want = exact.dijkstra(edges, [0])
    for (mode, k), (scheme, parts) in zip(MODES, itertools.cycle([("block", 4), ("mod", 3), ("hash", 5), ("range", 2), ("mod", 1)])):
        assert values(al.sssp(g, 0, mode=mode, parts=parts, scheme=scheme, max_local_rounds=k, check=False)) == want
    assert values(al.wcc(g, mode="pulse", parts=4)) == exact.components(edges, range(28))
    assert {r.id: r.component for r in al.wcc_levels(g, mode="pulse", parts=4, max_roots=1).collect()} == exact.components(edges, range(28))
    for how in ("push", "pull", "auto"):
        found = {r.id: r for r in al.bfs_levels(g, 0, direction=how).collect()}
        assert {i: r.level for i, r in found.items()} == exact.levels(edges, 0)
        assert all(r.parent is None if i == 0 else found[r.parent].level == r.level - 1 for i, r in found.items())


def test_baselines_agree(spark):
    g = as_graph(spark, EDGES)
    want = exact.dijkstra(EDGES, [0])
    start = al._seeds(g, [0], 0)
    for style in ("fixpoint", "push"):
        assert values(baselines.mirror_sync(g, start, parts=2, style=style)) == want
    placed = pt.assign(g, 2, "block", weight="w")
    assert values(baselines.master_worker(placed, start)) == want
    b1 = baselines.predecessor(placed, start)
    assert values(b1) == want and b1.rounds[0]["edge_search_steps"] == 7


def test_more_owners_than_vertices_and_no_edges(spark):
    assert values(al.sssp(as_graph(spark, EDGES), 0, mode="pulse", parts=9)) == {0: 0, 1: 3, 2: 1, 3: 8, 4: 11}
    empty = as_graph(spark, [], [3])
    assert values(al.sssp(empty, 3, mode="pulse", parts=2)) == {3: 0}
    assert values(al.sssp(empty, 3, mode="plain", parts=2)) == {3: 0}


@pytest.mark.parametrize("edges,what", [([(0, 1, -1)], "negative"), ([(0, 1, None)], "null")])
def test_bad_weights_are_refused(spark, edges, what):
    with pytest.raises(ValueError, match=what):
        al.sssp(as_graph(spark, edges), 0)


@pytest.mark.parametrize("mode", ["plain", "pulse"])
def test_overflow_raises(spark, mode):
    with pytest.raises(Exception, match="(?i)overflow"):
        al.sssp(as_graph(spark, [(0, 1, 1 << 62), (1, 2, 1 << 62)]), 0, mode=mode, parts=2)


def test_sums_cannot_be_iterated(spark):
    placed = pt.assign(as_graph(spark, EDGES), 2, "mod")
    with pytest.raises(ValueError, match="repeat-safe"):
        superstep.run(placed, al._seeds(as_graph(spark, EDGES), [0], 0), op=SUM)


@pytest.mark.parametrize("mode", ["plain", "pulse"])
def test_a_round_has_one_exchange(spark, mode):
    r = al.sssp(as_graph(spark, EDGES), 0, mode=mode, parts=4, explain=True)
    plan = r.plan.split("== Physical Plan ==")[1]
    assert plan.count("Exchange ") == 1 and "shufflepartitionidpassthrough" in plan


def test_fusion_saves_rounds_on_a_lattice_but_not_with_scattered_owners(spark):
    g = graph(spark, "/root/testdata/sf0.001", "grid", width=10)
    near = {m: al.sssp(g, 0, mode=m, parts=4, check=False) for m in ("short_circuit", "pulse")}
    assert len(near["pulse"].rounds) * 2 < len(near["short_circuit"].rounds)
    assert near["pulse"].total("queued") < near["short_circuit"].total("queued")
    assert values(near["pulse"]) == values(near["short_circuit"])


def test_known_answers(spark):
    d = "/root/testdata/sf0.001"
    trade = values(al.sssp(graph(spark, d, "trade"), 0, mode="pulse"))
    assert len(trade) == 210 and max(trade.values()) == 18
    grid = values(al.sssp(graph(spark, d, "grid", width=10), 0, mode="pulse"))
    assert len(grid) == 150 and max(grid.values()) == 847


def test_bad_seeds_only_lower_distances(spark):
    g = graph(spark, "/root/testdata/sf0.001", "trade")
    good, bad = values(al.sssp(g, 0, mode="pulse")), values(al.bad_seed_sssp(g, mode="pulse"))
    assert all(bad[i] <= good[i] for i in good) and any(bad[i] < good[i] for i in good)


def test_ranks(spark):
    g = as_graph(spark, EDGES)
    got = {r.id: r["rank"] for r in al.pagerank_fixed(g, 3).collect()}
    assert sum(got.values()) == 562_675_000_000 and (got[4], got[3], got[1]) == (261_412_500_000, 149_425_000_000, 79_087_500_000)
    assert got == exact.pagerank_fixed(EDGES, 3)
    r = al.pagerank(g, stop="fixed", max_iter=3)
    assert all(abs(x["rank"] - got[x.id] / 1e12) < 1e-6 for x in r.df.collect())
    assert all(x["mass"] <= 1 + 1e-9 for x in r.rounds)
    spread = al.pagerank(g, dangling="spread", max_iter=3, stop="fixed")
    assert abs(spread.rounds[-1]["mass"] - 1) < 1e-9
    exact_, delta = al.pagerank(g, tol=1e-13).df, al.pagerank_delta(g, tol=1e-13).df
    want = {x.id: x["rank"] for x in exact_.collect()}
    assert all(abs(x["rank"] - want[x.id]) < 1e-9 for x in delta.collect())


def test_owners_grow_with_the_edges_and_idle_ones_get_none(spark, monkeypatch):
    rng = random.Random(11)
    hubs = [(rng.randrange(4), rng.randrange(400), rng.randrange(1, 9)) for _ in range(900)]
    edges = hubs + [(b, a, w) for a, b, w in hubs] + [(k, k + 1, 1) for k in range(1000, 1400)]
    g = as_graph(spark, edges)
    assert pt.assign(g, None, "block", weight="w").parts == 8
    monkeypatch.setattr(pt, "OWNED", 100)
    placed = pt.assign(g, None, "block", weight="w")
    sizes = [r.edges for r in pt.partition_stats(placed).collect()]
    assert placed.parts == 22 and max(sizes) <= 4 * 100 + max(sum(a == k for a, _, _ in edges) for k in range(4))
    want = exact.dijkstra(edges, [0])
    asked, real = [], superstep.working
    monkeypatch.setattr(superstep, "working", lambda busy, *dfs: asked.append(busy) or real(busy, *dfs))
    for mode, k in (("pulse", None), ("short_circuit", None), ("bounded_pulse", 2)):
        assert values(al.sssp(g, 0, mode=mode, max_local_rounds=k)) == want
    assert asked[0] is None and all(b is None or len(b) < placed.parts for b in asked) and any(asked)
    start = al._seeds(g, [0], 0)
    for style in ("fixpoint", "push"):
        assert values(baselines.mirror_sync(g, start, style=style)) == want
    assert values(baselines.master_worker(placed, start)) == want


@pytest.mark.parametrize("style", ["fixpoint", "push"])
def test_mirrors_write_once_between_pulse_and_state(spark, monkeypatch, style):
    """A phase stores what the replicas found and the new state; masters and the directory of replicas are not stored or dealt again."""
    stored = []
    monkeypatch.setattr(baselines, "cut", lambda df: stored.append(df) or superstep.cut(df))
    g = as_graph(spark, EDGES)
    r = baselines.mirror_sync(g, al._seeds(g, [0], 0), parts=3, scheme="mod", style=style)
    assert values(r) == exact.dijkstra(EDGES, [0])
    assert len(stored) == len(r.rounds) > 2
    assert r.total("reduce_msgs") > 0 and r.total("bcast_msgs") > 0 and r.rounds[-1]["reduce_msgs"] == 0
