"""Edges in blocks: the same edges, values, rounds and counters as placed rows."""

import random

import exact
import pyarrow as pa
import pytest
import test_rounds as tr

from redgraph import queries
from redgraph.functions.reduce import MIN
from redgraph.operators import algorithms as al
from redgraph.operators import baselines, packed, superstep
from redgraph.operators import partition as pt
from redgraph.sources.tables import graph

RNG = random.Random(5)
EDGES = [(RNG.randrange(30), RNG.randrange(30), RNG.randrange(0, 9)) for _ in range(140)] + [(4, b, 7 + b) for b in range(30)] + [(3, 3, 2)]
NAMES = ("generated", "local", "remote_raw", "queued", "accepted", "bytes", "batches", "local_rounds", "through_master")


def counters(r):
    return [[x.get(n) or 0 for n in NAMES] for x in r.rounds]


def test_blocks_hold_all_edges_also_of_hubs_larger_than_a_block(monkeypatch):
    monkeypatch.setattr(packed, "_SLICE", 7)
    edges = [(s * 10**10, d * 10**10, w) for s, d, w in EDGES]
    rows = pa.RecordBatch.from_pydict({"part": pa.array([s % 3 for s, _, _ in EDGES], pa.int32()), "src": [e[0] for e in edges], "dst": [e[1] for e in edges], "dst_part": pa.array([d % 3 for _, d, _ in EDGES], pa.int32()), "w": [e[2] for e in edges]})
    blocks = pa.Table.from_batches([packed._blocks([rows, rows])])
    assert max(blocks.column("n").to_pylist()) == 7
    found = packed.unpacked(blocks).to_pydict()
    assert sorted(zip(found["src"], found["dst"], found["w"])) == sorted(edges * 2)


@pytest.mark.parametrize("far", [1, 10**9])
def test_a_step_in_small_slices_reaches_the_exact_values(monkeypatch, far):
    """One owner alone, ids close together or far apart, and the best mail for each foreign id."""
    monkeypatch.setattr(packed, "_SLICE", 5)
    edges = [(s, d, w) for s, d, w in EDGES if s < 20]
    rows = pa.RecordBatch.from_pydict({"part": pa.array([0] * len(edges), pa.int32()), "src": [s * far for s, _, _ in edges], "dst": [d * far for _, d, _ in edges], "dst_part": pa.array([int(d >= 20) for _, d, _ in edges], pa.int32()), "w": [w for _, _, w in edges]})
    state = pa.table({"id": [i * far for i in range(20)], "val": pa.array([0] + [None] * 19, pa.int64()), "changed": [True] + [False] * 19})
    out = packed.step(0, state, pa.Table.from_batches([packed._blocks([rows])]), "plus_weight", MIN.at, MIN.worst, "pulse", None, 1024).to_pylist()
    want = exact.dijkstra(edges, [0])
    near = {r["id"] // far: r["val"] for r in out if r["kind"] == packed.STATE}
    assert near == {i: v for i, v in want.items() if 0 < i < 20}
    assert {r["id"] // far: r["val"] for r in out if r["kind"] == packed.MAIL} == {i: v for i, v in want.items() if i >= 20}


@pytest.mark.parametrize("mode,k", tr.MODES)
def test_values_and_counters_equal_those_of_placed_rows(spark, mode, k):
    g = tr.as_graph(spark, EDGES, range(32))
    rows = al.sssp(g, 0, mode=mode, parts=3, max_local_rounds=k)
    blocks = al.sssp(g, 0, mode=mode, placed=packed.pack(g, 3, weight="w", check=True), max_local_rounds=k, batch_size=1024)
    assert tr.values(blocks) == tr.values(rows) == exact.dijkstra(EDGES, [0])
    assert counters(blocks) == counters(rows)


def test_long_runs_over_blocks_end_in_one_task(spark, monkeypatch):
    edges = [(a, b, 1 + (a * 7 + b) % 5) for i in range(18) for a, b in ((i, i + 1), (i + 1, i))]
    g = tr.as_graph(spark, edges)
    placed = packed.pack(g, 3, "mod", weight="w")
    one_by_one = al.sssp(g, 0, mode="plain", parts=3, scheme="mod")
    monkeypatch.setattr(superstep, "LONG", 2)
    gathered = al.sssp(g, 0, mode="plain", placed=placed)
    assert tr.values(gathered) == tr.values(one_by_one)
    assert counters(gathered) == counters(one_by_one)


def test_coordinator_over_blocks(spark):
    g = tr.as_graph(spark, EDGES)
    start = al._seeds(g, [0], 0)
    rows, blocks = (baselines.master_worker(p, start) for p in (pt.assign(g, 3, "block", weight="w"), packed.pack(g, 3, "block", weight="w")))
    assert tr.values(blocks) == tr.values(rows) == exact.dijkstra(EDGES, [0])
    assert counters(blocks) == counters(rows)


def test_faults_are_refused_and_no_edges_are_none(spark):
    for edges, what in (([(0, 1, -1)], "negative"), ([(0, 1, None)], "null weights"), ([(0, None, 1)], "null ends")):
        with pytest.raises(ValueError, match=what):
            packed.pack(tr.as_graph(spark, edges), None, weight="w", check=True)
    empty = tr.as_graph(spark, [], [3])
    assert tr.values(al.sssp(empty, 3, placed=packed.pack(empty, 2, weight="w"))) == {3: 0}


def never(*a, **k):
    raise AssertionError("edges were placed as rows")


def test_the_coordinator_query_takes_blocks(spark, sf, monkeypatch):
    want = tr.values(al.sssp(graph(spark, sf, "trade"), 0, mode="pulse"))
    monkeypatch.setattr(pt, "assign", never)
    assert {r.id: r.dist for r in queries.QUERIES["sssp_trade_master"](spark, sf).collect()} == want


def test_the_query_of_costs_takes_blocks_placed_once(spark, sf, monkeypatch):
    r = al.sssp(graph(spark, sf, "trade"), 0, mode="plain", parts=8)
    monkeypatch.setattr(pt, "assign", never)
    found = {(x.mode, x.name): x.value for x in queries.QUERIES["sssp_costs"](spark, sf).collect()}
    assert len(found) == 52
    assert {n: found["plain", n] for n in NAMES[:6]} == {n: r.total(n) for n in NAMES[:6]}


def test_the_cube_builds_each_graph_once(spark, sf, monkeypatch):
    r = al.sssp(graph(spark, sf, "trade"), 0, mode="plain")
    monkeypatch.setattr(al, "assign", never)
    found = {(x.algo, x.mode, x.graph): (x.value, x.n) for x in queries.QUERIES["counters_cube"](spark, sf).collect()}
    assert found["sssp", "plain", "trade"] == (r.total("generated"), len(r.rounds))
    assert found[None, None, None][0] == sum(found["sssp", m, g][0] for m in ("plain", "pulse") for g in ("trade", "user_hop"))
