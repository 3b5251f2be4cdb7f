"""Runs with long paths end in one task; rounds, values and counters are those of the rounds in Spark."""

import pytest
import test_rounds as tr

from redgraph.operators import algorithms as al
from redgraph.operators import superstep
from redgraph.sources.tables import graph


@pytest.mark.parametrize("mode,k", tr.MODES)
def test_counters_equal_those_of_single_rounds(spark, monkeypatch, mode, k):
    edges = [(a, b, 1 + (a * 7 + b) % 5) for i in range(18) for a, b in ((i, i + 1), (i + 1, i), (i, (i * 5) % 19))]
    g = tr.as_graph(spark, edges, range(20))
    monkeypatch.setattr(superstep, "GATHERED", -1)
    one_by_one = al.sssp(g, 0, mode=mode, parts=3, scheme="mod", max_local_rounds=k)
    monkeypatch.setattr(superstep, "GATHERED", 1 << 22)
    monkeypatch.setattr(superstep, "LONG", 2)
    gathered = al.sssp(g, 0, mode=mode, parts=3, scheme="mod", max_local_rounds=k)
    assert tr.values(gathered) == tr.values(one_by_one)
    assert len(gathered.rounds) > 2
    names = ("generated", "local", "remote_raw", "queued", "accepted", "bytes", "batches", "local_rounds")
    assert [[r.get(n) or 0 for n in names] for r in gathered.rounds] == [[r.get(n) or 0 for n in names] for r in one_by_one.rounds]


def test_a_limit_on_rounds_holds(spark, monkeypatch):
    monkeypatch.setattr(superstep, "LONG", 2)
    g = tr.as_graph(spark, [(i, i + 1, 1) for i in range(9)])
    with pytest.raises(RuntimeError):
        al.sssp(g, 0, mode="plain", parts=2, max_rounds=5)


def test_the_whole_lattice_takes_few_jobs(spark, sf):
    """Fifty rows of customers at the smallest size take more rounds than jobs."""
    g = graph(spark, sf, "grid", width=3)
    before = spark.sparkContext.statusTracker().getJobIdsForGroup(None)
    r = al.sssp(g, 0, mode="plain")
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup(None)) - len(before)
    assert len(r.rounds) > 40
    assert jobs < 4 * superstep.LONG


def test_a_path_may_be_longer_than_any_constant(spark):
    """One round for each vertex at most: a chain of 10,100 hops ended with an error before."""
    n = 10_100
    g = tr.as_graph(spark, [(i, i + 1, 1) for i in range(n)])
    r = al.sssp(g, 0, mode="plain", parts=2)
    assert len(r.rounds) == n + 1
    assert sorted(tr.values(r).items()) == [(i, i) for i in range(n + 1)]


def test_values_that_never_settle_are_refused(spark, monkeypatch):
    monkeypatch.setattr(superstep, "LONG", 2)
    g = tr.as_graph(spark, [(0, 1, -1), (1, 2, 0), (2, 0, 0)])
    with pytest.raises(RuntimeError, match="no fixed point after 4 rounds"):
        al.sssp(g, 0, mode="plain", parts=2, check=False)
