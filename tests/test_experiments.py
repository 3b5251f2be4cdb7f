"""Traversals, functions in SQL, and the published experiments at the smallest scale."""

import pandas as pd
import pytest
from pyspark.sql import functions as F

from redgraph import experiments
from redgraph.functions import udf
from redgraph.operators import algorithms as al
from redgraph.operators.graph import adjacency
from test_rounds import EDGES, as_graph, values

D = "/root/testdata/sf0.001"


@pytest.mark.parametrize("mode", ["plain", "uncombined"])
def test_traversals_agree(spark, mode):
    g = as_graph(spark, EDGES)
    runs = [al.sssp(g, 0, mode=mode, parts=2, traversal=t) for t in ("vertex", "edge", "auto")]
    assert all(values(r) == values(runs[0]) and r.rounds == runs[0].rounds for r in runs)
    with pytest.raises(ValueError):
        al.sssp(g, 0, traversal="sideways")


def test_functions_in_sql(spark):
    udf.register(spark)
    adjacency(as_graph(spark, EDGES)).createOrReplaceTempView("adj")
    assert {tuple(r) for r in spark.sql("SELECT n.* FROM adj, LATERAL neighbours(id, neighbours) n").collect()} == set(EDGES)

    def twice(x: pd.Series) -> pd.Series:
        return x * 2

    assert spark.range(3).select(udf.expression(twice)(F.col("id")).alias("x")).agg(F.sum("x")).first()[0] == 6


def test_comparison(spark):
    rows = experiments.comparison(spark, D, graphs=("user_hop",), algos=("SSSP",), systems=("plain", "pulse", "predecessor", "master"), parts=4).collect()
    by = {r.system: r for r in rows}
    assert by["plain"].queued <= by["predecessor"].queued and by["pulse"].rounds <= by["plain"].rounds


def test_scaling_and_profile(spark):
    assert experiments.strong_scaling(spark, D, "user_hop", systems=("pulse",), parts=(1, 2)).count() == 2
    assert experiments.weak_scaling(spark, "WCC", 200, (1, 2)).count() == 2
    assert experiments.phase_profile(spark, D, ("user_hop",)).count() == 4
