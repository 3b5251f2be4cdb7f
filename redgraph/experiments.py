"""The published experiments on the given tables and generated graphs, each as one DataFrame.

Social and hub-heavy graphs are stood in for by ``trade`` and ``user_hop``, road networks by the
lattice ``grid`` and ``event_chain``, directed graphs with dangling ends by ``cust_supp``.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from redgraph.operators import algorithms as al
from redgraph.operators import baselines, metrics
from redgraph.operators import partition as pt
from redgraph.operators.graph import PropertyGraph, connect, random_weights
from redgraph.operators.superstep import RunResult
from redgraph.sources.generate import rmat, uniform
from redgraph.sources.tables import graph

SYSTEMS = ("plain", "short_circuit", "pulse", "predecessor", "peer", "master")
MATRIX = "algo string, system string, graph string, parts int, seconds double, rounds int, generated long, queued long"


def workload(spark: SparkSession, sf_dir: str, name: str) -> PropertyGraph:
    """A graph of the tables by name, or ``rmat`` and ``uniform`` with random weights, made connected."""
    if name == "rmat":
        return connect(random_weights(rmat(spark, 8, 8), 1, 100))
    if name == "uniform":
        return connect(random_weights(uniform(spark, 500, 4000), 1, 100))
    return graph(spark, sf_dir, name, **({"width": 10} if name == "grid" else {}))


def run_system(g: PropertyGraph, algo: str, system: str, parts: int = 8) -> RunResult:
    """One algorithm (``SSSP`` or ``WCC``) by one system."""
    if algo == "WCC":
        from redgraph.operators.graph import symmetrize

        g = symmetrize(g) if g.directed else g
    start = al._seeds(g, [0], 0) if algo == "SSSP" else g.ids().select("id", F.col("id").alias("val"))
    expression, weight = ("plus_weight", "w") if algo == "SSSP" else ("same", None)
    if system == "peer":
        return baselines.mirror_sync(g, start, expression=expression, parts=parts, weight=weight)
    placed = pt.assign(g, parts, "block", weight=weight)
    if system == "master":
        return baselines.master_worker(placed, start, expression=expression)
    if system == "predecessor":
        return baselines.predecessor(placed, start, expression=expression)
    return al.fixed_point(g, start, expression=expression, mode=system, placed=placed)


def comparison(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = ("trade", "user_hop", "grid", "rmat", "uniform"), algos: tuple[str, ...] = ("SSSP", "WCC"), systems: tuple[str, ...] = SYSTEMS, parts: int = 8) -> DataFrame:
    """Seconds, rounds and messages of every algorithm, system and graph."""
    rows = []
    for name in graphs:
        g = workload(spark, sf_dir, name)
        for algo in algos:
            for system in systems:
                began = time.perf_counter()
                r = run_system(g, algo, system, parts)
                rows.append((algo, system, name, parts, time.perf_counter() - began, len(r.rounds), r.total("generated"), r.total("queued") or r.total("reduce_msgs") + r.total("bcast_msgs")))
    return spark.createDataFrame(rows, MATRIX)


def strong_scaling(spark: SparkSession, sf_dir: str, name: str, algo: str = "SSSP", systems: tuple[str, ...] = ("plain", "pulse"), parts: tuple[int, ...] = (1, 2, 4, 8)) -> DataFrame:
    """One graph over growing numbers of owners, with and without fused rounds."""
    g = workload(spark, sf_dir, name)
    out = None
    for system in systems:
        rows = metrics.strong_scaling(spark, lambda p, s=system: run_system(g, algo, s, p), list(parts)).withColumn("system", F.lit(system))
        out = rows if out is None else out.unionByName(rows)
    return out


def weak_scaling(spark: SparkSession, algo: str = "SSSP", edges_per_part: int = 50_000, parts: tuple[int, ...] = (1, 2, 4)) -> DataFrame:
    """Recursive-matrix graphs whose edges grow with the owners."""

    def make(p: int) -> PropertyGraph:
        scale = max(4, (edges_per_part * p // 8).bit_length())
        g = random_weights(rmat(spark, scale, max(1, edges_per_part * p >> scale)), 1, 100)
        return connect(g) if algo == "SSSP" else g

    return metrics.weak_scaling(spark, make, lambda g, p: run_system(g, algo, "pulse", p), list(parts))


def phase_profile(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = ("trade", "user_hop", "grid")) -> DataFrame:
    """Modelled shares of edge lookup, reads and exchange in a run of the predecessor."""
    out = None
    for name in graphs:
        g = workload(spark, sf_dir, name)
        rows = metrics.phase_breakdown(spark, g, lambda g=g: run_system(g, "SSSP", "predecessor")).withColumn("graph", F.lit(name))
        out = rows if out is None else out.unionByName(rows)
    return out
