"""Measures: times, phases, update curves, costs, speed-ups and skew, each as rows of a DataFrame."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from redgraph.operators.graph import PropertyGraph
from redgraph.operators.mailbox import lock_cycles
from redgraph.operators.partition import Placed
from redgraph.operators.superstep import RunResult


def timed(action: Callable[[], object], repeats: int = 5) -> list[float]:
    """Seconds of each run of ``action``."""
    out = []
    for _ in range(repeats):
        began = time.perf_counter()
        action()
        out.append(time.perf_counter() - began)
    return out


def with_limit(spark: SparkSession, action: Callable[[], object], seconds: float) -> tuple[object | None, float | None]:
    """The result and time of ``action``, or ``(None, None)`` if its jobs ran beyond the limit and were cancelled."""
    tag = f"limit-{time.monotonic_ns()}"
    late = threading.Event()

    def stop() -> None:
        late.set()
        spark.interruptTag(tag)

    timer = threading.Timer(seconds, stop)
    spark.addTag(tag)
    timer.start()
    began = time.perf_counter()
    try:
        result = action()
        return (None, None) if late.is_set() else (result, time.perf_counter() - began)
    except Exception:
        if late.is_set():
            return None, None
        raise
    finally:
        timer.cancel()
        spark.removeTag(tag)


def edge_search_cost(g: PropertyGraph) -> DataFrame:
    """Steps to find every neighbour's edge by search (sum of squared degrees) and by iteration (sum of degrees)."""
    d = g.edges.groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    return d.agg(F.sum(F.col("d") * F.col("d")).alias("search_steps"), F.sum("d").alias("iteration_steps"))


def update_curve(result: RunResult) -> DataFrame:
    """``round, accepted``: vertices improved in each round, from cold start over the peak to the tail."""
    spark = result.df.sparkSession
    return spark.createDataFrame([(k + 1, int(r.get("accepted") or 0)) for k, r in enumerate(result.rounds)], "round long, accepted long")


def curve_shape(curve: DataFrame) -> DataFrame:
    """Rounds up to the peak, rounds after it, and the largest change from one round to the next."""
    w = Window.orderBy("round")  # one row per round
    c = curve.withColumn("step", F.col("accepted") - F.lag("accepted").over(w)).withColumn("moving", F.avg("accepted").over(w.rowsBetween(-1, 1)))
    peak = F.max(F.struct("accepted", (-F.col("round")).alias("r")))["r"]
    return c.agg((-peak).alias("cold_start"), (F.max("round") + peak).alias("tail"), F.max("step").alias("steepest"), F.max("moving").alias("highest_mean"))


def cost_table(result: RunResult, placed: Placed, batch_size: int = 1024) -> DataFrame:
    """Messages, bytes, batches, rounds, reads and modelled lock cycles of one run."""
    spark = result.df.sparkSession
    total = result.total
    passes = sum(-(-int(r.get("queued") or 0) // batch_size) for r in result.rounds)
    rows = {
        "global_rounds": len(result.rounds), "local_rounds": total("local_rounds"), "generated": total("generated"), "local": total("local"), "remote_raw": total("remote_raw"), "queued": total("queued"), "accepted": total("accepted"),
        "bytes": total("bytes"), "batches": total("batches") or passes, "gets_local": 2 * total("generated"), "gets_remote": 0, "locks_per_element": lock_cycles("per_element", candidates=total("generated"), shipped=total("queued")),
        "locks_batched": lock_cycles("batched", passes=passes, parts=placed.parts),
    }
    return spark.createDataFrame([(k, int(v)) for k, v in rows.items()], "name string, value long")


def redundancy(result: RunResult, g: PropertyGraph) -> float:
    """Candidates generated over the fewest that reach all: one per edge that leaves a reached vertex."""
    least = g.edges.join(result.df.select(F.col("id").alias("src")), "src", "left_semi").count()
    return result.total("generated") / max(least, 1)


def phase_breakdown(spark: SparkSession, g: PropertyGraph, run: Callable[[], RunResult]) -> DataFrame:
    """Seconds of one run beside the modelled shares of edge lookup, reads and exchange."""
    began = time.perf_counter()
    result = run()
    seconds = time.perf_counter() - began
    search = edge_search_cost(g).first()
    work = {"edge_lookup": search["search_steps"], "get": 2 * result.total("generated"), "sync_reduce": result.total("queued")}
    total = max(sum(work.values()), 1)
    return spark.createDataFrame([(k, int(v), seconds * v / total) for k, v in work.items()] + [("total", int(total), seconds)], "phase string, steps long, seconds double")


def speedup(table: DataFrame, ours: str, other: str, *, how: str = "ratio_of_means", limit: float | None = None) -> DataFrame:
    """How much faster ``ours`` is than ``other`` by algorithm and setup, from ``algo, system, setup, graph, seconds``.

    ``limit`` is charged for runs that did not end (null seconds); without it such graphs are left out.
    """
    s = F.coalesce("seconds", F.lit(limit)) if limit is not None else F.col("seconds")
    a = table.where(F.col("system") == ours).select("algo", "setup", "graph", s.alias("a"))
    b = table.where(F.col("system") == other).select("algo", "setup", "graph", s.alias("b"))
    pair = a.join(b, ["algo", "setup", "graph"]).where("a IS NOT NULL AND b IS NOT NULL")
    value = {"mean_ratio": F.avg(F.col("b") / F.col("a")), "ratio_of_means": F.avg("b") / F.avg("a"), "geomean": F.exp(F.avg(F.log(F.col("b") / F.col("a"))))}[how]
    return pair.groupBy("algo", "setup").agg(value.alias("speedup"), F.sum((F.col("a") < F.col("b")).cast("long")).alias("wins"), F.count(F.lit(1)).alias("graphs"))


def counters_cube(counters: DataFrame) -> DataFrame:
    """Totals of counters by every subset of algorithm, mode and graph."""
    return counters.cube("algo", "mode", "graph").agg(F.sum("value").alias("value"), F.count(F.lit(1)).alias("n"))


def rank_error(a: DataFrame, b: DataFrame) -> DataFrame:
    """L1 and L-infinity distance of two rank tables ``id, rank``; missing ranks count as 0."""
    gap = F.abs(F.coalesce(F.col("ra"), F.lit(0.0)) - F.coalesce(F.col("rb"), F.lit(0.0)))
    return a.select("id", F.col("rank").alias("ra")).join(b.select("id", F.col("rank").alias("rb")), "id", "full_outer").agg(F.sum(gap).alias("l1"), F.max(gap).alias("linf"))


def strong_scaling(spark: SparkSession, run: Callable[[int], RunResult], parts: list[int], repeats: int = 1) -> DataFrame:
    """One graph, growing numbers of owners: ``parts, seconds, rounds, speedup``."""
    rows = []
    for p in parts:
        kept: list[RunResult] = []
        seconds = timed(lambda p=p, kept=kept: kept.append(run(p)), repeats)
        rows.append((p, sum(seconds) / len(seconds), len(kept[-1].rounds)))
    return spark.createDataFrame([(p, s, r, rows[0][1] / s) for p, s, r in rows], "parts int, seconds double, rounds int, speedup double")


def weak_scaling(spark: SparkSession, make: Callable[[int], PropertyGraph], run: Callable[[PropertyGraph, int], RunResult], parts: list[int]) -> DataFrame:
    """Edges grow with the owners: ``parts, edges, seconds, efficiency``."""
    rows = []
    for p in parts:
        g = make(p)
        edges = g.edges.count()
        rows.append((p, edges, timed(lambda g=g, p=p: run(g, p), 1)[0]))
    return spark.createDataFrame([(p, e, s, rows[0][2] / s) for p, e, s in rows], "parts int, edges long, seconds double, efficiency double")
