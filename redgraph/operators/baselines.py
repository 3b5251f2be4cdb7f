"""The systems compared with, as communication patterns over the same rounds.

``predecessor``: every candidate is shipped in one burst, edges are searched and every read is locked;
``mirror_sync``: each part holds replicas of all ends of its edges, runs to a local fixed point, folds
changed replicas at their master and sends the result back to the replicas;
``master_worker``: all mail passes one coordinator.  Answers are the same; counters differ.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from redgraph.functions.reduce import MIN, ReduceOp
from redgraph.operators import local_engine, packed
from redgraph.operators.graph import PropertyGraph
from redgraph.operators.local_engine import KERNELS, MAIL, SCHEMA
from redgraph.operators.mailbox import lock_cycles
from redgraph.operators.packed import Packed
from redgraph.operators.partition import Placed, assign, working
from redgraph.operators.superstep import RunResult, run
from redgraph.session import cut, cut_placed, told


def predecessor(placed: Placed, start: DataFrame, *, expression: str = "plus_weight", op: ReduceOp = MIN, **more) -> RunResult:
    """Uncombined rounds, with the modelled costs of edge search and locks beside their counters."""
    result = run(placed, start, expression=expression, op=op, mode="uncombined", **more)
    search = placed.edges.groupBy("src").agg(F.count(F.lit(1)).alias("d")).agg(F.sum(F.col("d") * F.col("d"))).first()[0] or 0
    for r in result.rounds:
        r["lock_cycles"] = lock_cycles("per_element", candidates=r.get("generated", 0), shipped=r.get("queued", 0))
    if result.rounds:
        result.rounds[0]["edge_search_steps"] = int(search)
    return result


def _replica_pulse(part: int, state: pa.Table, edges: pa.Table, kernel: str, at, worst: int) -> pa.Table:
    """Run a part's replicas to a local fixed point; every far end counts as local, changed replicas are reported."""
    near = edges.set_column(edges.schema.get_field_index("dst_part"), "dst_part", pa.array(np.full(edges.num_rows, part, np.int32)))
    out = local_engine.pulse(part, state, near, kernel, at, worst, None, 1 << 30)
    kind = out.column("kind").to_numpy().copy()
    kind[kind == local_engine.STATE] = MAIL  # a changed replica is mail to its master
    return out.set_column(0, "kind", pa.array(kind))


def mirror_sync(g: PropertyGraph, start: DataFrame, *, expression: str = "plus_weight", op: ReduceOp = MIN, parts: int | None = None, scheme: str = "block", weight: str | None = "w", style: str = "fixpoint", max_rounds: int = 10_000) -> RunResult:
    """Masters and mirrors: two exchanges per phase, counted as ``reduce_msgs`` and ``bcast_msgs``.

    ``style='push'`` does one local round per phase instead of a local fixed point.
    """
    p = assign(g, parts, scheme, weight=weight)
    own, parts = p.of, p.parts
    ends = p.edges.select("part", F.col("src").alias("id")).unionByName(p.edges.select("part", F.col("dst").alias("id")))
    replicas = ends.unionByName(p.vertices.select("part", "id")).distinct()
    first = start.select("id", F.col("val").cast("long").alias("val"))
    state = replicas.join(first, "id", "left").select("part", "id", own(F.col("id")).alias("home"), "val", F.col("val").isNotNull().alias("changed"))
    state = cut_placed(state.repartitionById(parts, "part"), parts)
    # which parts hold a replica, kept at the master
    directory = cut_placed(state.select(F.col("home").alias("dh"), F.col("id").alias("di"), F.col("part").alias("bp")).repartitionById(parts, "dh"), parts)
    result = RunResult(state)
    at, worst = op.at, op.worst
    limit = 1 if style == "push" else None
    busy = None

    def work(key, mine: pa.Table, edges: pa.Table) -> pa.Table:
        if limit is None:
            return _replica_pulse(key[0].as_py(), mine.drop_columns(["home"]), edges, expression, at, worst)
        near = edges.set_column(edges.schema.get_field_index("dst_part"), "dst_part", pa.array(np.full(edges.num_rows, key[0].as_py(), np.int32)))
        out = local_engine.pulse(key[0].as_py(), mine.drop_columns(["home"]), near, expression, at, worst, 1, 1 << 30)
        return out.set_column(0, "kind", pa.array(np.where(out.column("kind").to_numpy() == local_engine.STATE, MAIL, out.column("kind").to_numpy()).astype(np.int32)))

    for _ in range(max_rounds):
        seen, back, watch = Observation(), Observation(), Observation()
        held, edges = working(busy, state, p.edges)
        out = held.groupBy("part").cogroup(edges.groupBy("part")).applyInArrow(work, SCHEMA)
        away = (F.col("kind") == MAIL) & (own(F.col("id")) != F.col("part"))
        out = cut(out.observe(seen, *[F.sum(n).alias(n) for n in ("generated", "accepted")], F.max("rounds").alias("local_rounds"), F.sum(away.cast("long")).alias("reduce_msgs")))
        moved = out.where(F.col("kind") == MAIL).select("part", "id", "val")
        # to the master and back: only mail moves, masters and the directory stay where they are
        mail = moved.select(own(F.col("id")).alias("up"), F.col("id").alias("ui"), "val").repartitionById(parts, "up")
        best = mail.groupBy("up", "ui").agg(op.agg(F.col("val")).alias("best"))
        old = state.where("part = home").select(F.col("part").alias("op_"), F.col("id").alias("oi"), F.col("val").alias("old"))
        fold = F.when(F.col("old").isNull(), F.col("best")).otherwise(op.merge(F.col("old"), F.col("best")))
        improved = best.join(old, (F.col("up") == F.col("op_")) & (F.col("ui") == F.col("oi"))).where(F.col("old").isNull() | (fold != F.col("old"))).select("up", "ui", fold.alias("best"))
        told_ = improved.join(directory, (F.col("up") == F.col("dh")) & (F.col("ui") == F.col("di"))).observe(back, F.sum((F.col("bp") != F.col("dh")).cast("long")).alias("bcast_msgs"))
        told_ = told_.select("bp", F.col("ui").alias("bi"), "best").repartitionById(parts, "bp")
        mine = moved.select(F.col("part").alias("mp"), F.col("id").alias("mi"), F.col("val").alias("mv")).repartitionById(parts, "mp")
        new = state.join(told_, (F.col("part") == F.col("bp")) & (F.col("id") == F.col("bi")), "left").join(mine, (F.col("part") == F.col("mp")) & (F.col("id") == F.col("mi")), "left")
        local = F.coalesce("mv", "val")  # what the replica itself knows after its local rounds
        value = F.coalesce("best", local)
        changed = ~value.eqNullSafe(local) if limit is None else ~value.eqNullSafe(F.col("val"))
        new = new.select("part", "id", "home", value.alias("val"), changed.alias("changed"))
        state = cut_placed(new.observe(watch, F.sum(F.col("changed").cast("long")).alias("changed"), F.collect_set(F.when(F.col("changed"), F.col("part"))).alias("busy")), parts)
        counts = told(seen) | told(back) | told(watch)
        busy = counts.pop("busy", None) or None
        result.rounds.append(counts)
        if not (counts.pop("changed") if "changed" in counts else state.where("changed").count()):
            break
    else:
        raise RuntimeError(f"no fixed point after {max_rounds} rounds")
    result.df = state.where("part = home AND val IS NOT NULL").select("part", "id", "val")
    return result


def master_worker(placed: Placed, start: DataFrame, *, expression: str = "plus_weight", op: ReduceOp = MIN, max_rounds: int = 10_000) -> RunResult:
    """Fused rounds whose mail is folded by one coordinator task and dealt again: two hops and a serial step.

    The coordinator is the bottleneck that this baseline is about; use it for comparison only.
    """
    first = start.select("id", F.col("val").cast("long").alias("val"))
    state = cut_placed(placed.vertices.join(first, "id", "left").select("part", "id", "val", F.col("val").isNotNull().alias("changed")).repartitionById(placed.parts, "part"), placed.parts)
    result = RunResult(state)
    at, worst = op.at, op.worst
    busy = None

    blocks = isinstance(placed, Packed)
    names = ("generated", "local", "remote_raw", "queued", "accepted")
    told_ = {n: F.col("told")[k] if blocks else F.col(n) for k, n in enumerate(names)}
    rounds = F.col("told")[len(packed.COUNTERS) - 1] if blocks else F.col("rounds")

    def work(key, mine: pa.Table, edges: pa.Table) -> pa.Table:
        if blocks:
            return packed.step(key[0].as_py(), mine, edges, expression, at, worst, "pulse", None, 1024)
        return local_engine.pulse(key[0].as_py(), mine, edges, expression, at, worst, None, 1024)

    for _ in range(max_rounds):
        seen, watch, hub = Observation(), Observation(), Observation()
        held, edges = working(busy, state, placed.blocks if blocks else placed.edges)
        out = held.groupBy("part").cogroup(edges.groupBy("part")).applyInArrow(work, packed.OUT if blocks else SCHEMA)
        out = cut(out.observe(seen, *[F.sum(c).alias(n) for n, c in told_.items()], F.max(rounds).alias("local_rounds")))
        mail = out.where(F.col("kind") == MAIL).select("part", "id", "val").coalesce(1)
        mail = mail.observe(hub, F.count(F.lit(1)).alias("through_master")).groupBy("part", "id").agg(op.agg(F.col("val")).alias("mail"))
        own = out.where(F.col("kind") == local_engine.STATE).select(F.col("part").alias("op_"), F.col("id").alias("oi"), F.col("val").alias("own")).repartitionById(placed.parts, "op_")
        got = mail.select(F.col("part").alias("gp"), F.col("id").alias("gi"), "mail").repartitionById(placed.parts, "gp")
        new = state.join(own, (F.col("part") == F.col("op_")) & (F.col("id") == F.col("oi")), "left").join(got, (F.col("part") == F.col("gp")) & (F.col("id") == F.col("gi")), "left")
        base = F.coalesce("own", "val")
        value = F.when(base.isNull(), F.col("mail")).when(F.col("mail").isNull(), base).otherwise(op.merge(base, F.col("mail")))
        new = new.select("part", "id", value.alias("val"), (~value.eqNullSafe(base)).alias("changed"))
        state = cut_placed(new.observe(watch, F.sum(F.col("changed").cast("long")).alias("changed"), F.collect_set(F.when(F.col("changed"), F.col("part"))).alias("busy")), placed.parts)
        counts = told(seen) | told(hub) | told(watch)
        busy = counts.pop("busy", None) or None
        result.rounds.append(counts)
        if not (counts.pop("changed") if "changed" in counts else state.where("changed").count()):
            break
    else:
        raise RuntimeError(f"no fixed point after {max_rounds} rounds")
    result.df = state.where("val IS NOT NULL").select("part", "id", "val")
    return result
