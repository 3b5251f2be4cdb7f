"""Rounds of a reduction program over a placed graph.

=================  ==============================================================================
mode               one global round
=================  ==============================================================================
``uncombined``     expand the frontier, ship every candidate
``plain``          fold candidates per sender and target first; local targets also go by mail
``short_circuit``  local targets are updated at once, foreign ones folded and shipped
``pulse``          local rounds until nothing local moves, then one exchange of the best values
``bounded_pulse``  the same with at most ``max_local_rounds`` local rounds; the rest is carried over
=================  ==============================================================================

Each round is one job: it reads the placed state and edges without an exchange, ships the mail in one
exchange, merges it, and writes the new state by a reliable checkpoint that keeps the placement.  The
driver sees counters only.

A run that is not over after ``LONG`` rounds has long paths and small frontiers: then a job a round costs far more
than its work.  If all edges fit one task, the rounds that are left run there, with the same owners, mail and counters.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from itertools import count

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from redgraph.functions.reduce import MIN, ReduceOp
from redgraph.operators import local_engine, packed
from redgraph.operators.local_engine import COUNTS, MAIL, SCHEMA, STATE
from redgraph.operators.mailbox import ENTRY_BYTES
from redgraph.operators.packed import Packed
from redgraph.operators.partition import Placed, working
from redgraph.session import cut, cut_placed, fixed, scoped, told

#: A frontier of at most so many rows (24 bytes each) is sent to all tasks; its size is counted by the round before.
SMALL_FRONTIER = 200_000
#: Rounds after which a run over at most so many edges (some 100 bytes each) goes on in one task.
LONG, GATHERED = 12, 1 << 22
#: The same for edges in blocks (some 60 bytes each while they are indexed).
GATHERED_BLOCKS = 1 << 23
MODES = ("uncombined", "plain", "short_circuit", "pulse", "bounded_pulse")
EXPRESSIONS: dict[str, Callable[[Column, Column], Column]] = {"plus_weight": lambda v, w: v + w, "same": lambda v, w: v, "plus_one": lambda v, w: v + 1, "least_with_weight": lambda v, w: F.least(v, w)}


@dataclass
class RunResult:
    """The result ``(part, id, val)``, the counters of each round and the plan of a round."""

    df: DataFrame
    rounds: list[dict] = field(default_factory=list)
    plan: str = ""

    def total(self, name: str) -> int:
        return sum(r.get(name) or 0 for r in self.rounds)

    def counters(self, **labels) -> DataFrame:
        """``round, name, value`` and the given labels, one row per counter."""
        spark = self.df.sparkSession
        rows = [(k, n, int(v or 0)) for k, r in enumerate(self.rounds) for n, v in r.items()]
        out = spark.createDataFrame(rows, "round int, name string, value long")
        for k, v in labels.items():
            out = out.withColumn(k, F.lit(v))
        return out


def run(
    placed: Placed, start: DataFrame, *, expression: str = "plus_weight", op: ReduceOp = MIN, mode: str = "plain", max_local_rounds: int | None = None, max_rounds: int | None = None, batch_size: int = 1024, traversal: str = "auto", explain: bool = False
) -> RunResult:
    """Repeat until no vertex changes.  ``start`` has ``id, val`` of the first frontier; others have no value.

    ``traversal`` is ``vertex`` (look small frontiers up from the edges), ``edge`` (merge with all edges) or
    ``auto``, which takes the frontier's counted size; it concerns the two modes without local rounds.
    Without ``max_rounds`` a run may take as many rounds as its longest path has hops, so at most one for each vertex
    and one more that changes nothing; values that still change then never settle (a cycle that improves itself).
    """
    if traversal not in ("vertex", "edge", "auto"):
        raise ValueError(f"unknown traversal {traversal}")
    if mode not in MODES:
        raise ValueError(f"unknown mode {mode}")
    if not op.fusible:
        raise ValueError(f"{op.name} cannot be iterated to a fixed point: it is not repeat-safe")
    # every vertex has a row, unreached ones without a value: joins from the left then keep the placement
    first = start.select("id", F.col("val").cast("long").alias("val"))
    owned = placed.vertices.join(first, "id", "left")
    state = cut_placed(owned.select("part", "id", "val", F.col("val").isNotNull().alias("changed")).repartitionById(placed.parts, "part"), placed.parts)
    result = RunResult(state)
    rounds = 1 if mode == "short_circuit" else max_local_rounds if mode == "bounded_pulse" else None
    steps = _Steps(placed, expression, op)
    changed = busy = None  # not counted before the first round
    for k in count():
        if k == max_rounds:
            raise RuntimeError(f"no fixed point after {max_rounds} rounds")
        watch = Observation()
        small = changed is not None and changed <= SMALL_FRONTIER and traversal != "edge"
        if isinstance(placed, Packed):
            new, seen = steps.packed_round(state, mode, rounds, batch_size, watch, busy)
        elif mode in ("uncombined", "plain"):
            new, seen = steps.mail_round(state, mode == "plain", watch, small)
        else:
            new, seen = steps.pulse_round(state, rounds, batch_size, watch, busy)
        if explain and not k:
            with scoped(state.sparkSession, fixed(placed.parts)):
                result.plan = new._jdf.queryExecution().toString()
        state = cut_placed(new, placed.parts)
        counts = told(seen) | told(watch)
        busy = counts.pop("busy", None) or None
        changed = counts.pop("changed") if "changed" in counts else state.where("changed").count()
        counts["accepted"] = (counts.get("accepted") or 0) + (counts.pop("by_mail", 0) or 0)
        counts["bytes"] = ENTRY_BYTES * (counts.get("queued") or 0)
        result.rounds.append(counts)
        if not changed:
            break
        if k + 1 == LONG and max_rounds is None:
            max_rounds = max(placed.vertices.count(), LONG) + 1
        if k + 1 == LONG and traversal == "auto" and placed.edges.count() <= (GATHERED_BLOCKS if isinstance(placed, Packed) else GATHERED):
            result.df, more = _gathered(state, placed, expression, op, mode, rounds, max_rounds - LONG, batch_size)
            result.rounds += more
            return result
    result.df = state.where("val IS NOT NULL").select("part", "id", "val")
    return result


def _gathered(state: DataFrame, placed: Placed, expression: str, op: ReduceOp, mode: str, limit: int | None, max_rounds: int, batch_size: int) -> tuple[DataFrame, list[dict]]:
    """The result and the counters of all rounds that are left, run in one task."""
    at, worst = op.at, op.worst
    blocks = isinstance(placed, Packed)

    def work(mine: pa.Table, edges: pa.Table) -> pa.Table:
        return local_engine.remaining(mine, packed.unpacked(edges) if blocks else edges, expression, at, worst, mode, limit, max_rounds, batch_size)

    one = F.lit(0).alias("all")
    mine = state.select(one, "part", "id", "val", "changed")
    edges = placed.blocks.select(one, *placed.blocks.columns) if blocks else placed.edges.select(one, "src", "dst", "w")
    out = cut(mine.groupBy("all").cogroup(edges.groupBy("all")).applyInArrow(work, SCHEMA))
    told_ = out.where(F.col("kind") == COUNTS).orderBy("id").collect()  # one row for each round
    if not told_ or told_[-1].more:
        raise RuntimeError(f"no fixed point after {max_rounds + LONG} rounds")
    names = ["generated", "local", "remote_raw", "queued", "accepted"] + ([] if mode in ("uncombined", "plain") else ["batches"])
    rounds = [{n: r[n] for n in names} | ({} if mode in ("uncombined", "plain") else {"local_rounds": r["rounds"]}) | {"bytes": ENTRY_BYTES * r["queued"]} for r in told_]
    return out.where(F.col("kind") == STATE).select("part", "id", "val"), rounds


class _Steps:
    """The columns of a round over ``placed``, built once per run: planning a round then takes few calls on the driver."""

    def __init__(self, placed: Placed, expression: str, op: ReduceOp):
        self.placed, self.expression, self.op = placed, expression, op
        fold = lambda a, b: F.when(a.isNull(), b).when(b.isNull(), a).otherwise(op.merge(a, b))
        base = fold(F.col("val"), F.col("own"))
        new = fold(base, F.col("mail"))
        by_mail = ~new.eqNullSafe(base)
        self.owned = (F.col("part") == F.col("up")) & (F.col("id") == F.col("ui"))
        self.after = [F.col("part"), F.col("id"), new.alias("val"), (by_mail | F.coalesce("more", F.lit(False))).alias("changed"), by_mail.alias("by_mail")]
        # one number per owner at most
        self.counts = [*[F.sum(F.col(n).cast("long")).alias(n) for n in ("changed", "by_mail")], F.collect_set(F.when(F.col("changed"), F.col("part"))).alias("busy")]
        self.edges = placed.edges.withColumnRenamed("part", "from_part").withColumnRenamed("dst_part", "to_part")
        self.leaving = (F.col("part") == F.col("from_part")) & (F.col("id") == F.col("src"))
        self.ends = [F.col(n) for n in ("from_part", "to_part", "dst")]
        self.value = EXPRESSIONS[expression](F.col("val"), F.col("w"))
        self.folded = [op.agg(self.value).alias("val"), F.count(F.lit(1)).alias("n")]
        near = F.when(F.col("from_part") == F.col("to_part"), F.col("n")).otherwise(0)
        self.mail_counts = [F.sum("n").alias("generated"), F.sum(near).alias("local"), F.sum(F.col("n") - near).alias("remote_raw"), F.count(F.lit(1)).alias("queued")]
        self.sent = [F.col("to_part").alias("up"), F.col("dst").alias("ui"), F.col("val").alias("sent")]
        self.got = op.agg(F.col("sent")).alias("mail")
        self.nothing = [F.col("up"), F.col("ui"), F.lit(None).cast("long").alias("own"), F.col("mail"), F.lit(False).alias("more")]
        kind = lambda k, name: op.agg(F.when(F.col("kind") == k, F.col("val"))).alias(name)
        self.both = [kind(STATE, "own"), kind(MAIL, "mail"), F.max("more").alias("more")]
        names = ("generated", "local", "remote_raw", "queued", "accepted", "batches")
        self.pulse_counts = [*[F.sum(n).alias(n) for n in names], F.max("rounds").alias("local_rounds")]
        self.packed_counts = [F.sum(F.col("told")[k]).alias(n) for k, n in enumerate(names)]
        self.out = [F.col("kind"), F.col("part").alias("up"), F.col("id").alias("ui"), F.col("val"), F.col("more")]

    def merged(self, state: DataFrame, updates: DataFrame, watch: Observation) -> DataFrame:
        """State joined with its updates ``up, ui, own, mail, more``: both sides are placed, so nothing moves."""
        both = state.join(updates, self.owned, "left")
        return both.select(*self.after).observe(watch, *self.counts).select("part", "id", "val", "changed")

    def mail_round(self, state: DataFrame, combine: bool, watch: Observation, small: bool) -> tuple[DataFrame, Observation]:
        """Expand, fold and merge with DataFrame operators only; a small frontier is looked up from the edges."""
        seen = Observation()
        frontier = state.where("changed").select("part", "id", "val")
        rows = (F.broadcast(frontier) if small else frontier).join(self.edges, self.leaving)
        mail = rows.groupBy(*self.ends).agg(*self.folded) if combine else rows.select(*self.ends, self.value.alias("val"), F.lit(1).cast("long").alias("n"))
        sent = mail.observe(seen, *self.mail_counts).select(*self.sent).repartitionById(self.placed.parts, "up")
        return self.merged(state, sent.groupBy("up", "ui").agg(self.got).select(*self.nothing), watch), seen

    def pulse_round(self, state: DataFrame, rounds: int | None, batch_size: int, watch: Observation, busy: list[int] | None = None) -> tuple[DataFrame, Observation]:
        """Run each owner's local rounds in one task, ship what leaves it, merge; only the edges of ``busy`` owners are handed out."""
        seen = Observation()
        expression, at, worst = self.expression, self.op.at, self.op.worst

        def work(key: tuple[pa.Scalar, ...], mine: pa.Table, edges: pa.Table) -> pa.Table:
            return local_engine.pulse(key[0].as_py(), mine, edges, expression, at, worst, rounds, batch_size)

        mine, edges = working(busy, state, self.placed.edges)
        out = mine.groupBy("part").cogroup(edges.groupBy("part")).applyInArrow(work, SCHEMA).observe(seen, *self.pulse_counts)
        # the row of counters travels too: an exchange without rows would be dropped with what was observed below it
        sent = out.select(*self.out).repartitionById(self.placed.parts, "up").where(F.col("kind") != COUNTS)
        return self.merged(state, sent.groupBy("up", "ui").agg(*self.both), watch), seen

    def packed_round(self, state: DataFrame, mode: str, rounds: int | None, batch_size: int, watch: Observation, busy: list[int] | None = None) -> tuple[DataFrame, Observation]:
        """A round of any mode over edges in blocks: one task for each owner that has work, one exchange of mail."""
        seen = Observation()
        expression, at, worst = self.expression, self.op.at, self.op.worst

        def work(key: tuple[pa.Scalar, ...], mine: pa.Table, blocks: pa.Table) -> pa.Table:
            return packed.step(key[0].as_py(), mine, blocks, expression, at, worst, mode, rounds, batch_size)

        mine, blocks = working(busy, state, self.placed.blocks)
        counts = self.packed_counts[:5] if mode in ("uncombined", "plain") else [*self.packed_counts, F.max(F.col("told")[len(packed.COUNTERS) - 1]).alias("local_rounds")]
        out = mine.groupBy("part").cogroup(blocks.groupBy("part")).applyInArrow(work, packed.OUT).observe(seen, *counts)
        sent = out.select(*self.out).repartitionById(self.placed.parts, "up").where(F.col("kind") != COUNTS)
        return self.merged(state, sent.groupBy("up", "ui").agg(*self.both), watch), seen
