"""The queue of updates between owners: filling, folding, cutting into batches, delivering.

A mailbox row is ``from_part, to_part, dst, val`` (and ``seq`` where order matters).  Folding is a
grouping by sender and target, which Spark does before the exchange; delivery is one exchange by the
receiving owner.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from redgraph.functions.reduce import ReduceOp
from redgraph.operators.partition import Placed

ENTRY_BYTES = 16
_ROWS = 65_536


def emit(frontier: DataFrame, placed: Placed, value: Column, *, keep_order: bool = False, small: bool = False) -> DataFrame:
    """Candidates of all edges that leave the frontier (``part, id, val``): no exchange, the join is co-located.

    A frontier that is known to be ``small`` is looked up from the edges instead (vertex-centric), which
    spares sorting them; else both sides are sorted and merged (edge-centric).
    ``value`` is an expression over ``val`` (of the source) and ``w`` (of the edge).
    """
    e = placed.edges.withColumnRenamed("part", "from_part")
    if small:
        frontier = F.broadcast(frontier)
    rows = frontier.join(e, (F.col("part") == F.col("from_part")) & (F.col("id") == F.col("src"))).select("from_part", F.col("dst_part").alias("to_part"), "dst", value.alias("val"), "src")
    if keep_order:
        rows = rows.withColumn("seq", F.struct("from_part", "src"))
    return rows.drop("src")


def shorten(mailbox: DataFrame, op: ReduceOp) -> DataFrame:
    """One entry per sender and target, for operators whose updates may be folded in any order."""
    if not (op.commutative and op.associative):
        raise ValueError(f"{op.name} keeps every entry")
    return mailbox.groupBy("from_part", "to_part", "dst").agg(op.agg(F.col("val")).alias("val"))


def short_circuit(mailbox: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Updates that the sender owns itself, and those that must travel."""
    return mailbox.where("from_part = to_part"), mailbox.where("from_part <> to_part")


def chunk(mailbox: DataFrame, batch_size: int) -> DataFrame:
    """Number the fixed-size blocks of every (sender, receiver) queue; a queue is what one sender folded, so it is bounded by its own vertices' targets."""
    order = Window.partitionBy("from_part", "to_part").orderBy("dst", "val")
    return mailbox.withColumn("chunk", F.floor((F.row_number().over(order) - 1) / batch_size).cast("long"))


def batch_counts(mailbox: DataFrame, batch_size: int) -> DataFrame:
    """Per (sender, receiver): entries, batches and bytes; passes are the most batches of any pair."""
    return mailbox.groupBy("from_part", "to_part").agg(F.count(F.lit(1)).alias("entries")).select(
        "from_part", "to_part", "entries", F.ceil(F.col("entries") / batch_size).alias("batches"), (F.col("entries") * ENTRY_BYTES).alias("bytes"))


def deliver(mailbox: DataFrame, op: ReduceOp, parts: int) -> DataFrame:
    """``part, id, val`` at the owner: partly folded where it was made, one exchange, folded again."""
    sent = mailbox.select(F.col("to_part").alias("part"), F.col("dst").alias("id"), "val").repartitionById(parts, "part")
    return sent.groupBy("part", "id").agg(op.agg(F.col("val")).alias("val"))


def sync_batched(mailbox: DataFrame, state: DataFrame, op: ReduceOp, parts: int) -> DataFrame:
    """Fold, deliver and merge a mailbox into ``state(part, id, val)``."""
    return merge(state, deliver(shorten(mailbox, op), op, parts), op)


def sync_all_to_all(mailbox: DataFrame, state: DataFrame, op: ReduceOp, parts: int) -> DataFrame:
    """Deliver every raw entry in one exchange; folded by the receiver only."""
    sent = mailbox.select(F.col("to_part").alias("part"), F.col("dst").alias("id"), "val").repartitionById(parts, "part")
    got = sent.groupBy("part", "id").agg(op.agg(F.col("val")).alias("val"))
    return merge(state, got, op)


def sync_chunks(mailbox: DataFrame, state: DataFrame, op: ReduceOp, parts: int, batch_size: int) -> DataFrame:
    """The same result, one block of every queue at a time, until the queues are drained.

    All blocks travel in one exchange; each owner takes them in the order of their numbers and folds one
    at a time into its state, so it holds its state and one block of every sender.
    """
    blocks = chunk(shorten(mailbox, op), batch_size).select(F.col("to_part").alias("part"), F.col("dst").alias("id"), "val", "chunk")
    # its own values come before all blocks
    mine = state.select("part", "id", "val", F.lit(-1).cast("long").alias("chunk"))
    rows = mine.unionByName(blocks).repartitionById(parts, "part").sortWithinPartitions("chunk")

    def drain(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: dict[str, np.ndarray] | None = None
        at, ready, ahead = -1, [], None
        for batch in _with_end(batches):
            if batch is not None:
                number = batch.column("chunk").to_numpy()
                cuts = [0, *(np.flatnonzero(number[1:] != number[:-1]) + 1).tolist(), len(number)]
                pieces = [(int(number[a]), batch.slice(a, b - a)) for a, b in zip(cuts, cuts[1:], strict=False) if b > a]
            else:
                pieces = [(None, None)]
            for ahead, piece in pieces:
                if ready and ahead != at:
                    own, ready = _fold(own, pa.Table.from_batches(ready), op), []
                at = ahead
                if piece is not None:
                    ready.append(piece)
        if own is not None:
            for a in range(0, len(own["id"]), _ROWS):
                yield pa.RecordBatch.from_arrays([pa.array(own[n][a : a + _ROWS], t, mask=own["none"][a : a + _ROWS] if n == "val" else None) for n, t in (("part", pa.int32()), ("id", pa.int64()), ("val", pa.int64()))], names=["part", "id", "val"])

    return rows.mapInArrow(drain, "part int, id long, val long")


def _with_end(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch | None]:
    yield from batches
    yield None


def _fold(own: dict[str, np.ndarray] | None, rows: pa.Table, op: ReduceOp) -> dict[str, np.ndarray]:
    """An owner's values ``part, id, val, none`` sorted by id, with the rows of one block folded in."""
    none = rows.column("val").is_null().to_numpy()
    new = {"part": rows.column("part").to_numpy(), "id": rows.column("id").to_numpy(), "val": rows.column("val").fill_null(op.worst).to_numpy(), "none": none}
    if own is None:
        own = {k: v[:0] for k, v in new.items()}
    at = np.searchsorted(own["id"], new["id"])
    known = at < len(own["id"])
    known[known] = own["id"][at[known]] == new["id"][known]
    if not own["val"].flags.writeable:
        own["val"], own["none"] = own["val"].copy(), own["none"].copy()
    given = known & ~new["none"]
    op.at(own["val"], at[given], new["val"][given])
    own["none"][at[given]] = False
    if known.all():
        return own
    fresh = {k: v[~known] for k, v in new.items()}
    ids, slot = np.unique(fresh["id"], return_inverse=True)
    part, val, none = np.empty(len(ids), fresh["part"].dtype), np.full(len(ids), op.worst, np.int64), np.ones(len(ids), bool)
    part[slot] = fresh["part"]
    op.at(val, slot[~fresh["none"]], fresh["val"][~fresh["none"]])
    none[slot[~fresh["none"]]] = False
    joined = {k: np.concatenate([own[k], v]) for k, v in (("part", part), ("id", ids), ("val", val), ("none", none))}
    order = np.argsort(joined["id"], kind="stable")
    return {k: v[order] for k, v in joined.items()}


def merge(state: DataFrame, got: DataFrame, op: ReduceOp) -> DataFrame:
    """New values of ``state``; targets without a value take the update."""
    g = got.select(F.col("part").alias("gp"), F.col("id").alias("gi"), F.col("val").alias("gv"))
    both = state.join(g, (F.col("part") == F.col("gp")) & (F.col("id") == F.col("gi")), "full_outer")
    val = F.when(F.col("val").isNull(), F.col("gv")).when(F.col("gv").isNull(), F.col("val")).otherwise(op.merge(F.col("val"), F.col("gv")))
    return both.select(F.coalesce("part", "gp").alias("part"), F.coalesce("id", "gi").alias("id"), val.alias("val"))


def put(state: DataFrame, updates: DataFrame) -> DataFrame:
    """Immediate writes (``part, id, seq, val``): the last one wins."""
    last = updates.groupBy("part", "id").agg(F.max_by("val", "seq").alias("val"))
    g = last.select(F.col("part").alias("gp"), F.col("id").alias("gi"), F.col("val").alias("gv"))
    both = state.join(g, (F.col("part") == F.col("gp")) & (F.col("id") == F.col("gi")), "full_outer")
    return both.select(F.coalesce("part", "gp").alias("part"), F.coalesce("id", "gi").alias("id"), F.coalesce("gv", "val").alias("val"))


def lock_cycles(strategy: str, *, candidates: int = 0, shipped: int = 0, passes: int = 0, parts: int = 1) -> int:
    """Modelled lock/unlock pairs: two operand reads and one update each, or one lock per pass and owner."""
    if strategy == "per_element":
        return 2 * candidates + shipped
    if strategy == "batched":
        return passes * parts
    raise ValueError(strategy)


def window_slots(parts: int, batch_size: int) -> int:
    """Entries that a receiver holds at once: one batch from each sender."""
    return parts * batch_size
