"""Minimum-cost repair of role sequences, then rendering.

A legal conversation is an optional system turn, then user and assistant turns in alternation, ending
with an assistant turn.  Each input turn may open a turn of its role, be relabelled, be merged into
the turn before, or be preceded by an inserted empty turn; every choice has a cost and dynamic
programming over the automaton's four states finds the cheapest repair of the whole sequence.

Costs compose as (min, +) matrices, one per turn, so a conversation of any length is solved in
blocks: each block reduces to a 4 x 4 matrix, the matrices of a conversation fix the state at each
block border, and blocks are then solved apart.  Turns are put in order once, over all tasks, and
written; a block is at most ``BLOCK_TURNS`` neighbours of that order, so turns of equal number, or of
no conversation, are cut into blocks like any others.  What meets in one task of a conversation is one
small matrix per block.  Output is one piece of rendered text per input turn; the pieces of a
conversation, joined in order, are the repaired conversation.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from redgraph.session import staged, task_count

ROLES = ("start", "system", "user", "assistant")
LEGAL = {0: (1, 2), 1: (2,), 2: (3,), 3: (2,)}
MERGE, RELABEL, UNKNOWN, INSERT = 1, 4, 2, 2
BLOCK_TURNS = 4096
_FAR = 1 << 40


def _moves(role: int) -> list[tuple[int, int, int, str, int | None]]:
    """``(from, to, cost, action, inserted)`` for an input turn; role 0 stands for an unknown one."""
    out = []
    relabel = lambda q: 0 if q == role else UNKNOWN if role == 0 else RELABEL
    for p in range(4):
        for q in LEGAL[p]:
            out.append((p, q, relabel(q), "keep" if q == role else "relabel", None))
        if p:
            out.append((p, p, MERGE + relabel(p), "merge" if p == role else "relabel+merge", None))
        for x in LEGAL[p]:
            for q in LEGAL[x]:
                out.append((p, q, INSERT + relabel(q), "insert" if q == role else "insert+relabel", x))
    return out


MOVES = [_moves(r) for r in range(4)]
#: Empty turns that complete a conversation, by its last state; a conversation has at least one turn.
ENDING = {1: (2, 3), 2: (3,), 3: ()}


def role_code(role: str | None) -> int:
    r = (role or "").strip().lower()
    return ROLES.index(r) if r in ROLES[1:] else 0


def forward(roles: list[int], cost: list[int]) -> tuple[list[int], list[list[int]]]:
    """Cheapest cost of each state after the turns, and the index of the move into it at each turn.

    Of equally cheap moves the first of the list wins: no insertion before insertion, opening before merging.
    """
    back = []
    for r in roles:
        after, via = [_FAR] * 4, [-1] * 4
        for k, (p, q, c, _, _) in enumerate(MOVES[r]):
            if cost[p] + c < after[q]:
                after[q], via[q] = cost[p] + c, k
        cost = after
        back.append(via)
    return cost, back


def solve(roles: list[int], entry: int, leave: int | None) -> list[tuple[int, int, str, int | None]]:
    """The moves ``(from, to, action, inserted)`` from state ``entry`` to ``leave`` (None: any, completed at the end)."""
    cost, back = forward(roles, [0 if s == entry else _FAR for s in range(4)])
    if leave is None:
        leave = min((3, 2, 1), key=lambda s: cost[s] + INSERT * len(ENDING[s]))
    out = []
    for r, via in zip(reversed(roles), reversed(back), strict=True):
        p, q, _, action, inserted = MOVES[r][via[leave]]
        out.append((p, q, action, inserted))
        leave = p
    return out[::-1]


def block_matrix(roles: list[int]) -> list[int]:
    return [c for s in range(4) for c in forward(roles, [0 if x == s else _FAR for x in range(4)])[0]]


def borders(matrices: list[list[int]]) -> list[int]:
    """State before each block and after the last one, on the cheapest completed path."""
    cost, back = [0, _FAR, _FAR, _FAR], []
    for m in matrices:
        ways = np.array(cost)[:, None] + np.array(m).reshape(4, 4)
        back.append(ways.argmin(axis=0))
        cost = ways.min(axis=0).tolist()
    state = min((3, 2, 1), key=lambda s: cost[s] + INSERT * len(ENDING[s]))
    out = [state]
    for via in reversed(back):
        state = int(via[state])
        out.append(state)
    return out[::-1]


def escape(text: str | None) -> str:
    """Text cannot open or close a turn: the opening bracket of a tag is set apart."""
    return (text or "").replace("<|", "< |")


def opening(role: int) -> str:
    return f"<|{ROLES[role]}|>\n"


CLOSING = "\n<|end|>\n"


def piece(move: tuple[int, int, str, int | None], text: str | None, last: bool) -> str:
    p, q, action, inserted = move
    if action.endswith("merge"):
        head = "\n\n"
    else:
        head = (CLOSING if p else "") + (opening(inserted) + CLOSING if inserted else "") + opening(q)
    tail = CLOSING + "".join(opening(x) + CLOSING for x in ENDING[q]) if last else ""
    return head + escape(text) + tail


def repair(turns: DataFrame, *, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text", block_turns: int = BLOCK_TURNS) -> DataFrame:
    """Per input turn: ``conv, turn, role, action, new_role, rendered, at``; ``at`` orders the turns of all conversations.

    Turns are ordered by turn (nulls first), then role and text, so ties and repeated rows have a
    fixed order.  Rows with a null conversation form one conversation.  Unknown and null roles must be
    relabelled or merged; null texts render as empty.  An empty table gives no rows.
    """
    spark = turns.sparkSession
    tasks = task_count(spark)
    rows = turns.select(F.col(conv_col).alias("__conv"), F.col(turn_col).alias("__turn"), F.col(role_col).alias("__role"), F.col(text_col).alias("__text"))
    # rows equal in all that orders them are dealt by a random number: any order of theirs is the same
    by = [F.col(c).asc_nulls_first() for c in ("__conv", "__turn", "__role", "__text")]
    sorted_ = rows.withColumn("__any", F.rand(1)).repartitionByRange(tasks, *by, "__any").sortWithinPartitions(*by, "__any").drop("__any")
    rows = staged(sorted_.withColumn("__at", F.monotonically_increasing_id()), "chat-turns")
    rows = rows.withColumn("__block", F.expr(f"__at div {block_turns}"))
    order = ["__conv", "__block", "__at"]
    conv = T.StructField("__conv", turns.schema[conv_col].dataType)

    def matrices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, group in _runs(batches, (0, 1)):
            yield pa.RecordBatch.from_arrays([pa.array([key[0]], kinds[0]), pa.array([key[1]], pa.int64()), pa.array([block_matrix([role_code(r[3]) for r in group])], pa.list_(pa.int64()))], names=["__conv", "__block", "matrix"])

    kinds = [to_arrow_type(conv.dataType), to_arrow_type(turns.schema[turn_col].dataType)]
    blocks = rows.select("__conv", "__block", "__at", "__role").repartition(tasks, "__conv", "__block").sortWithinPartitions(*order).mapInArrow(matrices, T.StructType([conv, T.StructField("__block", T.LongType()), T.StructField("matrix", T.ArrayType(T.LongType()))]))

    def states(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, group in _runs(batches, (0,)):
            found = borders([r[2] for r in group])
            n = len(group)
            yield pa.RecordBatch.from_arrays([pa.array([key[0]] * n, kinds[0]), pa.array([r[1] for r in group], pa.int64()), pa.array(found[:-1], pa.int32()), pa.array(found[1:], pa.int32()), pa.array([k == n - 1 for k in range(n)], pa.bool_())], names=["__c", "__b", "entry", "leave", "final"])

    kind = T.StructType([T.StructField("__c", conv.dataType), T.StructField("__b", T.LongType()), T.StructField("entry", T.IntegerType()), T.StructField("leave", T.IntegerType()), T.StructField("final", T.BooleanType())])
    fixed = blocks.repartition(tasks, "__conv").sortWithinPartitions("__conv", "__block").mapInArrow(states, kind)
    joined = rows.join(fixed, F.col("__conv").eqNullSafe(F.col("__c")) & (F.col("__block") == F.col("__b"))).select(*order, "__turn", "__role", "__text", "entry", "leave", "final")

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []
        for key, group in _runs(batches, (0, 1)):
            moves = solve([role_code(r[4]) for r in group], group[0][6], group[0][7])
            for k, (r, m) in enumerate(zip(group, moves, strict=True)):
                out.append((key[0], r[3], r[4], m[2], ROLES[m[1]], piece(m, r[5], group[0][8] and k == len(group) - 1), r[2]))
            if len(out) >= 2000:
                yield _batch(out)
                out = []
        if out:
            yield _batch(out)

    def _batch(out: list[tuple]) -> pa.RecordBatch:
        columns = list(zip(*out, strict=True))
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, [*kinds, *[pa.string()] * 4, pa.int64()], strict=True)], names=names)

    names = [conv_col, turn_col, role_col if role_col not in ("action", "new_role", "rendered", "at") else "role", "action", "new_role", "rendered", "at"]
    schema = T.StructType([T.StructField(names[0], conv.dataType), T.StructField(names[1], turns.schema[turn_col].dataType), *[T.StructField(n, T.StringType()) for n in names[2:-1]], T.StructField("at", T.LongType())])
    return joined.repartition(tasks, "__conv", "__block").sortWithinPartitions(*order).mapInArrow(pieces, schema)


def _runs(batches: Iterator[pa.RecordBatch], key: tuple[int, ...]) -> Iterator[tuple[tuple, list[tuple]]]:
    """Consecutive rows of equal key, over batch borders; a run is at most one block, or the blocks of a conversation."""
    rows = (r for b in batches for r in zip(*(c.to_pylist() for c in b.columns), strict=True))
    for k, group in groupby(rows, key=lambda r: tuple(r[i] for i in key)):
        yield k, list(group)


def rendered_conversations(pieces: DataFrame, *, conv_col: str = "conv_id") -> DataFrame:
    """One text per conversation, for conversations that fit in a row."""
    parts = F.array_sort(F.collect_list(F.struct("at", "rendered")))
    return pieces.groupBy(conv_col).agg(F.array_join(F.transform(parts, lambda x: x.rendered), "").alias("rendered"))


def op9_chat_repair(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repair(spark.read.parquet(f"{sf_dir}/conversations.parquet")).drop("at")
