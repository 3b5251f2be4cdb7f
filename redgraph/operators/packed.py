"""Edges packed into columns of bytes, for graphs whose owners have many.

An edge of a placed row costs some 60 bytes in each round: it is read, sorted with the state and handed over as a row.
Here edges are dealt once, as blocks: the edges of one owner that one task met, by their source, as arrays of the
narrowest type that holds them (six to ten bytes an edge).  A round hands blocks over as they are, indexes nothing and
expands a frontier in slices, so beside the blocks its memory follows the vertices of an owner and not its edges;
``uncombined`` alone lists the candidates that it ships.
Values, rounds and counters are those of ``superstep`` over the same owners.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from redgraph.operators.graph import PropertyGraph
from redgraph.operators.local_engine import COUNTS, KERNELS, MAIL, STATE, _expand
from redgraph.operators.partition import OWNED, OWNERS, Placed, owner, range_bounds, top_id
from redgraph.session import cut_placed, staged, told

BLOCK = "part int, n long, low long, high long, heads binary, sizes binary, dst binary, home binary, w binary"
OUT = "kind int, part int, id long, val long, more boolean, told array<long>"
COUNTERS = ("generated", "local", "remote_raw", "queued", "accepted", "batches", "rounds")

#: Edges that a task gathers before it packs them, edges of a slice, and the widest span of ids that gets a table of its own.
_GATHER, _SLICE, _SPAN = 1 << 21, 1 << 20, 1 << 23


@dataclass(frozen=True)
class Packed(Placed):
    """``Placed`` whose ``edges`` are rows of a file, placed nowhere; ``blocks`` are placed and hold the same edges."""

    blocks: DataFrame | None = None


def _narrow(a: np.ndarray, least: int = 1) -> bytes:
    """The bytes of whole numbers in the narrowest signed type; the reader tells the type by the length."""
    for t in (np.int8, np.int16, np.int32):
        if np.dtype(t).itemsize >= least and (not len(a) or (a.min() >= np.iinfo(t).min and a.max() <= np.iinfo(t).max)):
            return a.astype(t).tobytes()
    return a.astype(np.int64).tobytes()


def _wide(cell: pa.Scalar, n: int) -> np.ndarray:
    data = cell.as_buffer()
    return np.frombuffer(data, {1: np.int8, 2: np.int16, 4: np.int32, 8: np.int64}[data.size // n])


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: list[pa.RecordBatch] = []
    rows = 0
    for b in batches:
        held.append(b)
        rows += b.num_rows
        if rows >= _GATHER:
            yield _blocks(held)
            held, rows = [], 0
    if rows:
        yield _blocks(held)


def _blocks(held: list[pa.RecordBatch]) -> pa.RecordBatch:
    """One block for each owner of the given edges."""
    t = pa.Table.from_batches(held)
    part, src = t.column("part").to_numpy(), t.column("src").to_numpy()
    order = np.lexsort((src, part))
    part, src = part[order], src[order]
    dst, home, w = (t.column(c).to_numpy()[order] for c in ("dst", "dst_part", "w"))
    bounds = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1], [True]]))
    rows = []
    for first, end in zip(bounds[:-1], bounds[1:], strict=True):
        # no block has more edges than a slice, so one hub's edges may lie in several
        for a in range(first, end, _SLICE):
            b = min(a + _SLICE, end)
            heads, sizes = np.unique(src[a:b], return_counts=True)
            rows.append((int(part[a]), int(b - a), int(dst[a:b].min()), int(dst[a:b].max()), heads.astype(np.int64).tobytes(), sizes.astype(np.int32).tobytes(), _narrow(dst[a:b]), _narrow(home[a:b]), _narrow(w[a:b])))
    kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int64()] + [pa.binary()] * 5
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], [f.split()[0] for f in BLOCK.split(", ")])


def pack(g: PropertyGraph, parts: int | None, scheme: str = "block", *, weight: str | None = None, check: bool = False) -> Packed:
    """The owners of ``partition.assign``, with the edges in blocks: the graph is built and written once."""
    w = F.col(weight).cast("long") if weight else F.lit(1).cast("long")
    source = g.edges.select("src", "dst", w.alias("w"))
    watch = Observation()
    if check:
        count = lambda c: F.sum(c.cast("long"))
        faults = [count(F.col("src").isNull() | F.col("dst").isNull()).alias("null ends"), count(F.col("w").isNull()).alias("null weights"), count(F.coalesce(F.col("w") < 0, F.lit(False))).alias("negative weights")]
        source = source.observe(watch, *faults)
    source = staged(source, "edges")
    if check:
        for what, n in (told(watch) or source.agg(*faults).first().asDict()).items():
            if n:
                raise ValueError(f"{n} edges with {what}")
    g = PropertyGraph(source, g.vertices, g.directed, g.meta)
    if parts is None:
        parts = max(OWNERS, -(-source.count() // OWNED))
        if parts > OWNERS and scheme == "block":
            scheme = "range"
    of = owner(scheme, parts, top=top_id(g) if scheme == "block" else None, bounds=range_bounds(g, parts) if scheme == "range" else None)
    edges = source.select(of(F.col("src")).alias("part"), "src", "dst", of(F.col("dst")).alias("dst_part"), "w")
    blocks = cut_placed(edges.mapInArrow(_pack, BLOCK).repartitionById(parts, "part"), parts)
    vertices = cut_placed(g.ids().select("id", of(F.col("id")).alias("part")).repartitionById(parts, "part"), parts)
    return Packed(edges, vertices, parts, of, blocks)


class _Places:
    """Positions of ids in a sorted array: by a table if they lie close together, else by search."""

    def __init__(self, ids: np.ndarray):
        self.ids = ids
        self.table = None
        if len(ids) and int(ids[-1]) - int(ids[0]) < min(_SPAN, 64 * len(ids) + 1024):
            self.first = int(ids[0])
            self.table = np.full(int(ids[-1]) - self.first + 1, -1, np.int32)
            self.table[ids - self.first] = np.arange(len(ids), dtype=np.int32)

    def __call__(self, of: np.ndarray) -> np.ndarray:
        return self.table[of - self.first] if self.table is not None else np.searchsorted(self.ids, of)


class _Mail:
    """The best value for each far id, and its owner."""

    def __init__(self, at: Callable, worst: int, low: int, high: int):
        self.at, self.worst, self.low = at, worst, low
        self.dense = high - low < _SPAN
        if self.dense:
            self.best = np.full(high - low + 1, worst, np.int64)
            self.home = np.full(high - low + 1, -1, np.int32)  # -1: no mail
        self.held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.rows = 0

    def add(self, ids: np.ndarray, home: np.ndarray, val: np.ndarray) -> None:
        if self.dense:
            slot = ids - self.low
            self.at(self.best, slot, val)
            self.home[slot] = home
            return
        self.held.append(self._folded(ids.astype(np.int64), home.astype(np.int32), val))
        self.rows += len(self.held[-1][0])
        if self.rows > 4 * _SLICE and len(self.held) > 1:
            self.held = [self._folded(*(np.concatenate(c) for c in zip(*self.held, strict=True)))]
            self.rows = -len(self.held[0][0])  # fold again once as much has come as is kept

    def _folded(self, ids: np.ndarray, home: np.ndarray, val: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        kept, first, slot = np.unique(ids, return_index=True, return_inverse=True)
        best = np.full(len(kept), self.worst, np.int64)
        self.at(best, slot, val)
        return kept, home[first], best

    def all(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if self.dense:
            hit = np.flatnonzero(self.home >= 0)
            return hit + self.low, self.home[hit], self.best[hit]
        if not self.held:
            return np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, np.int64)
        return self._folded(*(np.concatenate(c) for c in zip(*self.held, strict=True)))


class _Each(_Mail):
    """Every candidate on its own."""

    def __init__(self):
        self.held = []

    def add(self, ids: np.ndarray, home: np.ndarray, val: np.ndarray) -> None:
        self.held.append((ids.astype(np.int64), home.astype(np.int32), val))

    def all(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return tuple(np.concatenate(c) for c in zip(*self.held, strict=True)) if self.held else (np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, np.int64))


def _slices(hit: np.ndarray, sizes: np.ndarray) -> Iterator[np.ndarray]:
    """``hit`` in runs of at most a slice of edges, or one head."""
    done = np.cumsum(sizes[hit], dtype=np.int64)
    at = 0
    while at < len(hit):
        ahead = int(done[at - 1]) if at else 0
        to = max(at + 1, int(np.searchsorted(done, ahead + _SLICE, side="right")))
        yield hit[at:to]
        at = to


def step(part: int, state: pa.Table, blocks: pa.Table, kernel: str, at: Callable, worst: int, mode: str, max_rounds: int | None, batch_size: int) -> pa.Table:
    """One owner's share of a round: local rounds and the best far values, or for ``plain`` and ``uncombined`` mail alone."""
    by_mail = mode in ("plain", "uncombined")
    ids = np.unique(state.column("id").to_numpy())  # every vertex of the owner has a row
    known = state.filter(state.column("val").is_valid())
    active = known.column("changed").to_numpy(zero_copy_only=False).astype(bool)
    if not active.any():
        return _out(part, *[np.empty(0, np.int64)] * 3, (np.empty(0, np.int64),) * 3, [0] * len(COUNTERS))
    place, where = _Places(ids), np.searchsorted(ids, known.column("id").to_numpy())
    value = np.full(len(ids), worst, np.int64)
    value[where] = known.column("val").to_numpy()
    before = value.copy()
    cells = []
    for k in range(blocks.num_rows):
        n = blocks.column("n")[k].as_py()
        heads, sizes = (np.frombuffer(blocks.column(c)[k].as_buffer(), t) for c, t in (("heads", np.int64), ("sizes", np.int32)))
        stop = np.cumsum(sizes, dtype=np.int64)
        cells.append((place(heads), sizes, stop - sizes, stop, *(_wide(blocks.column(c)[k], n) for c in ("dst", "home", "w"))))
    low, high = (min(blocks.column("low").to_pylist(), default=0), max(blocks.column("high").to_pylist(), default=0))
    mail = _Each() if mode == "uncombined" else _Mail(at, worst, low, high)
    front = np.unique(where[active])
    generated = local = accepted = rounds = 0
    candidates = KERNELS[kernel]
    while len(front) and (rounds < 1 if by_mail else max_rounds is None or rounds < max_rounds):
        rounds += 1
        turn = np.zeros(len(ids), bool)
        turn[front] = True
        new = value.copy()
        for heads, sizes, start, stop, dst, home, w in cells:
            for piece in _slices(np.flatnonzero(turn[heads]), sizes):
                e, of = _expand(piece, start, stop)
                found = candidates(value[heads[piece]][of], w[e].astype(np.int64))
                to, there = dst[e].astype(np.int64), home[e]
                near = there == part
                generated += len(e)
                local += int(near.sum())
                if by_mail:
                    mail.add(to, there, found)
                else:
                    at(new, place(to[near]), found[near])
                    far = ~near
                    mail.add(to[far], there[far], found[far])
        front = front[:0] if by_mail else np.flatnonzero(new != value)
        accepted += len(front)
        value = new
    moved = np.union1d(np.flatnonzero(value != before), front)
    carried = np.zeros(len(ids), bool)
    carried[front] = True
    sent = mail.all()
    per = np.unique(sent[1], return_counts=True)[1]
    counts = [generated, local, generated - local, len(sent[0]), accepted, rounds]
    return _out(part, ids[moved], value[moved], carried[moved], sent, [*counts[:5], int(np.sum(-(-per // batch_size))), counts[5]])


def _out(part: int, ids: np.ndarray, values: np.ndarray, carried: np.ndarray, sent: tuple[np.ndarray, np.ndarray, np.ndarray], counts: list[int]) -> pa.Table:
    """State rows, mail rows and one row of counters, in slices that share no memory with each other."""
    schema = pa.schema([("kind", pa.int32()), ("part", pa.int32()), ("id", pa.int64()), ("val", pa.int64()), ("more", pa.bool_()), ("told", pa.list_(pa.int64()))])
    tables = []

    def add(kind: int, parts: np.ndarray, i: np.ndarray, v: np.ndarray, more: np.ndarray, told_: pa.Array) -> None:
        tables.append(pa.Table.from_arrays([pa.array(np.full(len(i), kind, np.int32)), pa.array(parts.astype(np.int32)), pa.array(i.astype(np.int64)), pa.array(v.astype(np.int64)), pa.array(more.astype(bool)), told_], schema=schema))

    for a in range(0, len(ids), _SLICE):
        i = ids[a : a + _SLICE]
        add(STATE, np.full(len(i), part), i, values[a : a + _SLICE], carried[a : a + _SLICE], pa.nulls(len(i), pa.list_(pa.int64())))
    for a in range(0, len(sent[0]), _SLICE):
        i, home, best = (c[a : a + _SLICE] for c in sent)
        add(MAIL, home, i, best, np.zeros(len(i), bool), pa.nulls(len(i), pa.list_(pa.int64())))
    add(COUNTS, np.array([part]), np.zeros(1), np.zeros(1), np.zeros(1), pa.array([[int(c) for c in counts]], pa.list_(pa.int64())))
    return pa.concat_tables(tables)


def unpacked(blocks: pa.Table) -> pa.Table:
    """The edges of blocks as columns ``src, dst, w``, as ``local_engine.remaining`` reads them."""
    columns: dict[str, list[np.ndarray]] = {"src": [], "dst": [], "w": []}
    for k in range(blocks.num_rows):
        n = blocks.column("n")[k].as_py()
        heads, sizes = (np.frombuffer(blocks.column(c)[k].as_buffer(), t) for c, t in (("heads", np.int64), ("sizes", np.int32)))
        columns["src"].append(np.repeat(heads, sizes))
        for c in ("dst", "w"):
            columns[c].append(_wide(blocks.column(c)[k], n).astype(np.int64))
    return pa.table({c: np.concatenate(v) if v else np.empty(0, np.int64) for c, v in columns.items()})
