"""Near-duplicate groups at a stated similarity of word shingles, by SimHash and a range join of segment counts.

``simhash.links`` joins all fingerprints within two bits, which is what op7's contract asks for.  Texts
whose five-word shingles are alike to 0.8 differ in about 15 % of the bits, a radius at which nearly all
cells of one grid over 64 bits would meet.  The steps are the same here, with a wider radius:

* fingerprints of 128 bits over distinct shingles, embedded as the bit counts of their 64 two-bit segments;
* a range join: the Manhattan distance of two such vectors never exceeds the Hamming distance.  A band is
  some of the segments, dealt into ``BLOCKS`` blocks; vectors within distance one on a band differ in one
  segment, so they agree on all blocks but one and share the cell that leaves that block out.  ``RECALL`` of the pairs at
  the very threshold share a cell of at least one band, and more of those above it;
* pairs of a cell pass if the Hamming distance of the whole fingerprints and the numbers of shingles
  allow the similarity, and are then verified exactly on the shingles of both texts.

Blocks grow with the number of texts, so that a cell meets some hundred texts by chance whatever the size; rows per
text grow with them.  Cells are dealt by one exchange and compared in the task that
gets them, so nothing but allowed pairs leaves it.  First each text meets the nearest one of all its cells; texts that this joins into one group
are not compared again.  Of the rest, all allowed pairs of different groups are verified, up to ``PAIRS`` for each
text of a cell; a cell with more of them, or of more than ``MEET`` texts, links each to its smallest and is dealt to finer
ones by further segments, until none is crowded.  No pair of these is a row: the texts of a cell that has some travel to
one task, which verifies them there, and only links that join two groups leave it, fewer than the texts.  Texts of equal XXH64 are one text.

Bands miss some pairs (``RECALL``), and crowded cells may.  A last pass finds those by a rule that misses none: of two sets of
shingles in one order that are alike to s, the first n - ceil(s n) + m of each have m in common.  Texts that share so many and
are of different groups are candidates unless ``LOST`` standard deviations of their fingerprints speak against it, and are verified like the first.
"""

from __future__ import annotations

import math
import random
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from redgraph.llm.bytetext import FOLD, NONBLANK, Chunk, chunks, gram_hashes, mixed, word_hashes
from redgraph.llm.exact_dedup import THIN
from redgraph.operators.components import connected_components
from redgraph.session import scoped, staged, task_count

SHINGLE = 5
SIMILARITY = 0.8
RECALL = 0.95
PAIRS = 8
BITS = 128
SEGMENTS = BITS // 2
BLOCKS = 3
ROW = 500  # comparisons that cost as much as dealing a row to a cell
MEET = 256
FINER = 4  # segments by which a crowded cell is dealt
EMPTY = 0  # the one node of all texts without words
_BLOCK = 1 << 16
_CELLS = 1 << 17  # rows of cells compared at once
_DRAWN = 8192
TEXT_BYTES = 16 << 20  # of a block of texts that are verified
LOST = 6  # a pair at the very threshold differs in more bits than this with a chance below 1e-7
COMMON = 8  # one shingle in so many must be common to the heads of both texts
PAIR, LEAF, CENTRE = 0, 1, 2  # roles in a meeting: all pairs of its texts, or each leaf with the centre


def shingle_sets(chunk: Chunk, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of each document, sorted, and where each document's begin (n+1)."""
    buf = FOLD[chunk.buf]
    starts, ends, first = Chunk(chunk.row, buf, chunk.cuts).words(NONBLANK)
    words = word_hashes(buf, starts, ends)
    many = np.diff(first)
    doc = np.repeat(np.arange(chunk.n), many)
    g = gram_hashes(words, shingle)
    at = np.flatnonzero(doc[: len(g)] == doc[shingle - 1 :]) if len(g) else np.empty(0, np.int64)
    hashes, docs = [g[at]], [doc[at]]
    for m in range(1, shingle):  # a shorter text is one shingle
        d = np.flatnonzero(many == m)
        hashes.append(mixed(gram_hashes(words, m)[first[d]] + np.uint64(m)))
        docs.append(d)
    h, d = np.concatenate(hashes), np.concatenate(docs)
    order = np.lexsort((h, d))
    h, d = h[order], d[order]
    once = np.ones(len(h), bool)
    once[1:] = (h[1:] != h[:-1]) | (d[1:] != d[:-1])
    h, d = h[once], d[once]
    return h, np.searchsorted(d, np.arange(chunk.n + 1))


def wide_fingerprints(h: np.ndarray, edge: np.ndarray) -> np.ndarray:
    """Two 64-bit words per document: a bit is 1 if it is in over half of the document's shingle hashes."""
    n = len(edge) - 1
    doc = np.repeat(np.arange(n), np.diff(edge))
    out = np.zeros((n, 2), np.uint64)
    for word in range(2):
        x = h if not word else mixed(h ^ np.uint64(0xA0761D6478BD642F))
        counts = np.zeros((n, 64), np.int64)
        for a in range(0, len(x), _BLOCK):
            part = x[a : a + _BLOCK]
            bits = np.unpackbits(part.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            d = doc[a : a + _BLOCK]
            at = np.flatnonzero(np.concatenate([[True], d[1:] != d[:-1]]))
            counts[d[at]] += np.add.reduceat(bits, at, axis=0, dtype=np.int32)
        ones = (2 * counts > np.diff(edge)[:, None]).astype(np.uint8)
        out[:, word] = np.packbits(ones, axis=1, bitorder="little").view("<u8").ravel()
    return out


def head_counts(n: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """How many of ``n`` ordered shingles make the heads of a set, and how many of them sets alike to ``similarity`` share.

    Of two sets the smaller number holds, and no more than the larger set must have in common with any other.
    """
    common = np.ceil(similarity * n - 1e-9).astype(np.int64)
    share = 1 + n // COMMON
    return np.where(n > 0, np.minimum(n - common + share, n), 0), share


def _prints(rows: DataFrame, shingle: int, similarity: float = SIMILARITY) -> DataFrame:
    """``__id, __text, lo, hi, n, heads`` from rows ``__id, __text, text``; ``heads`` packs the least shingle hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk in chunks(batch.column(2)):
                h, edge = shingle_sets(chunk, shingle)
                fp = wide_fingerprints(h, edge).view(np.int64)
                keys = [c.slice(chunk.row, chunk.n) for c in batch.columns[:2]]
                n = np.diff(edge).astype(np.int64)
                heads = [h[a : a + m].tobytes() for a, m in zip(edge.tolist(), head_counts(n, similarity)[0].tolist(), strict=False)]
                yield pa.RecordBatch.from_arrays([*keys, pa.array(np.ascontiguousarray(fp[:, 0])), pa.array(np.ascontiguousarray(fp[:, 1])), pa.array(n), pa.array(heads, pa.binary())], names=["__id", "__text", "lo", "hi", "n", "heads"])

    schema = rows.select("__id", "__text").schema.add("lo", "long").add("hi", "long").add("n", "long").add("heads", "binary")
    return rows.select("__id", "__text", "text").mapInArrow(run, schema)


def flip_chance(similarity: float) -> float:
    """How often a bit differs between sets of one size and this Jaccard similarity."""
    return math.acos(2 * similarity / (1 + similarity)) / math.pi


def segment_counts(fp: np.ndarray) -> np.ndarray:
    """Packed bit counts (0, 1 or 2) of the two-bit segments of 64-bit words."""
    even, one = np.uint64(0x5555555555555555), np.uint64(1)
    high = (fp >> one) & even
    return ((fp & even) ^ high) | ((fp & even & high) << one)


def _mask(segments: list[int]) -> tuple[np.uint64, np.uint64]:
    """The places of the given segments in the packed counts of both words."""
    return tuple(np.uint64(sum(3 << 2 * (g % 32) for g in segments if g // 32 == word)) for word in (0, 1))


def strangers(nodes: int, size: int) -> float:
    """Texts that a cell of blocks of ``size`` segments holds by chance: two random texts agree on a segment with chance 3/8."""
    return nodes * 0.375 ** (size * (BLOCKS - 1))


def bands(nodes: int, similarity: float, recall: float = RECALL) -> list[list[list[int]]]:
    """For each band its blocks, each a list of segments.  Larger blocks take more bands, smaller ones more comparisons: the cheapest."""
    best, least = None, math.inf
    for size in range(2, SEGMENTS // BLOCKS + 1):
        found = _bands(size, similarity, recall)
        cost = len(found) * (ROW + strangers(nodes, size))
        if cost >= least:
            break
        best, least = found, cost
    return best


def _bands(size: int, similarity: float, recall: float) -> list[list[list[int]]]:
    """Bands share segments, so how many are needed is counted on drawn vectors at the threshold, not multiplied out."""
    chance = flip_chance(similarity)
    same = (1 - chance) ** 2 + chance * chance / 2  # of a segment's counts: no bit differs, or both do and make up for it
    agree = np.random.default_rng(0).random((SEGMENTS, _DRAWN)) < same
    hit = np.zeros(_DRAWN, bool)
    out: list[list[list[int]]] = []
    while not out or hit.mean() < recall:
        order = random.Random(len(out)).sample(range(SEGMENTS), SEGMENTS)
        for a in range(0, SEGMENTS - size * BLOCKS + 1, size * BLOCKS):
            blocks = [order[a + k * size : a + (k + 1) * size] for k in range(BLOCKS)]
            out.append(blocks)
            hit |= sum(agree[block].all(axis=0).astype(int) for block in blocks) >= BLOCKS - 1
            if hit.mean() >= recall:
                break
    return out


def _dealt(nodes: DataFrame, found: list[list[list[int]]]) -> DataFrame:
    """A row ``cell`` and the node's columns for each band and block left out; ``nodes``: ``key, lo, hi, n`` and perhaps ``root``, stored."""
    spark = nodes.sparkSession
    masks = [_mask([g for k, block in enumerate(band) if k != left for g in block]) for band in found for left in range(BLOCKS)]
    names = nodes.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lo, hi = (segment_counts(batch.column(c).to_numpy().view(np.uint64)) for c in ("lo", "hi"))
            for t, (low, high) in enumerate(masks):
                cell = mixed(mixed((lo & low) + np.uint64(t)) ^ (hi & high))
                yield pa.RecordBatch.from_arrays([pa.array(cell.view(np.int64)), *batch.columns], names=["cell", *names])

    # each row makes one per cell: deal rows to all tasks, or a few tasks would make all cells
    return nodes.where("n > 0").repartition(task_count(spark)).mapInArrow(run, "cell long, " + ", ".join(f"{c} long" for c in names))


def _whole(batches: Iterator[pa.RecordBatch], names: list[str]) -> Iterator[dict[str, np.ndarray]]:
    """Columns of whole cells, from batches in the order of the cells."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        held.append(batch)
        if sum(b.num_rows for b in held) < _CELLS:
            continue
        table = pa.Table.from_batches(held)
        cell = table.column("cell").to_numpy()
        cut = int(np.searchsorted(cell, cell[-1]))  # the last cell may go on
        if cut:
            yield {c: table.column(c).to_numpy()[:cut] for c in names}
        held = table.slice(cut).combine_chunks().to_batches()
    if held:
        table = pa.Table.from_batches(held)
        yield {c: table.column(c).to_numpy() for c in names}


def met(rows: dict[str, np.ndarray], reach: int, similarity: float, pairs: int, meet: int, nearest: bool, meetings: list[tuple[np.ndarray, ...]] | None = None) -> list[np.ndarray]:
    """Allowed pairs of keys ``a < b`` of different roots in whole cells sorted by ``cell, key``, and their differing bits.

    ``nearest``: only pairs of a key and the nearest other one of its cell, so at most one row for each.  ``meetings``
    gets the same as ``unit, row, role``: the rows of a cell that have allowed pairs, at most ``meet`` and a centre.
    """
    key, root, n = rows["key"], rows.get("root", rows["key"]), rows["n"]
    lo, hi = rows["lo"].view(np.uint64), rows["hi"].view(np.uint64)
    counts = segment_counts(lo), segment_counts(hi)
    order = random.Random("finer").sample(range(SEGMENTS), SEGMENTS)
    finer = [_mask(order[k : k + FINER]) for k in range(0, SEGMENTS, FINER)]
    turn = np.array(finer, np.uint64)
    at, group, begun = np.arange(len(key)), rows["cell"].view(np.uint64), rows["cell"].view(np.uint64)
    none = np.empty(0, np.int64)
    out = [[none, none, none]]
    for depth in range(len(finer) + 1):
        if depth:
            sort = np.lexsort((key[at], group))
            at, group, begun = at[sort], group[sort], begun[sort]
        first = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]])) if len(at) else np.empty(0, np.int64)
        if not len(first):
            break
        size = np.diff(np.append(first, len(at)))
        mixed_roots = np.minimum.reduceat(root[at], first) < np.maximum.reduceat(root[at], first)
        stay = np.repeat(mixed_roots, size)
        at, group, begun, size = at[stay], group[stay], begun[stay], size[mixed_roots]
        if not len(at):
            break
        first = np.cumsum(size) - size
        of = np.repeat(np.arange(len(size)), size)
        k, r, m, x, y = key[at], root[at], n[at], lo[at], hi[at]

        def good(i: np.ndarray, j: np.ndarray, r=r, m=m, x=x, y=y) -> tuple[np.ndarray, np.ndarray]:
            bits = np.bitwise_count(x[i] ^ x[j]).astype(np.int16) + np.bitwise_count(y[i] ^ y[j])
            near = np.flatnonzero((bits <= reach) & (r[i] != r[j]))
            a, b = m[i[near]], m[j[near]]
            near = near[np.minimum(a, b) >= similarity * np.maximum(a, b)]
            return near, bits[near].astype(np.int64)

        end = (first + size)[of]
        i, left, right, apart = np.flatnonzero((size <= meet)[of]), [none], [none], [none]
        for s in range(1, meet):
            i = i[i + s < end[i]]
            if not len(i):
                break
            near, bits = good(i, i + s)
            left.append(i[near])
            right.append(i[near] + s)
            apart.append(bits)
        a, b, bits = (np.concatenate(x) for x in (left, right, apart))
        crowded = size > meet
        if nearest:
            best = np.full(len(at), BITS << 32)
            np.minimum.at(best, b, (bits << 32) + a)
            np.minimum.at(best, a, (bits << 32) + b)
            i = np.flatnonzero(best < BITS << 32)
            j, bits = best[i] & 0xFFFFFFFF, best[i] >> 32
            a, b = np.minimum(i, j), np.maximum(i, j)
        else:
            crowded = crowded | (np.bincount(of[a], minlength=len(size)) > pairs * size)
            few = ~crowded[of[a]]
            a, b, bits = a[few], b[few], bits[few]
        out.append([k[a], k[b], bits])
        if meetings is not None:
            have = np.unique(np.concatenate([a, b]))
            meetings.append((mixed(group[have] ^ np.uint64(PAIR)), at[have], np.full(len(have), PAIR)))
        b = np.flatnonzero(crowded[of])
        a = first[of[b]]
        near, bits = good(a, b)
        out.append([k[a[near]], k[b[near]], bits])
        if meetings is not None and len(near):
            leaf, centre = b[near], a[near]
            turns = np.arange(len(leaf)) - np.searchsorted(centre, centre)  # centres ascend with their leaves
            unit = mixed(mixed(group[leaf] ^ np.uint64(LEAF)) + (turns // meet).astype(np.uint64))
            lead = turns % meet == 0
            meetings.append((unit, at[leaf], np.full(len(leaf), LEAF)))
            meetings.append((unit[lead], at[centre[lead]], np.full(int(lead.sum()), CENTRE)))
        if depth == len(finer):
            break
        at, begun = at[b], begun[b]
        mask = turn[(begun + np.uint64(depth)) % np.uint64(len(finer))]
        group = mixed(mixed(group[b] + (counts[0][at] & mask[:, 0])) ^ (counts[1][at] & mask[:, 1]))
    return [np.concatenate(x) for x in zip(*out, strict=True)]


def _reach(similarity: float, deviations: int = 4) -> int:
    """Differing bits that texts of this similarity have at most: some standard deviations beyond what is expected."""
    chance = flip_chance(similarity)
    return math.ceil(BITS * chance + deviations * math.sqrt(BITS * chance * (1 - chance)))


def _cells(nodes: DataFrame, similarity: float, recall: float) -> tuple[DataFrame, int]:
    """The nodes of each cell together and in order, and of how many texts a cell is crowded."""
    many = nodes.count()
    dealt = bands(many, similarity, recall)
    return _dealt(nodes, dealt).repartition("cell").sortWithinPartitions("cell", "key"), max(MEET, math.ceil(4 * strangers(many, len(dealt[0][0]))))


def candidates(nodes: DataFrame, similarity: float, recall: float = RECALL, *, nearest: bool = False) -> DataFrame:
    """Pairs ``a, b`` of keys that share a cell and that fingerprints and numbers of shingles allow, and their differing ``bits``.

    ``nodes``: stored ``key, lo, hi, n`` and perhaps ``root``, of which pairs have different ones.  ``nearest``: of each key only
    the pair with its nearest other one.
    """
    names, pairs, reach = ["cell", *nodes.columns], PAIRS, _reach(similarity)
    cells, meet = _cells(nodes, similarity, recall)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _whole(batches, names):
            a, b, bits = met(rows, reach, similarity, pairs, meet, nearest)
            order = np.lexsort((b, a))
            a, b, bits = a[order], b[order], bits[order]
            once = np.ones(len(a), bool)
            once[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
            yield pa.RecordBatch.from_arrays([pa.array(x[once]) for x in (a, b, bits)], names=["a", "b", "bits"])

    found = cells.mapInArrow(run, "a long, b long, bits long")
    return nearest_of_each(found) if nearest else found.distinct()


def meetings(nodes: DataFrame, similarity: float, recall: float = RECALL) -> DataFrame:
    """The pairs of ``candidates`` without a row for each: ``unit, role`` and the columns of the nodes that meet in it.

    A text has at most one row for each of its cells and finer cells, however many texts it meets there.
    """
    names, pairs, reach = ["cell", *nodes.columns], PAIRS, _reach(similarity)
    cells, meet = _cells(nodes, similarity, recall)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _whole(batches, names):
            found: list[tuple[np.ndarray, ...]] = []
            met(rows, reach, similarity, pairs, meet, False, found)
            unit, row, role = (np.concatenate(x) for x in zip(*found, strict=True)) if found else [np.empty(0, np.int64)] * 3
            yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.uint64).view(np.int64)) for x in (unit, role)] + [pa.array(rows[c][row.astype(np.int64)]) for c in names[1:]], names=["unit", "role", *names[1:]])

    return cells.mapInArrow(run, "unit long, role long, " + ", ".join(f"{c} long" for c in names[1:]))


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by ``cell``, those whose cell holds more than one."""
    rest = None
    for batch in batches:
        table = pa.Table.from_batches([batch] if rest is None else [rest, batch]).combine_chunks()
        cell = table.column("cell").to_numpy()
        if not len(cell):
            continue
        again = cell[1:] == cell[:-1]
        keep = np.concatenate([[False], again]) | np.concatenate([again, [False]])
        # the last row may go on; one that has company goes out now and leaves its cell behind twice
        known = rest is not None and bool(rest.column("old")[0].as_py())
        out = keep.copy()
        if known:
            out[0] = False
        last = len(cell) - 1
        told = bool(keep[last]) or (known and last == 0)
        if not told:
            out[last] = False
        found = table.filter(pa.array(out)).select(["cell", "key"])
        yield from found.to_batches()
        rest = table.slice(last).set_column(2, "old", pa.array([told])).combine_chunks().to_batches()[0]


def missed(heads: DataFrame, nodes: DataFrame, similarity: float) -> DataFrame:
    """Pairs ``a < b`` of different roots that share enough of their least shingles: all that can be alike to ``similarity``.

    ``heads``: stored ``key, n, heads``; ``nodes``: stored ``key, lo, hi, n, root``.  A shingle that one text alone has among its
    least ones, which most are, is dropped before the columns of the nodes are joined.
    """
    spark, names, reach = nodes.sparkSession, ["cell", "key", "lo", "hi", "n", "root"], _reach(similarity, LOST)

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            key, packed = batch.column("key").to_numpy(), batch.column("heads").to_pylist()
            cell = np.frombuffer(b"".join(packed), np.int64)
            many = np.array([len(x) // 8 for x in packed], np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(cell), pa.array(np.repeat(key, many)), pa.array(np.zeros(len(cell), bool))], names=["cell", "key", "old"])

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _whole(batches, names):
            for a, b, least in _apart(rows, reach, similarity):
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (np.minimum(a, b), np.maximum(a, b), least)], names=["a", "b", "least"])

    once = heads.where("n > 0").select("key", "heads").repartition(task_count(spark), "key").dropDuplicates(["key"])
    cells = once.mapInArrow(listed, "cell long, key long, old boolean")
    shared = staged(cells.repartition("cell").sortWithinPartitions("cell").mapInArrow(_shared, "cell long, key long"), "similar-shared")
    met = shared.join(nodes, "key").select(*names).repartition("cell").sortWithinPartitions("cell", "n")
    # a pair has a row for each shingle that its heads share
    return met.mapInArrow(pairs, "a long, b long, least long").groupBy("a", "b").agg(F.count(F.lit(1)).alias("many"), F.min("least").alias("least")).where("many >= least").select("a", "b")


def _apart(rows: dict[str, np.ndarray], reach: int, similarity: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Keys of pairs of different roots in whole cells sorted by ``cell, n``, that sizes and fingerprints allow, and how many cells they must share."""
    cell, key, n, root = (rows[c] for c in ("cell", "key", "n", "root"))
    lo, hi = rows["lo"].view(np.uint64), rows["hi"].view(np.uint64)
    last = np.flatnonzero(np.concatenate([cell[1:] != cell[:-1], [True]]))
    end = np.repeat(last + 1, np.diff(last, prepend=-1))
    share, need = head_counts(n, similarity)[1], np.ceil(similarity * n - 1e-9).astype(np.int64)
    i, s = np.arange(len(cell)), 1
    while len(i):
        i = i[i + s < end[i]]
        i = i[n[i] >= similarity * n[i + s]]  # sizes ascend: what is too large for a text stays so
        j = i + s
        bits = np.bitwise_count(lo[i] ^ lo[j]).astype(np.int16) + np.bitwise_count(hi[i] ^ hi[j])
        good = (bits <= reach) & (root[i] != root[j])
        if good.any():
            i_, j_ = i[good], j[good]
            yield key[i_], key[j_], np.minimum(share[i_], need[j_])
        s += 1


def nearest_of_each(pairs: DataFrame) -> DataFrame:
    """Of each key the pair ``a, b, bits`` with the fewest differing bits."""
    ends = pairs.select(F.explode(F.array("a", "b")).alias("of"), F.struct("bits", "a", "b").alias("pair"))
    return ends.groupBy("of").agg(F.min("pair").alias("pair")).select("pair.a", "pair.b", "pair.bits").distinct()


def _texts(rows: DataFrame, nodes: DataFrame, keys: DataFrame) -> DataFrame:
    """``key, text`` of the ``keys``, one row for each."""
    with scoped(rows.sparkSession, THIN):
        needed = nodes.join(keys.distinct(), "key").select("key", "rep")
        found = rows.join(needed, (F.col("__text") == F.col("key")) & F.col("__id").eqNullSafe(F.col("rep")))
        return staged(found.select("key", "text").dropDuplicates(["key"]), "similar-texts")


def _components(links: DataFrame) -> DataFrame:
    return staged(connected_components(links, "a", "b").withColumnsRenamed({"id": "key", "component": "root"}), "similar-roots")


def _verified(pairs: DataFrame, texts: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """The pairs whose shingle sets reach the similarity; ``texts``: stored ``key, text``.

    Texts are dealt into blocks, pairs to the cell of their two blocks; a text travels once to each cell that has a pair of it,
    not once for each pair.
    """
    size = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(-(-size // TEXT_BYTES), min(8, math.ceil(math.sqrt(2 * task_count(pairs.sparkSession)))))
    own = lambda c: F.pmod(F.xxhash64(F.lit("block"), c), F.lit(blocks))
    dealt = pairs.select("a", "b", F.least(own("a"), own("b")).alias("x"), F.greatest(own("a"), own("b")).alias("y"))
    needed = dealt.select(F.explode(F.array("a", "b")).alias("key"), F.col("x").alias("u"), F.col("y").alias("v")).distinct()
    sent = needed.join(texts, "key")

    def run(mine: pa.Table, held: pa.Table) -> pa.Table:
        text, sets = held.column("text").combine_chunks(), []
        for chunk in chunks(text):
            h, edge = shingle_sets(chunk, shingle)
            sets += [h[i:j] for i, j in zip(edge, edge[1:], strict=False)]
        of = dict(zip(held.column("key").to_pylist(), sets, strict=True))
        good = []
        for a, b in zip(mine.column("a").to_pylist(), mine.column("b").to_pylist(), strict=True):
            common = len(np.intersect1d(of[a], of[b], assume_unique=True))
            good.append(common >= similarity * (len(of[a]) + len(of[b]) - common))
        return mine.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    return staged(dealt.groupBy("x", "y").cogroup(sent.groupBy("u", "v")).applyInArrow(run, "a long, b long"), "similar-links")


def _joins(unit: dict[str, np.ndarray], sets: list[np.ndarray], reach: int, similarity: float) -> list[tuple[int, int]]:
    """Places of verified pairs of one meeting, nearest first, that join its groups: a forest, and all that a further link would join."""
    lo, hi, n, root = (unit[c] for c in ("lo", "hi", "n", "root"))
    if unit["role"].any():
        j = np.flatnonzero(unit["role"] == LEAF)
        i = np.full(len(j), np.flatnonzero(unit["role"] == CENTRE)[0])
    else:
        i, j = np.triu_indices(len(n), 1)
    bits = np.bitwise_count(lo[i] ^ lo[j]).astype(np.int16) + np.bitwise_count(hi[i] ^ hi[j])
    ok = (bits <= reach) & (root[i] != root[j]) & (np.minimum(n[i], n[j]) >= similarity * np.maximum(n[i], n[j]))
    i, j, bits = i[ok], j[ok], bits[ok]
    group = {r: r for r in root.tolist()}

    def of(r: int) -> int:
        while group[r] != r:
            group[r] = r = group[group[r]]
        return r

    out = []
    for k in np.argsort(bits, kind="stable").tolist():
        a, b = int(i[k]), int(j[k])
        x, y = of(int(root[a])), of(int(root[b]))
        if x == y:
            continue
        common = len(np.intersect1d(sets[a], sets[b], assume_unique=True))
        if common >= similarity * (len(sets[a]) + len(sets[b]) - common):
            group[max(x, y)] = min(x, y)
            out.append((a, b))
    return out


def _joined(meet: DataFrame, texts: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """Verified pairs ``a, b`` that join what ``meetings`` brought together; ``texts``: stored ``key, text``."""
    reach, names = _reach(similarity), ["unit", "role", "key", "lo", "hi", "n", "root"]

    def links(table: pa.Table) -> pa.RecordBatch:
        col = {c: table.column(c).to_numpy() for c in names}
        col |= {c: col[c].view(np.uint64) for c in ("lo", "hi")}
        sets: list[np.ndarray] = []
        for chunk in chunks(table.column("text").combine_chunks()):
            h, edge = shingle_sets(chunk, shingle)
            sets += [h[i:j] for i, j in zip(edge, edge[1:], strict=False)]
        cuts = [0, *(np.flatnonzero(col["unit"][1:] != col["unit"][:-1]) + 1).tolist(), table.num_rows]
        found = [(p + a, p + b) for p, q in zip(cuts, cuts[1:], strict=False) for a, b in _joins({c: x[p:q] for c, x in col.items()}, sets[p:q], reach, similarity)]
        a, b = np.array(found, np.int64).reshape(-1, 2).T
        return pa.RecordBatch.from_arrays([pa.array(col["key"][x]) for x in (a, b)], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            unit = batch.column("unit").to_numpy()
            cut = int(np.searchsorted(unit, unit[-1]))  # the last unit may go on
            if cut or held and held[-1].column("unit")[-1].as_py() != unit[0]:
                yield links(pa.Table.from_batches([*held, batch.slice(0, cut)]))
                held = []
            held.append(batch.slice(cut))
        if held:
            yield links(pa.Table.from_batches(held))

    with scoped(meet.sparkSession, THIN):
        sent = meet.join(texts, "key").select(*names, "text").repartition("unit").sortWithinPartitions("unit", "key")
        return staged(sent.mapInArrow(run, "a long, b long"), "similar-joined")


def similar_groups(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, similarity: float = SIMILARITY, recall: float = RECALL) -> DataFrame:
    """Per row ``__id, __text, root``: rows of one root are joined by links of at least ``similarity``.

    Words are lower-cased (A-Z) runs without blanks; a text of fewer words than a shingle is one shingle.
    Null, empty and blank texts form one group.  Rows with equal ids count as rows.
    """
    rows = docs.select(F.col(id_col).alias("__id"), F.xxhash64(text_col).alias("__text"), F.col(text_col).alias("text"))
    prints = staged(_prints(rows, shingle, similarity).withColumn("key", F.when(F.col("n") > 0, F.col("__text")).otherwise(F.lit(EMPTY).cast("long"))), "similar-prints")
    nodes = staged(prints.groupBy("key").agg(F.min("lo").alias("lo"), F.min("hi").alias("hi"), F.min("n").alias("n"), F.min("__id").alias("rep")), "similar-nodes")
    # each text meets its nearest first; what that joins need not be compared again
    vectors = nodes.select("key", "lo", "hi", "n")
    first = staged(candidates(vectors, similarity, recall, nearest=True), "similar-first")
    links = _verified(first, _texts(rows, nodes, first.select(F.explode(F.array("a", "b")).alias("key"))), shingle, similarity)
    rooted = staged(vectors.join(_components(links), "key", "left").withColumn("root", F.coalesce("root", "key")), "similar-rooted")
    rest = staged(meetings(rooted, similarity, recall), "similar-rest")
    joined = _joined(rest, _texts(rows, nodes, rest.select("key")), shingle, similarity)
    # what no band brought together; groups of the first pass need no more links
    late = staged(missed(prints, rooted, similarity), "similar-late")
    more = _verified(late, _texts(rows, nodes, late.select(F.explode(F.array("a", "b")).alias("key"))), shingle, similarity)
    root = _components(links.unionByName(joined).unionByName(more))
    return prints.join(root, "key", "left").select("__id", "__text", F.coalesce("root", "key").alias("root"))


def keep_one_of_each(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **rule) -> DataFrame:
    """One document of each group, all columns as they were: the smallest id (nulls last), then the smallest text hash."""
    return first_of_each(docs, staged(similar_groups(docs, id_col=id_col, text_col=text_col, **rule), "similar-groups"), id_col, text_col)


def first_of_each(docs: DataFrame, groups: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The rows of ``docs`` that come first in their group; ``groups``: ``__id, __text, root`` per row."""
    best = groups.groupBy("root").agg(F.min(F.struct(F.isnull("__id").alias("none"), F.col("__id").alias("id"), F.col("__text").alias("text"))).alias("best"))
    stay = best.select(F.col("best.id").alias("__id"), F.col("best.text").alias("__text")).distinct()
    rows = docs.withColumn("__text", F.xxhash64(text_col))
    kept = rows.join(stay.withColumnRenamed("__text", "__text2"), F.col(id_col).eqNullSafe(F.col("__id")) & (F.col("__text") == F.col("__text2")), "left_semi")
    order = Window.partitionBy(id_col, "__text").orderBy(*[F.col(c) for c, t in docs.dtypes if c not in (id_col, text_col) and not t.startswith("map")] or [F.lit(0)])
    return kept.withColumn("__rank", F.row_number().over(order)).where("__rank = 1").select(*docs.columns)
