"""SimHash fingerprints and an exact near-duplicate join by segment-popcount embedding.

A fingerprint is mapped to the bit counts of its 32 two-bit segments.  The Manhattan distance of two
such vectors never exceeds the Hamming distance of the fingerprints, so all links within two bits
lie within Manhattan distance two.  Such vectors differ in at most two of the blocks into which the
segments are dealt; a distinct fingerprint therefore enters one cell for each choice of all blocks but
two, and two fingerprints within distance two always share a cell.  Pairs of a cell are then verified
on all 64 bits.

A cell with more than ``PAIRS`` fingerprints is not paired up: its fingerprints are refined to
one-bit segments, where a shared cell proves the link and holds at most 65 fingerprints, so that
linking each to the smallest is exact.  Documents with equal fingerprints are folded before the join.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from redgraph.llm.bytetext import FOLD, NONBLANK, Chunk, chunks
from redgraph.llm.exact_dedup import THIN
from redgraph.llm.similar_documents import first_of_each
from redgraph.operators.components import connected_components
from redgraph.session import cut, scoped, staged, task_count

SHINGLE = 3
SEED = 42
PAIRS = 48
SEGMENTS = 32
_BLOCK = 1 << 17
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _left(x: np.ndarray, bits: int) -> np.ndarray:
    return (x << np.uint64(bits)) | (x >> np.uint64(64 - bits))


def xxh64_spans(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int = SEED) -> np.ndarray:
    """XXH64 of many byte ranges of one buffer; ranges of one length are hashed together."""
    out = np.empty(len(starts), np.uint64)
    size = ends - starts
    padded = np.concatenate([buf, np.zeros(8, np.uint8)])
    wide = np.ndarray((len(padded) - 7,), "<u8", padded.data, strides=(1,))
    half = np.ndarray((len(padded) - 3,), "<u4", padded.data, strides=(1,))
    order = np.argsort(size, kind="stable")
    lengths, first = np.unique(size[order], return_index=True)
    with np.errstate(over="ignore"):
        for n, a, b in zip(lengths.tolist(), first.tolist(), [*first[1:].tolist(), len(order)], strict=True):
            rows = order[a:b]
            if n > 512:
                out[rows] = [xxhash.xxh64_intdigest(buf[i : i + n].tobytes(), seed) for i in starts[rows].tolist()]
                continue
            p = starts[rows]
            if n >= 32:
                lanes = [np.full(len(p), x, np.uint64) for x in (np.uint64(seed) + _P1 + _P2, np.uint64(seed) + _P2, np.uint64(seed), np.uint64(seed) - _P1)]
                for _ in range(n // 32):
                    for k in range(4):
                        lanes[k] = _left(lanes[k] + wide[p + 8 * k] * _P2, 31) * _P1
                    p = p + 32
                h = _left(lanes[0], 1) + _left(lanes[1], 7) + _left(lanes[2], 12) + _left(lanes[3], 18)
                for lane in lanes:
                    h = (h ^ (_left(lane * _P2, 31) * _P1)) * _P1 + _P4
            else:
                h = np.full(len(p), np.uint64(seed) + _P5, np.uint64)
            h = h + np.uint64(n)
            rest = n % 32
            for _ in range(rest // 8):
                h = _left(h ^ (_left(wide[p] * _P2, 31) * _P1), 27) * _P1 + _P4
                p = p + 8
            if rest % 8 >= 4:
                h = _left(h ^ (half[p].astype(np.uint64) * _P1), 23) * _P2 + _P3
                p = p + 4
            for _ in range(rest % 4):
                h = _left(h ^ (padded[p].astype(np.uint64) * _P5), 11) * _P1
                p = p + 1
            h = (h ^ (h >> np.uint64(33))) * _P2
            h = (h ^ (h >> np.uint64(29))) * _P3
            out[rows] = h ^ (h >> np.uint64(32))
    return out


def chunk_fingerprints(chunk: Chunk, shingle: int = SHINGLE) -> np.ndarray:
    """Fingerprint of each document of a chunk, as unsigned 64-bit integers."""
    buf = FOLD[chunk.buf]
    starts, ends, first = Chunk(chunk.row, buf, chunk.cuts).words(NONBLANK)
    out = np.zeros(chunk.n, np.uint64)
    if not len(starts):
        return out
    solid = NONBLANK[buf]
    keep = solid.copy()
    keep[1:] |= solid[:-1]  # one separator after each word
    line = np.where(solid, buf, np.uint8(32))[keep]
    moved = np.cumsum(keep) - 1
    begin = moved[starts]
    finish = begin + (ends - starts)
    many = np.diff(first)
    grams = np.where(many >= shingle, many - shingle + 1, np.minimum(many, 1))
    edge = np.concatenate([[0], np.cumsum(grams)])
    total = int(edge[-1])
    doc = np.repeat(np.arange(chunk.n), grams)
    head = first[doc] + np.arange(total) - edge[doc]
    tail = np.minimum(head + shingle, first[doc + 1]) - 1
    counts = np.zeros((chunk.n, 64), np.int64)
    for a in range(0, total, _BLOCK):
        b = min(a + _BLOCK, total)
        h = xxh64_spans(line, begin[head[a:b]], finish[tail[a:b]])
        bits = np.unpackbits(h.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        d = doc[a:b]
        at = np.flatnonzero(np.concatenate([[True], d[1:] != d[:-1]]))
        counts[d[at]] += np.add.reduceat(bits, at, axis=0, dtype=np.int32)
    ones = (2 * counts > grams[:, None]).astype(np.uint8)
    return np.packbits(ones, axis=1, bitorder="little").view("<u8").ravel().astype(np.uint64)


def fingerprints(docs: DataFrame, keys: list[str], *, text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """``keys`` and ``fp`` (the fingerprint as a signed long).  Null and empty texts get 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [chunk_fingerprints(c, shingle) for c in chunks(batch.column(len(keys)))]
            fp = np.concatenate(found).view(np.int64) if found else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(fp)], names=[*keys, "fp"])

    schema = T.StructType([T.StructField(k, docs.schema[k].dataType) for k in keys] + [T.StructField("fp", T.LongType())])
    return docs.select(*keys, text_col).mapInArrow(run, schema)


def _signed(x: int) -> Column:
    return F.lit(x - (1 << 64) if x >> 63 else x).cast("long")


def _popcount_cells(fp: Column) -> Column:
    """Packed bit counts (0, 1 or 2) of the 32 two-bit segments."""
    even = _signed(0x5555555555555555)
    shifted = F.shiftrightunsigned(fp, 1)
    one = fp.bitwiseXOR(shifted).bitwiseAND(even)
    two = fp.bitwiseAND(shifted).bitwiseAND(even)
    return one.bitwiseOR(F.shiftleft(two, 1))


def _grids(nodes: int) -> list[int]:
    """Masks over the packed counts, one per grid: all but two of the blocks into which the segments are dealt.

    Vectors within Manhattan distance two differ in at most two segments' blocks or in one, so they are
    equal on all others and share a cell of at least one grid.  More rows take more, smaller blocks: a
    cell then meets fewer strangers (two random fingerprints agree on a segment with chance 3/8).
    """
    for blocks in (6, 8, 10, 12, 16):
        edge = [SEGMENTS * i // blocks for i in range(blocks + 1)]
        part = [sum(3 << 2 * j for j in range(a, b)) for a, b in zip(edge, edge[1:], strict=False)]
        whole = (1 << 2 * SEGMENTS) - 1
        masks = [whole & ~(part[i] | part[j]) for j in range(blocks) for i in range(j)]
        if nodes * sum(0.375 ** (m.bit_count() // 2) for m in masks) <= 1:
            break
    return masks


def links(distinct: DataFrame, max_bits: int = 2) -> DataFrame:
    """Links ``(a, b)`` between distinct fingerprints ``fp`` that connect all pairs within ``max_bits``.

    Every returned pair is within ``max_bits``; every pair within ``max_bits`` is connected by them.
    ``distinct`` must be stored: it is read more than once.
    """
    if max_bits not in (0, 1, 2):
        raise ValueError("the range join leaves out two blocks of segments: at most two bits")
    masks = _grids(distinct.count())
    # each row makes one per grid: deal rows to all tasks, or a few tasks would make all cells
    spread = distinct.repartition(task_count(distinct.sparkSession)).select("fp", _popcount_cells(F.col("fp")).alias("own"))
    cells = spread.select("fp", F.explode(F.array(*[F.xxhash64(F.lit(k), F.col("own").bitwiseAND(_signed(m))) for k, m in enumerate(masks)])).alias("cell"))
    with scoped(distinct.sparkSession, THIN):
        shared = staged(cells.groupBy("cell").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "simhash-shared")
        crowd = staged(cells.join(shared, "cell").select("cell", "fp", "n"), "simhash-cells")
    few = crowd.where(F.col("n") <= PAIRS).select("cell", "fp")
    near = F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= max_bits
    pairs = few.select("cell", F.col("fp").alias("a")).join(few.select(F.col("cell").alias("c2"), F.col("fp").alias("b")), (F.col("cell") == F.col("c2")) & (F.col("a") < F.col("b")) & near).select("a", "b")
    many = crowd.where(F.col("n") > PAIRS).select("fp").distinct()
    flips = many.select("fp", F.explode(F.array(F.col("fp"), *[F.col("fp").bitwiseXOR(_signed(1 << j)) for j in range(64)])).alias("middle"))
    group = Window.partitionBy("middle").orderBy("fp")  # at most 65 fingerprints
    star = flips.withColumn("a", F.first("fp").over(group)).where("a <> fp").select("a", F.col("fp").alias("b"))
    if max_bits < 2:
        star = _tight(many, max_bits)
    return pairs.unionByName(star).distinct()


def _tight(many: DataFrame, max_bits: int) -> DataFrame:
    """Links at distance one inside crowded cells: a flip of one bit that is itself present."""
    flips = many.select(F.col("fp").alias("a"), F.explode(F.array(*[F.col("fp").bitwiseXOR(_signed(1 << j)) for j in range(64)])).alias("b"))
    return flips.where("a < b").join(many.select(F.col("fp").alias("b")), "b").select("a", "b").where(F.lit(max_bits == 1))


def near_groups(prints: DataFrame, id_col: str = "doc_id", max_bits: int = 2) -> DataFrame:
    """``(fp, component)`` for each distinct fingerprint; component = smallest id of its group.

    ``prints`` has one row per document and must be stored (it is read twice).  Null ids take part in
    linking but never name a group that has another id.
    """
    distinct = staged(prints.groupBy("fp").agg(F.min(id_col).alias("first")), "simhash-distinct")
    edges = links(distinct.select("fp"), max_bits)
    root = connected_components(edges, "a", "b").withColumnsRenamed({"id": "fp", "component": "root"})
    rooted = cut(distinct.join(root, "fp", "left").withColumn("root", F.coalesce("root", "fp")))
    return rooted.join(rooted.groupBy("root").agg(F.min("first").alias("component")), "root").select("fp", "root", "component")


def near_duplicates(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, max_bits: int = 2) -> DataFrame:
    """Per document: ``id, fp, component``.  Empty and null texts have fingerprint 0 and link as any other.

    Rows with equal ids are kept as rows; a null id gets the smallest id of its group, if there is one.
    """
    prints = staged(fingerprints(docs, [id_col], text_col=text_col, shingle=shingle), "simhash-prints")
    return prints.join(near_groups(prints, id_col, max_bits).select("fp", "component"), "fp").select(id_col, "fp", "component")


def keep_one_of_each(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, max_bits: int = 2) -> DataFrame:
    """One document of each group, all columns as they were: the smallest id (nulls last), then the smallest text hash."""
    keyed = docs.select(id_col, text_col).withColumn("__text", F.xxhash64(text_col))
    prints = staged(fingerprints(keyed.withColumnRenamed(id_col, "__id"), ["__id", "__text"], text_col=text_col, shingle=shingle), "simhash-prints")
    groups = near_groups(prints, "__id", max_bits)
    return first_of_each(docs, prints.join(groups.select("fp", "root"), "fp").select("__id", "__text", "root"), id_col, text_col)


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.col("component").alias("component_id"))
