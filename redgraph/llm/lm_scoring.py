"""Stupid-backoff language-model scores from n-gram count tables partitioned by hash.

Rows are dealt into batches of ``BATCH_BYTES`` of text by a hash of where they stand, so that rows equal
in all columns are dealt apart too.  Each batch folds its n-grams of an order to distinct 64-bit hashes
with counts and cuts the sorted list by leading hash bits into partitions of ``PART_BYTES`` of text: those
pieces are the rows of the n-gram relation, partitioned by hash, with one entry per batch however frequent
an n-gram is.  A partition sums its pieces to the count table and joins it back to every piece, in the
order of the piece, so only counts travel back.  Batches join their texts with these counts, and
every document sums the scores of its words.

Empty pieces are not written, and a partition is many batches long, so there are never more pieces than
distinct n-grams in the batches: at the most the plain exploded relation, folded by batch.

Counts cover all rows.  With ``leave_one_out`` (the default) a document is scored by the counts of
all other rows, so that its own n-grams do not pass as evidence.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from redgraph.llm.bytetext import ALNUM, FOLD, Chunk, chunks, gram_hashes, mixed, word_hashes
from redgraph.session import staged

ORDER = 3
BACKOFF = 0.4
BATCH_BYTES = 6 << 20  # of text; a batch is what a Python worker holds at once
PART_BYTES = 32 << 20  # of text whose n-grams of one order meet in a partition
_ALL_WORDS = np.uint64((1 << 64) - 1)  # stands for all n-grams together


class _Words:
    """The words of a batch of texts as hashes, with the document of each."""

    def __init__(self, texts: pa.ChunkedArray) -> None:
        hashes, counts = [], []
        for chunk in chunks(texts):
            buf = FOLD[chunk.buf]
            starts, ends, first = Chunk(0, buf, chunk.cuts).words(ALNUM)
            hashes.append(word_hashes(buf, starts, ends))
            counts.append(np.diff(first))
        self.words = np.concatenate(counts) if counts else np.empty(0, np.int64)
        self.hash = np.concatenate(hashes) if hashes else np.empty(0, np.uint64)
        self.first = np.concatenate([[0], np.cumsum(self.words)])
        self.doc = np.repeat(np.arange(len(self.words)), self.words)

    def grams(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Where n words of one document start, and their hash."""
        at = np.flatnonzero(self.first[self.doc + 1] - np.arange(len(self.hash)) >= n)
        return at, mixed(gram_hashes(self.hash, n)[at] ^ np.uint64(n * 0x632BE59BD9B4E019 & 0xFFFFFFFFFFFFFFFF))


def _distinct(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashes with counts; the last entry counts all of them."""
    every, n = np.unique(hashes[hashes != _ALL_WORDS], return_counts=True)
    return np.append(every, _ALL_WORDS), np.append(n, len(hashes))


def _packed(x: np.ndarray) -> bytes:
    """Unsigned integers as planes of equal bytes, as few planes as the largest needs."""
    planes = max(1, (int(x.max()).bit_length() + 7) // 8) if len(x) else 1
    return bytes([planes]) + x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :planes].T.tobytes()


def _unpacked(b: bytes) -> np.ndarray:
    planes = b[0]
    raw = np.frombuffer(b, np.uint8, offset=1).reshape(planes, -1)
    out = np.zeros((raw.shape[1], 8), np.uint8)
    out[:, :planes] = raw.T
    return out.view("<u8").ravel()


def _pieces(n: int, bits: int):
    def fold(table: pa.Table) -> pa.Table:
        batch = table.column("__batch")[0].as_py()
        every, count = _distinct(_Words(table.column("__text")).grams(n)[1])
        edge = np.searchsorted(every, np.arange(1, 1 << bits, dtype=np.uint64) << np.uint64(64 - bits)) if bits else np.empty(0, np.int64)
        edge = np.concatenate([[0], edge, [len(every)]])
        parts = [k for k in range(1 << bits) if edge[k] < edge[k + 1]]
        keys = []
        for k in parts:
            own = every[edge[k] : edge[k + 1]]
            keys.append(_packed(np.diff(own, prepend=np.uint64(k << (64 - bits) if bits else 0))))
        return pa.table({"part": pa.array(parts, pa.int32()), "batch": pa.array([batch] * len(parts), pa.int64()), "keys": pa.array(keys, pa.binary()), "counts": pa.array([_packed(count[edge[k] : edge[k + 1]]) for k in parts], pa.binary())})

    return fold


def _totals(table: pa.Table) -> pa.Table:
    """The count table of one hash partition, joined back to each piece."""
    keys = [np.cumsum(_unpacked(b.as_buffer()), dtype=np.uint64) for b in table.column("keys")]
    counts = [_unpacked(b.as_buffer()) for b in table.column("counts")]
    edge = np.cumsum([0, *map(len, keys)])
    _, entry = np.unique(np.concatenate(keys), return_inverse=True)
    total = np.bincount(entry, weights=np.concatenate(counts)).astype(np.uint64)
    told = [_packed(total[entry[a:b]]) for a, b in zip(edge[:-1], edge[1:], strict=True)]
    return pa.table({"batch": table.column("batch"), "part": table.column("part"), "totals": pa.array(told, pa.binary())})


def _scorer(order: int, backoff: float, leave_one_out: bool, id_col: str):
    def score(docs: pa.Table, told: pa.Table) -> pa.Table:
        text = _Words(docs.column("__text"))
        told = told.sort_by([("n", "ascending"), ("part", "ascending")])
        level = told.column("n").to_numpy()
        n_docs, size = len(text.words), len(text.doc)
        seen = np.zeros((order, size), np.int64)
        for k in range(order):
            at, h = text.grams(k + 1)
            every, _ = _distinct(h)
            total = np.concatenate([_unpacked(told.column("totals")[i].as_buffer()) for i in np.flatnonzero(level == k + 1).tolist()]).astype(np.int64)
            if len(total) != len(every):
                raise RuntimeError("a batch changed between two readings")
            entry = np.searchsorted(every, h)
            value = total[entry]
            if leave_one_out and len(entry):
                _, inverse, own = np.unique(text.doc[at] * len(every) + entry, return_inverse=True, return_counts=True)
                value = value - own[inverse]
            seen[k, at] = value
            if not k:
                everything = total[-1]
        words = everything - (text.words[text.doc] if leave_one_out else 0)
        place = np.arange(size) - text.first[text.doc]
        result = np.where(seen[0] > 0, np.log(np.maximum(seen[0], 1)) - np.log(np.maximum(words, 1)), -np.log(words + 1.0))
        used = np.ones(size, np.int64)
        for k in range(2, order + 1):
            i = np.flatnonzero(place >= k - 1)
            whole, context = seen[k - 1, i - k + 1], seen[k - 2, i - k + 1]
            hit = whole > 0
            result[i[hit]] = np.log(whole[hit]) - np.log(context[hit])
            result[i[~hit]] += math.log(backoff)
            used[i[hit]] = k
        sums = np.bincount(text.doc, weights=result, minlength=n_docs)
        full = np.bincount(text.doc, weights=used == order, minlength=n_docs).astype(np.int64)
        return pa.table({id_col: docs.column("__id"), "n_words": pa.array(text.words, pa.int64()), "log_score": pa.array(sums, pa.float64()), "n_full": pa.array(full, pa.int64())})

    return score


def batch_plan(size: int, batch_bytes: int, part_bytes: int) -> tuple[int, int]:
    """Batches and bits of the hash that name a partition, for so many bytes of text."""
    return max(1, -(-size // batch_bytes)), max(0, (-(-size // part_bytes) - 1).bit_length())


def placed_rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """``__id, __text, __at``: ``__at`` is a hash of the file and row where a row stands, else of a written row number."""
    take = [F.col(id_col).alias("__id"), F.col(text_col).alias("__text")]
    try:
        return docs.select(*take, F.xxhash64("_metadata.file_path", "_metadata.row_index").alias("__at"))
    except AnalysisException:  # not a plain scan of files
        numbered = staged(docs.select(*take, F.monotonically_increasing_id().alias("__row")), "ngram-rows")
        return numbered.select("__id", "__text", F.xxhash64("__row").alias("__at"))


def score_documents(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", order: int = ORDER, backoff: float = BACKOFF, leave_one_out: bool = True, batch_bytes: int = BATCH_BYTES, part_bytes: int = PART_BYTES) -> DataFrame:
    """Per row: ``id, n_words, log_score`` (sum of natural logs), ``n_full`` (words scored without backing off).

    A word takes the longest n-gram of its document that was seen, each step down costs ``backoff``;
    the first words of a document have shorter contexts.  A word that was never seen scores as one in
    (all words + 1).  Null and empty texts have no words and score 0.  Rows with equal ids are scored
    apart, each by the counts of all other rows.  An empty table gives no rows; other columns are not
    read, whatever their names.
    """
    spark = docs.sparkSession
    rows = placed_rows(docs, id_col, text_col)
    size = rows.agg(F.sum(F.octet_length(F.coalesce("__text", F.lit(""))) + 1)).first()[0] or 0
    batches, bits = batch_plan(size, batch_bytes, part_bytes)
    rows = rows.select("__id", "__text", F.pmod("__at", F.lit(batches)).alias("__batch"))
    dealt = rows.groupBy("__batch")
    told = None
    for n in range(1, order + 1):  # one order at a time: what is exchanged for one is gone before the next
        pieces = dealt.applyInArrow(_pieces(n, bits), "part int, batch long, keys binary, counts binary")
        level = staged(pieces.groupBy("part").applyInArrow(_totals, "batch long, part int, totals binary"), f"ngram-totals-{n}").withColumn("n", F.lit(n))
        told = level if told is None else told.unionByName(level)
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), T.StructField("n_words", T.LongType()), T.StructField("log_score", T.DoubleType()), T.StructField("n_full", T.LongType())])
    if not size:
        return spark.createDataFrame([], schema)
    return dealt.cogroup(told.groupBy("batch")).applyInArrow(_scorer(order, backoff, leave_one_out, id_col), schema)


def op8_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = score_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select("doc_id", "n_words", F.round("log_score", 5).alias("log_score"), "n_full")


SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS w FROM documents),
t AS (SELECT r, i, w[i] AS a, w[i - 1] AS b, w[i - 2] AS c, len(w) AS m FROM (SELECT r, w, unnest(range(1, len(w) + 1)) AS i FROM d)),
u AS (SELECT *, count(*) OVER (PARTITION BY a) - count(*) OVER (PARTITION BY r, a) AS u1, count(*) OVER () - m AS n FROM t),
b2 AS (SELECT *, CASE WHEN i > 1 THEN count(*) FILTER (i > 1) OVER (PARTITION BY b, a) - count(*) FILTER (i > 1) OVER (PARTITION BY r, b, a) END AS u2, lag(u1) OVER (PARTITION BY r ORDER BY i) AS p1 FROM u),
b3 AS (SELECT *, CASE WHEN i > 2 THEN count(*) FILTER (i > 2) OVER (PARTITION BY c, b, a) - count(*) FILTER (i > 2) OVER (PARTITION BY r, c, b, a) END AS u3, lag(u2) OVER (PARTITION BY r ORDER BY i) AS p2 FROM b2),
s AS (SELECT r, CASE WHEN u3 > 0 THEN ln(u3) - ln(p2) ELSE CASE WHEN i > 2 THEN ln(0.4) ELSE 0 END + CASE WHEN u2 > 0 THEN ln(u2) - ln(p1) ELSE CASE WHEN i > 1 THEN ln(0.4) ELSE 0 END +
      CASE WHEN u1 > 0 THEN ln(u1) - ln(n) ELSE -ln(n + 1) END END END AS x, coalesce(u3 > 0, false) AS full3 FROM b3)
SELECT doc_id, CAST(len(any_value(w)) AS BIGINT) AS n_words, round(coalesce(sum(x), 0), 5) AS log_score, CAST(coalesce(sum(full3::INT), 0) AS BIGINT) AS n_full
FROM d LEFT JOIN s USING (r) GROUP BY r, doc_id
"""
