"""Benchmark decontamination with suffix arrays over the training text.

Each task cuts its training rows into shards of bounded size, builds a suffix array over the words
of a shard and binary-searches every suffix of every benchmark item in it.  Windows of ``window``
consecutive item words (an item with fewer words is one window) mark the training words that they cover.
Suffixes that begin with one window share its search; from there each of them is followed at every
location for as long as the words agree, which yields its longest verbatim matches.

The array is sparse: a match of ``window`` words can only start where that many words in a row occur
in the benchmark at all, so other positions are left out before sorting.  It is sorted by the words of
a window, the part that is searched.  Words compare by a 64-bit hash; words inside hits are compared
byte by byte afterwards.

There is no shuffle: benchmark items travel to the rows, in blocks of at most ``block_bytes``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from redgraph.llm.bytetext import ALNUM, FOLD, Chunk, chunks, word_hashes
from redgraph.session import cut, staged

WINDOW = 10
BLOCK_BYTES = 16 << 20
SPANS = "array<struct<item_id:string,item_word:int,doc_word:int,length:int>>"
COVER = "array<struct<doc_word:int,length:int>>"


@dataclass
class Block:
    """A bounded part of the benchmark, ready to be searched."""

    vocabulary: np.ndarray  # sorted word hashes; the id of a word is its place plus one
    spelling: list[bytes]
    words: np.ndarray  # ids of all item words, one after the other, each item followed by a 0
    item_of: np.ndarray  # item number of each of them
    place: np.ndarray  # its place in the item
    items: list[str]
    start: np.ndarray  # distinct windows: place in ``words`` of the first suffix that begins with it
    width: np.ndarray  # words of the window
    suffix_from: np.ndarray  # windows to all suffixes that begin with them, as compressed rows
    suffixes: np.ndarray
    owner_from: np.ndarray  # windows to items, likewise
    owners: np.ndarray
    least: int  # shortest window
    short: np.ndarray  # by word id: shortest window that starts with the word

    @staticmethod
    def of(rows: list[tuple[str, str | None]], window: int) -> Block:
        texts = pa.array([t or "" for _, t in rows], pa.large_string())
        per_item: list[np.ndarray] = []
        names: dict[int, bytes] = {}
        for chunk in chunks(texts):
            buf = FOLD[chunk.buf]
            starts, ends, first = Chunk(0, buf, chunk.cuts).words(ALNUM)
            h = word_hashes(buf, starts, ends)
            for x, a, b in zip(h.tolist(), starts.tolist(), ends.tolist(), strict=True):
                names.setdefault(x, buf[a:b].tobytes())
            per_item += [h[first[i] : first[i + 1]] for i in range(chunk.n)]
        vocabulary = np.array(sorted(names), np.uint64)
        words, item_of, place = [], [], []
        found: dict[bytes, int] = {}
        start, width, suffixes, owners = [], [], [], []
        short = np.full(len(vocabulary) + 1, window, np.int64)
        at = 0
        for i, h in enumerate(per_item):
            ids = np.searchsorted(vocabulary, h).astype(np.int32) + 1
            words += [ids, np.zeros(1, np.int32)]
            item_of.append(np.full(len(h) + 1, i))
            place.append(np.arange(len(h) + 1))
            w = min(window, len(h))
            if w and w < window:
                short[ids[0]] = min(short[ids[0]], w)
            for j in range(len(h) - w + 1 if w else 0):
                key = ids[j : j + w].tobytes()
                if key not in found:
                    found[key] = len(start)
                    start.append(at + j)
                    width.append(w)
                    suffixes.append([])
                    owners.append([])
                k = found[key]
                suffixes[k].append(at + j)
                if not owners[k] or owners[k][-1] != i:
                    owners[k].append(i)
            at += len(h) + 1
        flat = lambda xs, kind: np.concatenate(xs).astype(kind) if xs else np.empty(0, kind)
        return Block(
            vocabulary, [names[x] for x in vocabulary.tolist()], flat(words, np.int32), flat(item_of, np.int64), flat(place, np.int64), [r[0] for r in rows],
            np.array(start, np.int64), np.array(width, np.int64), np.cumsum([0, *map(len, suffixes)]), flat([np.array(s) for s in suffixes], np.int64), np.cumsum([0, *map(len, owners)]), flat([np.array(o) for o in owners], np.int64),
            min(width, default=window), short,
        )


def sparse_suffix_array(ids: np.ndarray, run: np.ndarray, at: np.ndarray, depth: int, vocabulary: int) -> np.ndarray:
    """Sort the suffixes that start at ``at`` by their first ``depth`` words.

    A suffix ends after ``run`` words (a word unknown to the benchmark or the document's end), which
    sorts before any word.  Several words are packed in one key; only ties are looked at further.
    """
    bits = max(1, int(vocabulary + 1).bit_length())
    step = max(1, 62 // bits)
    order = np.arange(len(at))

    def key(of: np.ndarray, skip: int) -> np.ndarray:
        k = np.zeros(len(of), np.int64)
        for d in range(skip, skip + step):
            k <<= bits
            alive = run[of] > d
            k[alive] |= ids[of[alive] + d]
        return k

    k = key(at, 0)
    order = np.argsort(k, kind="stable")
    group = np.concatenate([[0], np.cumsum(k[order][1:] != k[order][:-1])]) if len(at) else order
    done = step
    while done < depth and len(at):
        tied = np.zeros(len(at), bool)
        same = group[1:] == group[:-1]
        tied[1:] |= same
        tied[:-1] |= same
        tied &= run[at[order]] > done
        slot = np.flatnonzero(tied)
        if not len(slot):
            break
        # members that end here sort first; they already do, as the others only move among
        # themselves behind them
        ended = np.zeros(len(at), bool)
        ended[run[at[order]] <= done] = True
        block = np.lexsort((~ended, group))
        order = order[block]
        slot = np.flatnonzero(tied[block])
        of = order[slot]
        k = key(at[of], done)
        inner = np.lexsort((k, group[slot]))
        order[slot] = of[inner]
        k, g = k[inner], group[slot]
        fresh = np.ones(len(at), bool)
        fresh[1:] = group[1:] != group[:-1]
        more = np.ones(len(slot), bool)
        more[1:] = (k[1:] != k[:-1]) | (g[1:] != g[:-1])
        fresh[slot] |= more
        group = np.cumsum(fresh) - 1
        done += step
    return at[order]


def narrowed(word: np.ndarray, suffixes: np.ndarray, ids: np.ndarray, run: np.ndarray, depth: int, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Binary search, for many queries at once: the part of [lo, hi) whose word at ``depth`` is ``word``."""

    def bound(target: np.ndarray) -> np.ndarray:
        a, b = lo.copy(), hi.copy()
        while True:
            open_ = a < b
            if not open_.any():
                return a
            mid = (a + b) >> 1
            p = suffixes[np.minimum(mid, len(suffixes) - 1)]
            value = np.where(run[p] > depth, ids[np.minimum(p + depth, len(ids) - 1)], 0)
            less = open_ & (value < target)
            a = np.where(less, mid + 1, a)
            b = np.where(open_ & ~less, mid, b)

    return bound(word), bound(word + 1)


def search_shard(block: Block, chunk: Chunk, window: int) -> dict[str, list]:
    """Word, hit and item counts of each document of a shard.

    ``spans`` has a row for each longest match: document, item, word of the item, word of the document, length.
    """
    buf = FOLD[chunk.buf]
    starts, ends, first = Chunk(chunk.row, buf, chunk.cuts).words(ALNUM)
    n_words = np.diff(first)
    out = {"n_words": n_words.tolist(), "n_hit": [0] * chunk.n, "items": [[] for _ in range(chunk.n)], "cover": [[] for _ in range(chunk.n)], "spans": np.empty((0, 5), np.int64)}
    if not len(starts) or not len(block.start):
        return out
    h = word_hashes(buf, starts, ends)
    slot = np.minimum(np.searchsorted(block.vocabulary, h), len(block.vocabulary) - 1)
    ids = np.where(block.vocabulary[slot] == h, slot + 1, 0).astype(np.int64)
    while True:
        found = _search(block, ids, first, window)
        if found is None:
            return out
        at, query, cover = found
        wrong = [i for i in np.flatnonzero(cover).tolist() if buf[starts[i] : ends[i]].tobytes() != block.spelling[ids[i] - 1]]
        if not wrong:
            break
        ids[wrong] = 0  # equal hashes of different words: such a word is unknown to the benchmark
    hit = np.concatenate([[0], np.cumsum(cover)])
    out["n_hit"] = (hit[first[1:]] - hit[first[:-1]]).tolist()
    opens = cover & ~np.concatenate([[False], cover[:-1]])
    opens[first[:-1][n_words > 0]] |= cover[first[:-1][n_words > 0]]
    opens = np.flatnonzero(opens)
    for p, n in zip(opens.tolist(), (hit[np.append(opens[1:], len(cover))] - hit[opens]).tolist(), strict=True):
        d = int(np.searchsorted(first, p, side="right")) - 1
        out["cover"][d].append((int(p - first[d]), n))
    s, p, length = longest_matches(block, ids, first, at, query)
    d = np.searchsorted(first, p, side="right") - 1
    spans = np.stack([d, block.item_of[s], block.place[s], p - first[d], length], axis=1)
    out["spans"] = spans[np.lexsort(spans.T[::-1])]
    doc = np.searchsorted(first, at, side="right") - 1
    pairs = np.unique(doc * len(block.start) + query)
    doc, query = pairs // len(block.start), pairs % len(block.start)
    many = block.owner_from[query + 1] - block.owner_from[query]
    index = np.repeat(block.owner_from[query] - np.concatenate([[0], np.cumsum(many)[:-1]]), many) + np.arange(many.sum())
    both = np.unique(np.repeat(doc, many) * len(block.items) + block.owners[index])
    for x in both.tolist():
        out["items"][x // len(block.items)].append(block.items[x % len(block.items)])
    return out


def _search(block: Block, ids: np.ndarray, first: np.ndarray, window: int):
    n = len(ids)
    stop = np.where(ids == 0, np.arange(n), n)
    stop = np.minimum.accumulate(stop[::-1])[::-1]
    border = first[np.minimum(np.searchsorted(first, np.arange(n), side="right"), len(first) - 1)]
    run = np.minimum(stop, border) - np.arange(n)
    at = np.flatnonzero((run >= block.least) & (run >= block.short[ids]) & (ids > 0))
    if not len(at):
        return None
    suffixes = sparse_suffix_array(ids, run, at, int(block.width.max()), len(block.vocabulary))
    live = np.arange(len(block.start))
    lo, hi = np.zeros(len(live), np.int64), np.full(len(live), len(suffixes), np.int64)
    places, queries = [], []
    depth = 0
    while len(live):
        lo, hi = narrowed(block.words[block.start[live] + depth], suffixes, ids, run, depth, lo, hi)
        depth += 1
        there = lo < hi
        for k in np.flatnonzero(there & (block.width[live] == depth)).tolist():
            p = suffixes[lo[k] : hi[k]]
            places.append(p)
            queries.append(np.full(len(p), live[k]))
        there &= block.width[live] > depth
        live, lo, hi = live[there], lo[there], hi[there]
    if not places:
        return None
    at, query = np.concatenate(places), np.concatenate(queries)
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + block.width[query], -1)
    return at, query, np.cumsum(edge[:-1]) > 0


def longest_matches(block: Block, ids: np.ndarray, first: np.ndarray, at: np.ndarray, query: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Item place, document place and length of every match that no further word on either side extends.

    ``query`` are the windows found and ``at`` where.  A suffix and a location with the same word before them
    are the rest of a longer match, so only pairs with different words before them are formed at all.
    """
    opening = np.zeros(len(ids) + 1, bool)
    opening[first] = True
    before = np.where(opening[at] | (ids[at - 1] == 0), -1, ids[at - 1])  # a border equals no word
    order = np.lexsort((before, query))
    at, before, query = at[order], before[order], query[order]
    windows, begins = np.unique(query, return_index=True)
    pairs = [(np.empty(0, np.int64),) * 3]
    for k, a, b in zip(windows.tolist(), begins.tolist(), np.append(begins[1:], len(query)).tolist(), strict=True):
        s = block.suffixes[block.suffix_from[k] : block.suffix_from[k + 1]]
        left = block.words[s - 1]  # the 0 behind an item stands before the next one, and the last before the first
        for x in np.unique(left).tolist():
            c, d = a + np.searchsorted(before[a:b], [x, x + 1])
            p, some = np.concatenate([at[a:c], at[d:b]]), s[left == x]
            pairs.append((np.repeat(some, len(p)), np.tile(p, len(some)), np.full(len(p) * len(some), block.width[k])))
    s, p, length = (np.concatenate(x) for x in zip(*pairs, strict=True))
    limit = first[np.searchsorted(first, p, side="right")] - p
    going = np.arange(len(s))
    while len(going):
        n = length[going]
        inside = n < limit[going]
        word = ids[np.minimum(p[going] + n, len(ids) - 1)]
        going = going[inside & (word > 0) & (word == block.words[s[going] + n])]
        length[going] += 1
    return s, p, length


def benchmark_blocks(benchmark: DataFrame, id_col: str, text_col: str, block_bytes: int) -> Iterator[list[tuple[str, str | None]]]:
    """The benchmark in blocks of bounded size; only one partition and one block are on the driver."""
    rows, size = [], 0
    for item, text in benchmark.select(F.col(id_col).cast("string"), F.col(text_col)).toLocalIterator():
        rows.append(("" if item is None else item, text))
        size += 64 + 4 * len(text or "")
        if size >= block_bytes:
            yield rows
            rows, size = [], 0
    if rows:
        yield rows


def match_benchmark(
    docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = WINDOW, block_bytes: int = BLOCK_BYTES
) -> DataFrame:
    """Per training row: ``id, n_words, n_hit, items`` (sorted), ``cover`` (runs of hit words) and ``spans``.

    ``spans`` holds the longest matches of every benchmark suffix and where they lie: each verbatim match of
    at least a window that no further word on either side extends, once per item and location.  A row's spans
    depend on no other row.

    Null or empty texts have no words and no hits; a null item id counts as the empty string; equal
    items are all listed; other columns are not read.  With several blocks a row's hit words are
    joined by interval, so that a word that two blocks cover counts once.
    """
    spark = docs.sparkSession
    kind = docs.schema[id_col].dataType
    schema = T.StructType([T.StructField(id_col, kind), T.StructField("n_words", T.LongType()), T.StructField("n_hit", T.LongType()), T.StructField("items", T.ArrayType(T.StringType())), T.StructField("cover", T._parse_datatype_string(COVER)), T.StructField("spans", T._parse_datatype_string(SPANS))])
    blocks = [spark.sparkContext.broadcast(Block.of(rows, window)) for rows in benchmark_blocks(benchmark, item_col, item_text_col, block_bytes)]
    if len(blocks) < 2:
        return docs.select(id_col, text_col).mapInArrow(_matcher(blocks[0] if blocks else None, window), schema)
    # ids may repeat or be null: the rows are numbered once and joined by that number
    numbered = staged(docs.select(F.monotonically_increasing_id().alias("__row"), F.col(id_col), F.col(text_col)), "benchmark-rows")
    by_row = T.StructType([T.StructField("__row", T.LongType()), *schema.fields[1:]])
    joined = _joined([numbered.select("__row", text_col).mapInArrow(_matcher(shared, window), by_row) for shared in blocks])
    return numbered.select("__row", id_col).join(joined, "__row").select(*schema.names)


def _joined(parts: list[DataFrame]) -> DataFrame:
    """Several blocks: rows are joined by their number; covered runs are merged, so that a word counts once."""
    every = None
    for p in parts:
        p = cut(p)
        every = p if every is None else every.unionByName(p)
    runs = F.array_sort(F.flatten(F.collect_list("cover")))
    merged = F.aggregate(
        runs,
        F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("to")),
        lambda s, x: F.struct((s.n + F.greatest(F.lit(0).cast("long"), x.doc_word + x.length - F.greatest(s.to, x.doc_word.cast("long")))).alias("n"), F.greatest(s.to, (x.doc_word + x.length).cast("long")).alias("to")),
        lambda s: s.n,
    )
    items = F.array_sort(F.array_distinct(F.flatten(F.collect_list("items"))))
    return every.groupBy("__row").agg(F.max("n_words").alias("n_words"), merged.alias("n_hit"), items.alias("items"), runs.alias("cover"), F.flatten(F.collect_list("spans")).alias("spans"))


def _span_lists(spans: np.ndarray, n: int, items: list[str]) -> pa.Array:
    """Rows of ``spans``, ordered by document, as one list a document."""
    columns = [pa.array(items, pa.string()).take(pa.array(spans[:, 1])), *(pa.array(spans[:, k], pa.int32()) for k in (2, 3, 4))]
    offsets = pa.array(np.searchsorted(spans[:, 0], np.arange(n + 1)), pa.int32())
    return pa.ListArray.from_arrays(offsets, pa.StructArray.from_arrays(columns, names=["item_id", "item_word", "doc_word", "length"]))


def _matcher(shared, window: int):
    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = shared.value if shared is not None else Block.of([], window)
        names = None
        for batch in batches:
            names = names or batch.schema.names
            for chunk in chunks(batch.column(1)):
                found = search_shard(block, chunk, window)
                n = chunk.n
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(chunk.row, n), pa.array(found["n_words"], pa.int64()), pa.array(found["n_hit"], pa.int64()), pa.array([sorted(x) for x in found["items"]], pa.list_(pa.string())),
                        pa.array([[dict(zip(("doc_word", "length"), s, strict=True)) for s in x] for x in found["cover"]], pa.list_(pa.struct([("doc_word", pa.int32()), ("length", pa.int32())]))),
                        _span_lists(found["spans"], n, block.items),
                    ],
                    names=[names[0], "n_words", "n_hit", "items", "cover", "spans"],
                )

    return match


def remove_contaminated(docs: DataFrame, benchmark: DataFrame, *, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The rows of ``docs`` that no benchmark window hits, all columns as they were, without a shuffle."""
    spark, at = docs.sparkSession, docs.columns.index(text_col)

    def keeper(shared):
        def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                clean: list[bool] = []
                for chunk in chunks(batch.column(at)):
                    clean += [n == 0 for n in search_shard(shared.value, chunk, window)["n_hit"]]
                yield batch.filter(pa.array(clean, pa.bool_()))

        return keep

    for k, rows in enumerate(benchmark_blocks(benchmark, item_col, item_text_col, block_bytes)):
        docs = (cut(docs) if k else docs).mapInArrow(keeper(spark.sparkContext.broadcast(Block.of(rows, window))), docs.schema)
    return docs


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = match_benchmark(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    items = F.concat_ws(",", F.array_sort(F.array_distinct("items")))
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(items, 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated")
    )


SQL = r"""
WITH iw AS (SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
win AS (SELECT DISTINCT item_id, least(10, len(w)) AS k, array_to_string(w[i:i + least(10, len(w)) - 1], ' ') AS g
        FROM (SELECT item_id, w, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS i FROM iw WHERE len(w) > 0)),
dw AS (SELECT row_number() OVER () AS r, doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS w FROM documents),
dg AS (SELECT r, k, i, array_to_string(w[i:i + k - 1], ' ') AS g
       FROM (SELECT r, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM dw, (SELECT DISTINCT k FROM win) WHERE len(w) >= k)),
hit AS (SELECT r, i, dg.k, item_id FROM dg JOIN win ON dg.g = win.g AND dg.k = win.k),
covered AS (SELECT r, count(DISTINCT p) AS n FROM (SELECT r, unnest(range(i, i + k)) AS p FROM (SELECT DISTINCT r, i, k FROM hit)) GROUP BY r),
found AS (SELECT r, count(*) AS n, string_agg(CAST(item_id AS VARCHAR), ',' ORDER BY CAST(item_id AS VARCHAR)) AS s FROM (SELECT DISTINCT r, item_id FROM hit) GROUP BY r)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(covered.n, 0) AS BIGINT) AS n_hit, CAST(coalesce(found.n, 0) AS BIGINT) AS n_items,
       sha256(coalesce(found.s, '')) AS items_sha256, coalesce(covered.n, 0) > 0 AS contaminated
FROM dw LEFT JOIN covered USING (r) LEFT JOIN found USING (r)
"""
