"""Toxic passages as maximum-scoring segments over token log-odds.

A word scores the log-odds of its use in toxic against clean labelled text.  Words that the labels
show too rarely take the odds of their longest known prefix: the counts of a token are smoothed by a
Dirichlet prior whose mean is the toxic share of its parent prefix, down to the share of all words.
One linear scan over a document finds all maximal scoring segments, that is every passage whose score
no extension or cut improves.  The best score of clean text of a given length follows an extreme
value law, fitted on clean labelled documents; it gives every segment an E-value, and a logistic
curve on the calibrated scores gives the probability that the document is toxic.

Fitting uses at most ``FIT_ROWS`` labelled rows (those of the smallest id digests) and all their tokens
that are in at least ``LEAST`` of them; that bound on rows also bounds the model.  Scores for calibration
come from the other half of these rows.  All else runs over whole texts of all rows, without a shuffle.
Of labelled rows with one text the majority of labels counts, an even split as clean.  Only the id, text
and label columns are read, so other columns of any name (``key``, ``label``, ``score``) do no harm.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from redgraph.llm.bytetext import ALNUM, FOLD, Chunk, chunks, mixed, word_hashes
from redgraph.session import staged

FIT_ROWS = 24_000
PREFIXES = (9, 8, 7, 6, 5, 4)  # bytes, deepest first
PRIOR = 4.0
LEAST = 3
SURE = 1.3  # standard deviations that the log-odds must keep on their side of 0
FLAT = 0.7  # weaker evidence than this counts as none
DRIFT = 0.08  # what a word without evidence costs a passage
E_VALUE = 0.05
RATES = (0.1, 8.0)  # bounds of the extreme-value rate
IDLE = 2.0  # a segment adds evidence beyond this score times the rate
SEGMENTS = "array<struct<word:int,words:int,score:double,e_value:double>>"


@dataclass
class Model:
    """Sorted token hashes with scores, the extreme-value law (rate, size) and the logistic curve."""

    tokens: np.ndarray
    scores: np.ndarray
    rate: float = 1.0
    size: float = 1.0
    curve: tuple[float, ...] = (-8.0, 1.0, 0.0)


def token_hashes(h: np.ndarray, level: int) -> np.ndarray:
    return mixed(h ^ np.uint64(0x9E3779B97F4A7C15 * (level + 1) & 0xFFFFFFFFFFFFFFFF))


def word_scores(model: Model, buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Score of each word: its own if known, else that of its longest known prefix, else the drift."""
    out = np.zeros(len(starts))
    if not len(model.tokens):
        return out - DRIFT
    left = np.arange(len(starts))
    for level, size in enumerate((0, *PREFIXES)):
        use = left if not size else left[ends[left] - starts[left] >= size]
        if len(use):
            h = token_hashes(word_hashes(buf, starts[use], ends[use] if not size else starts[use] + size), level)
            at = np.minimum(np.searchsorted(model.tokens, h), len(model.tokens) - 1)
            known = model.tokens[at] == h
            out[use[known]] = model.scores[at[known]]
            rest = np.ones(len(starts), bool)
            rest[use[known]] = False
            left = left[rest[left]]
    return np.where(np.abs(out) < FLAT, 0.0, out) - DRIFT


def maximal_segments(scores: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring segments ``(first, last, score)`` of a sequence, in one linear scan."""
    total = np.concatenate([[0.0], np.cumsum(scores)])
    stack: list[tuple[int, int, float, float, int]] = []  # first, last, sum before, sum through, nearest with a smaller sum before
    for i in np.flatnonzero(scores > 0).tolist():
        first, last, left, right = i, i, float(total[i]), float(total[i + 1])
        while True:
            j = len(stack) - 1
            while j >= 0 and stack[j][2] >= left:
                j = stack[j][4]
            if j < 0 or stack[j][3] >= right:
                stack.append((first, last, left, right, j))
                break
            first, left = stack[j][0], stack[j][2]
            del stack[j:]
    return [(a, b, right - left) for a, b, left, right, _ in stack]


def chunk_segments(model: Model, chunk: Chunk) -> tuple[np.ndarray, list[list[tuple[int, int, float]]]]:
    buf = FOLD[chunk.buf]
    starts, ends, first = Chunk(chunk.row, buf, chunk.cuts).words(ALNUM)
    scores = word_scores(model, buf, starts, ends)
    good = np.concatenate([[0], np.cumsum(scores > 0)])
    rising = good[first[1:]] > good[first[:-1]]
    return np.diff(first), [maximal_segments(scores[first[d] : first[d + 1]]) if rising[d] else [] for d in range(chunk.n)]


def features(model: Model, words: int, found: list[tuple[int, int, float]]) -> tuple[float, float]:
    """The best score above its expected extreme, and the evidence of all segments together."""
    if not found:
        return -math.log(model.size * max(words, 1) + 1) / 4, 0.0
    expected = math.log(model.size * max(words, 1))
    best = model.rate * max(s for _, _, s in found) - expected
    return best, math.log1p(sum(max(0.0, model.rate * s - IDLE) for _, _, s in found))


def probability(model: Model, x: tuple[float, float]) -> float:
    a, b, c = model.curve
    z = a + b * min(x[0], 40.0) + c * x[1]
    return 1 / (1 + math.exp(-z)) if z > -700 else 0.0


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 5 == 0


def fit(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", rows: int = FIT_ROWS) -> Model:
    """Learn from labelled rows that are not held out.  Without labels of both kinds all scores are 0."""
    spark = docs.sparkSession
    wanted = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull() & ~held_out(F.col(id_col))).select(F.col(id_col).alias("__id"), F.col(label_col).cast("int").alias("label"))
    wanted = wanted.withColumn("__order", F.md5(F.col("__id").cast("string"))).orderBy("__order", "label").limit(rows)
    chosen = docs.select(id_col, text_col).join(F.broadcast(wanted), F.col(id_col) == F.col("__id")).select(F.xxhash64(text_col).alias("key"), F.col(text_col).alias("text"), "label")
    # copies would let the words of one text pass as evidence: one row of each text
    once = chosen.groupBy("key").agg(F.min("text").alias("text"), (2 * F.sum("label") > F.count(F.lit(1))).cast("int").alias("label"))
    sample = staged(once.withColumn("fold", F.abs(F.col("key") % 2).cast("int")), "toxicity-fit")
    counts = _counts(sample)
    both = Model(*_scores(counts, (0, 1)))
    if not len(both.tokens):
        return Model(both.tokens, both.scores, curve=(-20.0, 0.0, 0.0))
    points = []
    for fold in (0, 1):
        half = Model(*_scores(counts, (1 - fold,)))
        points += _points(spark, sample.where(F.col("fold") == fold), half)
    return _calibrated(both, points)


def _counts(sample: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Level, hash, parent hash and occurrences by (fold, label) of the tokens of the sample."""

    def tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            side = batch.column(1).to_numpy() * 2 + batch.column(2).to_numpy()
            for chunk in chunks(batch.column(0)):
                buf = FOLD[chunk.buf]
                starts, ends, first = Chunk(0, buf, chunk.cuts).words(ALNUM)
                doc = np.repeat(np.arange(chunk.n), np.diff(first))
                of = side[chunk.row : chunk.row + chunk.n]
                chain = [token_hashes(word_hashes(buf, starts, ends), 0)]
                for level, size in enumerate(PREFIXES, 1):
                    chain.append(token_hashes(word_hashes(buf, starts, np.minimum(starts + size, ends)), level))
                length = ends - starts
                parent = np.zeros(len(starts), np.uint64)
                for level in range(len(PREFIXES), -1, -1):
                    fits = length >= PREFIXES[level - 1] if level else np.ones(len(starts), bool)
                    if fits.any():
                        at = np.flatnonzero(fits)
                        order = np.lexsort((doc[at], chain[level][at]))
                        at = at[order]
                        token, d = chain[level][at], doc[at]
                        once = np.concatenate([[True], (token[1:] != token[:-1]) | (d[1:] != d[:-1])])  # a text counts a token once
                        at, token, d = at[once], token[once], d[once]
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), level, np.int32)), pa.array(token.view(np.int64)), pa.array(parent[at].view(np.int64)), pa.array(of[d].astype(np.int32)), pa.array(np.ones(len(at), np.int64))], names=["level", "token", "parent", "side", "n"])
                    parent = np.where(fits, chain[level], parent)

    seen = sample.select("text", "fold", "label").mapInArrow(tokens, "level int, token long, parent long, side int, n long")
    by = [F.sum(F.when(F.col("side") == k, F.col("n")).otherwise(0)).alias(f"n{k}") for k in range(4)]
    grouped = seen.groupBy("level", "token").agg(F.first("parent").alias("parent"), *by).where(f"n0 + n1 + n2 + n3 >= {LEAST}")
    told = grouped.select("level", "token", "parent", *[F.col(f"n{k}").cast("int").alias(f"n{k}") for k in range(4)]).toArrow()
    column = lambda name: told.column(name).to_numpy()
    return column("level").astype(np.int64), column("token").view(np.uint64), column("parent").view(np.uint64), np.stack([column(f"n{k}") for k in range(4)], axis=1).astype(np.float64)


def _scores(counts, folds: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
    level, token, parent, n = counts
    clean, toxic = sum(n[:, 2 * f] for f in folds), sum(n[:, 2 * f + 1] for f in folds)
    words = level == 0
    if not len(level) or not toxic[words].sum() or not clean[words].sum():
        return np.empty(0, np.uint64), np.empty(0)
    base = toxic[words].sum() / (toxic[words].sum() + clean[words].sum())
    order = np.argsort(token)
    ranked = token[order]
    share = np.full(len(level), base)
    spread = np.zeros(len(level))
    for at in range(len(PREFIXES), -1, -1):
        rows = np.flatnonzero(level == at)
        place = np.minimum(np.searchsorted(ranked, parent[rows]), len(ranked) - 1)
        above = np.where(ranked[place] == parent[rows], share[order[place]], base)
        share[rows] = (toxic[rows] + PRIOR * above) / (toxic[rows] + clean[rows] + PRIOR)
        spread[rows] = np.sqrt(1 / (toxic[rows] + 0.5) + 1 / (clean[rows] + 0.5))
    logit = np.log(share / (1 - share)) - math.log(base / (1 - base))
    sure = np.sign(logit) * np.maximum(0.0, np.abs(logit) - SURE * spread)
    return ranked, np.clip(sure[order], -1.0, 8.0)


def _points(spark: SparkSession, sample: DataFrame, model: Model) -> list[tuple[int, int, list[float]]]:
    """Label, words and segment scores of each row of one half of the sample, the best score first.

    Scores that add no evidence at the highest rate are left out, except the best one.
    """
    shared = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk in chunks(batch.column(0)):
                words, found = chunk_segments(shared.value, chunk)
                yield pa.RecordBatch.from_arrays([batch.column(1).slice(chunk.row, chunk.n), pa.array(words.astype(np.int32)), pa.array([telling(x) for x in found], pa.list_(pa.float64()))], names=["label", "words", "scores"])

    return [(r.label, r.words, list(r.scores)) for r in sample.select("text", "label").mapInArrow(run, "label int, words int, scores array<double>").collect()]


def telling(found: list[tuple[int, int, float]]) -> list[float]:
    scores = sorted((s for _, _, s in found), reverse=True)
    return scores[:1] + [s for s in scores[1:] if s * RATES[1] > IDLE]


def _calibrated(model: Model, points: list[tuple[int, int, list[float]]]) -> Model:
    """Fit the extreme-value law on clean rows, then the logistic curve on all."""
    clean = [(n, s[0]) for y, n, s in points if y == 0 and s and n]
    if len(clean) >= 20:
        n, s = np.array([x[0] for x in clean], float), np.array([x[1] for x in clean])
        best = (-math.inf, 1.0, 1.0)
        for rate in np.geomspace(*RATES, 90):
            # for a given rate the size that maximises the likelihood of a Gumbel law with location ln(size n)/rate
            size = len(n) / float(np.sum(n * np.exp(-rate * s)))
            y = rate * s - np.log(size * n)
            best = max(best, (float(np.sum(math.log(rate) - y - np.exp(-y))), float(rate), size))
        model.rate, model.size = best[1], best[2]
    x = np.array([(1.0, min(f[0], 40.0), f[1]) for f in (features(model, n, [(0, 0, v) for v in s]) for _, n, s in points)])
    y = np.array([p[0] for p in points], float)
    w = np.array([-3.0, 0.5, 0.5])
    ridge = np.array([1e-3, 1e-1, 1e-1])

    def loss(w: np.ndarray) -> float:
        z = x @ w
        return float(np.sum(np.logaddexp(0, z) - y * z) + 0.5 * np.sum(ridge * w * w))

    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p) + 1e-9)[:, None]) + np.diag(ridge), x.T @ (y - p) - ridge * w)
        size = 1.0
        while size > 1e-6 and loss(w + size * step) > loss(w):
            size /= 2
        w = w + size * step
        if np.abs(size * step).max() < 1e-8:
            break
    model.curve = tuple(float(v) for v in w)
    return model


def score_documents(docs: DataFrame, model: Model, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: ``id, score`` (0 to 1), ``words`` and the significant ``segments`` in text order.

    Null and empty texts have no words and take the score of a text without evidence.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for chunk in chunks(batch.column(1)):
                words, found = chunk_segments(m, chunk)
                score = [probability(m, features(m, int(n), x)) for n, x in zip(words, found, strict=True)]
                told = [[{"word": a, "words": b - a + 1, "score": s, "e_value": e} for a, b, s in x if (e := m.size * int(n) * math.exp(-m.rate * s)) <= E_VALUE] for n, x in zip(words, found, strict=True)]
                kind = pa.list_(pa.struct([("word", pa.int32()), ("words", pa.int32()), ("score", pa.float64()), ("e_value", pa.float64())]))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(chunk.row, chunk.n), pa.array(score, pa.float64()), pa.array(words.astype(np.int64)), pa.array(told, kind)], names=[batch.schema.names[0], "score", "words", "segments"])

    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), T.StructField("score", T.DoubleType()), T.StructField("words", T.LongType()), T.StructField("segments", T._parse_datatype_string(SEGMENTS))])
    return docs.select(id_col, text_col).mapInArrow(run, schema)


def reject_toxic(docs: DataFrame, model: Model, *, text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """The rows that score below ``threshold``, all columns as they were."""
    shared, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            keep: list[bool] = []
            for chunk in chunks(batch.column(at)):
                words, found = chunk_segments(m, chunk)
                keep += [probability(m, features(m, int(n), x)) < threshold for n, x in zip(words, found, strict=True)]
            yield batch.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = score_documents(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "words", "segments")
