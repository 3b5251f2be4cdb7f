"""Mixing sources to target weights by systematic sampling, in DataFrame functions only.

Targets: a share of all sizes is dealt to the sources by weight; a source stops at ``most`` times its
own size and the excess is dealt again by weight, until no source is above.  That fixed point is the
water level of a sorted prefix sum over the sources, one row per source.

Sampling: within a source every document expects the same number of copies (target / size of the
source).  The expected copies are prefix-summed along a fixed order, one offset per source is added,
and a document is emitted once for each integer that its stretch crosses.  The order runs through
size classes, so that the words taken follow the target closely.  A document's place in its source is
the count of all earlier buckets plus its place in its own bucket: no source, however large, meets in
one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from redgraph.session import cut

WEIGHTS = (5, 2, 1)
SHARE = 1.5
MOST = 2.0
SEED = 7
SPREAD, BUCKET_ROWS = 256, 1 << 18  # buckets of one source and size class at least; rows of the table for each bucket beyond


def source_key(source: Column) -> Column:
    """Sorts by code point with null last and is never null."""
    return F.when(source.isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), source))


def hash32(text: Column, seed: int) -> Column:
    """32 bits of a published digest, the same in any engine."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(text, F.lit("")))), 1, 8), 16, 10).cast("long")


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def size_class(size: Column) -> Column:
    """Four classes per doubling, from the leading three bits; grows with the size."""
    bits = F.length(F.bin(size))
    return (bits * 4 + F.call_function("shiftright", size, F.greatest(bits - 3, F.lit(0))).bitwiseAND(F.lit(3).cast("long"))).cast("int")


def source_targets(sizes: DataFrame, *, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """``key, source_size, target`` from one row ``(key, source_size)`` per source.

    The sources are ordered as a whole, so one task sees one short row per source: meant for up to some
    millions of sources.
    """
    by_key, by_level = Window.orderBy("key"), Window.orderBy("level", "key")
    turn = (F.row_number().over(by_key) - 1) % len(weights)
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), turn + 1)
    s = sizes.withColumn("w", w).withColumn("most", F.lit(float(most)) * F.col("source_size")).withColumn("level", F.col("most") / F.col("w"))
    before, everything = by_level.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    s = s.withColumn("rest_words", F.lit(float(share)) * F.sum("source_size").over(everything) - F.coalesce(F.sum("most").over(before), F.lit(0.0)))
    s = s.withColumn("rest_weight", F.sum("w").over(by_level.rowsBetween(0, Window.unboundedFollowing)))
    s = s.withColumn("lambda", F.col("rest_words") / F.col("rest_weight")).withColumn("place", F.row_number().over(by_level))
    s = s.withColumn("lambda", F.min(F.when(F.col("lambda") <= F.col("level"), F.struct("place", "lambda"))).over(everything)["lambda"])
    return s.select("key", "source_size", F.least("most", F.coalesce(F.col("lambda") * F.col("w"), F.col("most"))).alias("target"))


def buckets(rows: int) -> int:
    """Buckets of one source and size class: a power of two that follows the rows of the table."""
    return max(SPREAD, 1 << max(0, -(-rows // BUCKET_ROWS) - 1).bit_length())


def with_copies(sized: DataFrame, counted: DataFrame, *, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: float = MOST, seed: int = SEED) -> DataFrame:
    """Add ``source_size, target, copies`` to rows with the columns of ``PLAN``; ``counted`` are the same rows, narrow."""
    spread = buckets(counted.count())
    groups = counted.groupBy("__key", "__class", (F.col("__hash") % spread).alias("__bucket")).agg(F.count(F.lit(1)).alias("n"), F.sum("__size").alias("size"))
    targets = source_targets(groups.groupBy(F.col("__key").alias("key")).agg(F.sum("size").alias("source_size")), weights=weights, share=share, most=most)
    before = Window.partitionBy("__key").orderBy("__class", "__bucket").rowsBetween(Window.unboundedPreceding, -1)
    groups = groups.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))).join(targets.withColumnRenamed("key", "__key"), "__key").drop("n", "size")
    rows = sized.withColumn("__bucket", F.col("__hash") % spread).join(groups, ["__key", "__class", "__bucket"])
    own = Window.partitionBy("__key", "__class", "__bucket").orderBy("__size", "__hash", "__id", "__tie")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    place = F.col("before") + F.row_number().over(own)
    start = hash32(F.col("__key"), seed) / F.lit(4294967296.0)
    reach = lambda k: F.floor(rate * k + start)
    return rows.withColumn("__place", place).withColumn("copies", (reach(F.col("__place")) - reach(F.col("__place") - 1)).cast("long"))


def keyed(docs: DataFrame, id_col: str, text_col: str, source_col: str, seed: int) -> DataFrame:
    out = docs.withColumn("__tie", F.xxhash64(text_col)).withColumn("__key", source_key(F.col(source_col))).withColumn("__size", word_count(F.col(text_col))).withColumn("__id", F.col(id_col))
    return out.withColumn("__class", size_class(F.col("__size"))).withColumn("__hash", hash32(F.col(id_col).cast("string"), seed))


PLAN = ["__key", "__size", "__class", "__hash", "__id", "__tie"]


def mix_plan(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = SEED, **rule) -> DataFrame:
    """Per row: ``id, size, source_size, target, taken, copies``.

    A null source is a source of its own, last in order; null or empty texts have size 0 and follow
    the rate of their source; a source without words takes nothing.  Rows with equal ids count as
    documents of their own, ordered by a hash of their text, so that reruns agree.  Other columns are not
    read.
    """
    sized = cut(keyed(docs.select(id_col, text_col, source_col), id_col, text_col, source_col, seed).select(*PLAN))
    out = with_copies(sized, sized, seed=seed, **rule)
    return out.select(F.col("__id").alias(id_col), F.col("__size").alias("size"), "source_size", "target", (F.col("copies") * F.col("__size")).alias("taken"), "copies")


def mix(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = SEED, **rule) -> DataFrame:
    """The mixed corpus: each row as often as it was drawn, all columns as they were; names that begin with ``__`` are ours."""
    counted = keyed(docs.select(id_col, text_col, source_col), id_col, text_col, source_col, seed).select(*PLAN)
    drawn = with_copies(keyed(docs, id_col, text_col, source_col, seed), counted, seed=seed, **rule).where("copies > 0")
    return drawn.withColumn("__copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select(*docs.columns)


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_plan(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def draw_sql(table: str) -> str:
    """Common table expressions that end in ``drawn``: every row of ``table`` with its copies."""
    return rf"""
sized AS (SELECT *, CASE WHEN source IS NULL THEN '1' ELSE '0' || source END AS k, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS z,
          ('0x' || substr(md5('{SEED}:' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 8))::BIGINT AS h FROM {table}),
classed AS (SELECT *, length(bin(z)) * 4 + ((z >> greatest(length(bin(z)) - 3, 0)) & 3) AS c FROM sized),
src AS (SELECT k, sum(z)::BIGINT AS s, CAST([5.0, 2.0, 1.0][((row_number() OVER (ORDER BY k)) - 1) % 3 + 1] AS DOUBLE) AS w FROM sized GROUP BY k),
lev AS (SELECT *, 2.0::DOUBLE * s AS most, 2.0::DOUBLE * s / w AS level FROM src),
water AS (SELECT *, row_number() OVER l AS place,
          (1.5::DOUBLE * sum(s) OVER () - coalesce(sum(most) OVER (l ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(w) OVER (l ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS la
          FROM lev WINDOW l AS (ORDER BY level, k)),
tgt AS (SELECT k, s, least(most, coalesce((SELECT arg_min(la, place) FROM water WHERE la <= level) * w, most)) AS t FROM water),
placed AS (SELECT classed.*, s, t, row_number() OVER (PARTITION BY k ORDER BY c, h % (SELECT greatest({SPREAD}, CAST(2 ** ceil(log2(greatest(1, ceil(count(*) / {BUCKET_ROWS}.0)))) AS BIGINT)) FROM sized), z, h, doc_id) AS place FROM classed JOIN tgt USING (k)),
rated AS (SELECT *, CASE WHEN s > 0 THEN t / s ELSE 0 END AS rate, ('0x' || substr(md5('{SEED}:' || k), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS u FROM placed),
drawn AS (SELECT *, (floor(rate * place + u) - floor(rate * (place - 1) + u))::BIGINT AS copies FROM rated)"""


SQL = f"WITH {draw_sql('documents')} SELECT doc_id, z AS size, s AS source_size, t AS target, copies * z AS taken, copies FROM drawn"
