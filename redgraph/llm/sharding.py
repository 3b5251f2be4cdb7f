"""Sharding by proportional stratified interleaving.

Rows of each source are put in a seeded random order and get the fractional rank (place - 1/2) /
rows of the source.  Sorted by that rank, every stretch of the whole holds the sources in the
proportion of the mixture, so cutting the order into equal parts gives shards that all match it.

Neither a source nor the whole order meets in one task: the place within a source is the count of
earlier hash buckets plus the place in the own bucket, and the place in the whole is found the same
way over equal stretches of the fractional rank.  How many rows each stretch has follows from the
sizes of the sources alone.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from redgraph.llm.mixing import hash32, source_key

SHARDS = 16
SEED = 11
BUCKET_ROWS = 1 << 16  # rows of one bucket or stretch, as their numbers follow the rows of the table


def shard_rows(docs: DataFrame, *, id_col: str = "doc_id", source_col: str = "source", shards: int = SHARDS, seed: int = SEED) -> DataFrame:
    """All columns of ``docs`` plus ``shard`` and ``slot`` (gapless from 0); shard sizes differ by one row at most.

    A null source is a source of its own; null ids hash as the empty string; rows of one id are ordered by
    a digest of all their columns (maps left out), so that a repeated task deals them alike, and rows
    equal in all of them take neighbouring places in any order; an empty table gives no rows.  Columns
    named ``shard`` or ``slot`` are replaced.
    """
    docs = docs.drop("shard", "slot")
    rows = docs.count()
    bits = max(10, int(-(-rows // BUCKET_ROWS) - 1).bit_length())  # of the shuffle hash, that name a bucket of a source
    parts = max(4096, 1 << bits)
    tie = F.xxhash64(*[F.col(c) for c, t in docs.dtypes if "map<" not in t and t != "variant"])
    key = lambda df: df.withColumn("__key", source_key(F.col(source_col))).withColumn("__hash", hash32(F.col(id_col).cast("string"), seed)).withColumn("__bucket", F.shiftright("__hash", 32 - bits))
    groups = key(docs.select(id_col, source_col)).groupBy("__key", "__bucket").agg(F.count(F.lit(1)).alias("n"))
    source = Window.partitionBy("__key")
    groups = groups.withColumn("__before", F.coalesce(F.sum("n").over(source.orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn("__of", F.sum("n").over(source)).drop("n")
    own = Window.partitionBy("__key", "__bucket").orderBy("__hash", id_col, "__tie")
    ranked = key(docs.withColumn("__tie", tie)).join(groups, ["__key", "__bucket"]).withColumn("__place", F.col("__before") + F.row_number().over(own))
    ranked = ranked.withColumn("__part", F.expr(f"((2 * __place - 1) * {parts}) div (2 * __of)")).withColumn("__rank", (F.col("__place") - 0.5) / F.col("__of"))
    stretch = Window.partitionBy("__part").orderBy("__rank", "__key", "__place")
    ranked = ranked.join(stretches(groups.select("__key", "__of").distinct(), parts), "__part").withColumn("__at", F.col("__ahead") + F.row_number().over(stretch) - 1)
    return ranked.select(*docs.columns, F.expr(f"cast((__at * {shards}) div __all as int)").alias("shard"), F.expr(f"__at - ((((__at * {shards}) div __all) * __all + {shards - 1}) div {shards})").alias("slot"))


def stretches(sources: DataFrame, g: int) -> DataFrame:
    """``__part, __ahead, __all``: rows before each of ``g`` stretches, from one row ``(__key, __of)`` per source.

    A source with at most as many rows as there are stretches names the stretch of each row, a larger
    one the rows of each stretch: never more rows than documents, nor than sources times stretches.
    """
    first = lambda p: f"((2 * __of * {p} + {g}) + {2 * g - 1}) div {2 * g}"
    spread = sources.select("__of", F.explode(F.sequence(F.lit(0).cast("long"), F.least(F.col("__of"), F.lit(g)) - 1)).alias("j"))
    part = F.when(F.col("__of") <= g, F.expr(f"((2 * j + 1) * {g}) div (2 * __of)")).otherwise(F.col("j"))
    rows = F.when(F.col("__of") <= g, F.lit(1)).otherwise(F.expr(f"({first('(j + 1)')}) - ({first('j')})"))
    parts = spread.select(part.alias("__part"), rows.alias("n")).groupBy("__part").agg(F.sum("n").alias("n"))
    order = Window.orderBy("__part")  # one row per stretch
    return parts.select("__part", F.coalesce(F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__ahead"), F.sum("n").over(Window.partitionBy()).alias("__all"))


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", "source", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    return shard_rows(rows).select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source")


def order_sql(table: str, extra: str = "") -> str:
    """Common table expressions that end in ``sharded``: every row of ``table`` with shard and slot."""
    return f"""
s_hash AS (SELECT *, CASE WHEN source IS NULL THEN '1' ELSE '0' || source END AS sk, ('0x' || substr(md5('{SEED}:' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 8))::BIGINT AS sh FROM {table}),
s_place AS (SELECT *, row_number() OVER (PARTITION BY sk ORDER BY sh, doc_id) AS sp, count(*) OVER (PARTITION BY sk) AS sn FROM s_hash),
s_at AS (SELECT *, row_number() OVER (ORDER BY (sp - 0.5::DOUBLE) / sn, sk, sp) - 1 AS pos, count(*) OVER () AS total FROM s_place),
sharded AS (SELECT *, CAST(pos * {SHARDS} // total AS INTEGER) AS shard, CAST(pos - (((pos * {SHARDS}) // total) * total + {SHARDS - 1}) // {SHARDS} AS BIGINT) AS slot FROM s_at)"""


#: One step of the reflected checksum polynomial, 32 bits.
_BIT = "CASE WHEN a & 1 = 1 THEN xor(a >> 1, 3988292384) ELSE a >> 1 END"

SQL = f"""WITH {order_sql('documents')},
bits AS (SELECT list_transform(range(256), lambda n: list_reduce([n, 0, 0, 0, 0, 0, 0, 0, 0], lambda a, b: {_BIT})) AS steps),
nib AS (SELECT doc_id, source, shard, slot, list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda b: ('0x' || b)::BIGINT) AS b FROM sharded),
crc AS (SELECT nib.*, list_reduce(list_prepend(4294967295::BIGINT, b), lambda a, b: xor(a >> 8, steps[(xor(a, b) & 255) + 1])) AS c FROM nib, bits)
SELECT doc_id, CAST(len(b) + 1 AS BIGINT) AS size, CAST(xor(c, 4294967295::BIGINT) AS BIGINT) AS text_crc32, 'rows' AS law, shard, slot, CAST(NULL AS INTEGER) AS grown_shard, source FROM crc"""
