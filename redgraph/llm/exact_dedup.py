"""Exact de-duplication as a stateful stream, in DataFrame functions only.

A file stream feeds rows to a keyed streaming aggregation whose state lives in the disk-backed state
store and never expires.  For each content digest it retains how many rows were seen, the identifier
of the row that stays and a locator of its content (file and row in the file).  Rows are combined
per task before they are dealt, so a text that a third of all rows share is one state row per task.

Digests decide candidates only: every hit is compared with the content that the locator points to,
byte by byte, and rows of equal digest and different bytes form groups of their own.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from redgraph.session import scoped, shared_dir, staged

STORE = {"spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider", "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true"}
#: Input bytes for each part of the state (some tenths of them become state), and the fewest parts.  A
#: store reserves megabytes on disk however little it holds, so parts follow the data, not the shuffle.
STATE_BYTES, STATE_PARTS = 16 << 30, 24
#: Lets Spark thin out rows whose digest was seen once before their text is shuffled for the comparison.
THIN = {
    "spark.sql.optimizer.runtime.bloomFilter.applicationSideScanSizeThreshold": "0", "spark.sql.optimizer.runtime.bloomFilter.creationSideThreshold": "4g", "spark.sql.optimizer.runtime.bloomFilter.enabled": "true",
    "spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true",
}


def sha(text: Column) -> Column:
    return F.sha2(text, 256)


def _rows(source: DataFrame, id_col: str, text_col: str, digest: Callable[[Column], Column]) -> DataFrame:
    text = F.coalesce(F.col(text_col), F.lit("")).cast("binary")
    at = F.struct(F.col(id_col).alias("id"), F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("row"))
    return source.select(digest(text).alias("digest"), at.alias("at"), text.alias("content"))


def seen_digests(spark: SparkSession, path: str, *, id_col: str = "doc_id", text_col: str = "text", digest: Callable[[Column], Column] = sha, checkpoint: str | None = None, files_per_batch: int | None = None) -> DataFrame:
    """Run the stream over all files at ``path`` and return its state: ``digest, group_size, keep``.

    With a ``checkpoint`` of an earlier call only files that have come since are read: state goes on.
    """
    place = checkpoint or f"{shared_dir(spark)}/dedup-{uuid.uuid4().hex}"
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    # the last character as a class of one makes the path a pattern: it may then name a file or a folder
    rows = _rows(reader.parquet(f"{path[:-1]}[{path[-1]}]"), id_col, text_col, digest)
    state = rows.groupBy("digest").agg(F.count(F.lit(1)).alias("group_size"), F.max("at").alias("keep"))

    def emit(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{place}/state/batch={number}")

    parts = max(STATE_PARTS, _size(spark, path) // STATE_BYTES)
    with scoped(spark, STORE | {"spark.sql.streaming.internal.stateStore.partitions": str(parts)}):
        query = state.writeStream.outputMode("update").foreachBatch(emit).option("checkpointLocation", f"{place}/log").trigger(availableNow=True).start()
        query.awaitTermination()
    told = spark.read.schema(state.schema.add("batch", "long")).option("basePath", f"{place}/state").parquet(f"{place}/state") if _exists(spark, f"{place}/state") else spark.createDataFrame([], state.schema.add("batch", "long"))
    return told.groupBy("digest").agg(F.max("group_size").alias("group_size"), F.max("keep").alias("keep"))


def _size(spark: SparkSession, path: str) -> int:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(where).getLength()


def _exists(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where)


def exact_groups(spark: SparkSession, path: str, *, id_col: str = "doc_id", text_col: str = "text", digest: Callable[[Column], Column] = sha, **stream) -> DataFrame:
    """Per row of the Parquet files at ``path``: ``id, keep_id, group_size, kept, digest``.

    Null texts count as empty.  The row with the largest id stays, a null id before any other; of rows
    with equal ids the one that stands last in the files stays, so exactly one row of a group is kept.
    An empty table gives no rows.  Other columns are not read.
    """
    seen = staged(seen_digests(spark, path, id_col=id_col, text_col=text_col, digest=digest, **stream), "dedup-state")
    source = spark.read.parquet(path)
    rows = _rows(source, id_col, text_col, digest)
    out = rows.select("digest", "at").join(seen, "digest")
    odd = _unequal(rows, seen.where("group_size > 1"))
    if not odd.isEmpty():
        own = odd.groupBy("digest", "content").agg(F.count(F.lit(1)).alias("size2"), F.max("at").alias("keep2"))
        moved = odd.join(own, ["digest", "content"]).select("at", "size2", "keep2")
        lost = odd.groupBy("digest").agg(F.count(F.lit(1)).alias("lost"))
        out = out.join(moved, "at", "left").join(lost, "digest", "left")
        out = out.select("digest", "at", F.coalesce("size2", F.col("group_size") - F.coalesce("lost", F.lit(0))).alias("group_size"), F.coalesce("keep2", "keep").alias("keep"))
    return out.select(F.col("at.id").alias(id_col), F.col("keep.id").alias("keep_id"), "group_size", F.expr("at.file = keep.file AND at.row = keep.row").alias("kept"), "digest")


def _unequal(rows: DataFrame, repeated: DataFrame) -> DataFrame:
    """Hits whose bytes differ from the content at the locator of their digest; normally no rows.

    The contents at the locators are fetched first, one row per repeated digest; the hits then meet them
    in a join over one exchange, which Spark splits where many rows share a digest.
    """
    with scoped(rows.sparkSession, THIN):
        known = repeated.select(F.col("digest").alias("d2"), "keep", F.col("group_size").alias("size2"))
        first = staged(rows.join(known, (F.col("digest") == F.col("d2")) & (F.col("at") == F.col("keep"))).select("d2", "size2", F.col("content").alias("c2")), "dedup-first")
        return staged(rows.join(first.where("size2 > 1"), (F.col("digest") == F.col("d2")) & (F.col("content") != F.col("c2"))).select("digest", "at", "content"), "dedup-odd")


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = exact_groups(spark, f"{sf_dir}/documents.parquet")
    return found.withColumnRenamed("digest", "text_sha256")


SQL = """
SELECT doc_id, max(doc_id) OVER t AS keep_id, count(*) OVER t AS group_size, doc_id = max(doc_id) OVER t AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW t AS (PARTITION BY coalesce(text, ''))
"""
