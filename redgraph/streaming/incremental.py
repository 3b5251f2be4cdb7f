"""Streams of events: windowed activity, last-seen edges and incremental minimum labels.

A minimum that commutes may take late rows in any order, so labels are kept up to date by edge
insertions alone; sums are not, and deletions need a new run.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from redgraph.operators.components import connected_components
from redgraph.session import shared_dir, staged

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, pattern: str = "events.parquet", files_per_batch: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(EVENTS).option("pathGlobFilter", pattern)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.parquet(folder)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and return what it wrote."""
    spark = stream.sparkSession
    place = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("__batch", F.lit(number)).write.mode("overwrite").parquet(f"{place}/out/b={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{place}/log").trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.option("basePath", f"{place}/out").parquet(f"{place}/out").drop("b")
    if mode == "complete":
        last = out.agg(F.max("__batch")).first()[0]
        out = out.where(F.col("__batch") == last)
    return out.drop("__batch")


def activity(events: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Events per user and window (tumbling, or sliding with ``slide``); later rows than ``late`` are left out."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(w, "user_id").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("window.start").alias("start"), "user_id", "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Sessions of a user: runs of events with no longer gap."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


def distinct_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event id once within the watermark; the state of older ids is dropped."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def last_seen_edges(events: DataFrame) -> DataFrame:
    """An edge from each event to the next one of its user: the last event of a user is the state."""
    import pandas as pd

    def link(key, batches, state):
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        out = []
        for event in rows["event_id"].tolist():
            if last is not None:
                out.append((last, event))
            last = event
        state.update((last,))
        yield pd.DataFrame(out, columns=["src", "dst"])

    return events.groupBy("user_id").applyInPandasWithState(link, "src long, dst long", "last long", "append", "NoTimeout")


def incremental_labels(edge_stream: DataFrame) -> DataFrame:
    """Component labels kept by batches of edge insertions: ``id, component``.

    A batch joins its edges with the labels of their ends only, contracts that small graph, and moves the
    labels of the components that were joined.
    """
    spark = edge_stream.sparkSession
    place = f"{shared_dir(spark)}/labels-{uuid.uuid4().hex}"
    kept: list[DataFrame] = []

    def absorb(batch: DataFrame, number: int) -> None:
        edges = staged(batch.select("src", "dst").where("src IS NOT NULL AND dst IS NOT NULL"), "stream-edges")
        ends = edges.select(F.col("src").alias("id")).unionByName(edges.select(F.col("dst").alias("id"))).distinct()
        old = kept[-1] if kept else ends.limit(0).withColumn("component", F.col("id"))
        known = ends.join(old, "id", "left").withColumn("component", F.coalesce("component", "id"))
        e = edges.join(known.select(F.col("id").alias("src"), F.col("component").alias("a")), "src").join(known.select(F.col("id").alias("dst"), F.col("component").alias("b")), "dst")
        moved = connected_components(e, "a", "b").select(F.col("id").alias("component"), F.col("component").alias("to"))
        every = old.unionByName(known.join(old.select("id"), "id", "left_anti"))
        new = every.join(moved, "component", "left").select("id", F.coalesce("to", "component").alias("component"))
        kept.append(staged(new, "stream-labels"))

    query = edge_stream.writeStream.foreachBatch(absorb).option("checkpointLocation", f"{place}/log").trigger(availableNow=True).start()
    query.awaitTermination()
    return kept[-1] if kept else spark.createDataFrame([], "id long, component long")
