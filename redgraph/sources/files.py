"""Readers of edge lists and writers of results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from redgraph.operators.graph import PropertyGraph
from redgraph.operators.partition import Placed


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", weighted: bool = False, comment: str = "#") -> PropertyGraph:
    """Text edge lists ``src sep dst [sep weight]``; comment lines are dropped, malformed lines fail."""
    schema = "src long, dst long" + (", w long" if weighted else "")
    e = spark.read.schema(schema).option("sep", sep).option("comment", comment).option("mode", "FAILFAST").csv(path)
    return PropertyGraph(e if weighted else e.withColumn("w", F.lit(1).cast("long")))


def read_json_edges(spark: SparkSession, path: str) -> PropertyGraph:
    """One JSON object per line with ``src``, ``dst`` and optionally ``w``."""
    e = spark.read.schema("src long, dst long, w long").option("mode", "FAILFAST").json(path)
    return PropertyGraph(e.withColumn("w", F.coalesce("w", F.lit(1).cast("long"))))


def write_result(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    """Write a result as ``parquet``, ``orc``, ``json`` or ``csv`` (with a header)."""
    if fmt not in ("parquet", "orc", "json", "csv"):
        raise ValueError(f"unknown format {fmt}")
    writer = df.write.mode(mode).format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)


def write_partitioned_edges(p: Placed, target: str, *, table: bool = False) -> None:
    """Keep a placed graph: a folder per owner, or a table bucketed by owner whose joins need no exchange later."""
    edges = p.edges.sortWithinPartitions("part", "src", "dst")
    if table:
        edges.write.bucketBy(p.parts, "part").sortBy("part", "src").saveAsTable(target)
    else:
        edges.write.partitionBy("part").parquet(target)


def read_partitioned_edges(spark: SparkSession, path: str, parts: list[int] | None = None) -> DataFrame:
    """Edges of some owners only: folders of other owners are not listed."""
    e = spark.read.parquet(path)
    return e if parts is None else e.where(F.col("part").isin(parts))
