"""Connected components by contraction: alternate two star rewrites until they agree.

Published method for bulk-synchronous engines (large-star / small-star): every node hooks its larger
neighbours to its smallest one, then its smaller ones.  Logarithmic rounds in practice, each with
two keyed shuffles; nothing but counts reaches the driver, and no node's neighbours are collected.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from redgraph.session import cut, scoped


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """``(id, component)`` for every node with an edge to another one; component = smallest id reachable.

    Nulls and self loops are dropped.  Isolated nodes do not appear: the caller knows them.
    """
    spark = edges.sparkSession
    # a round leaves no broadcast behind: they would gather in the executors, round by round
    with scoped(spark, {"spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}):
        e = edges.select(F.col(src).alias("u"), F.col(dst).alias("v")).where("u <> v")
        e = cut(e.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
        before = _mark(e)
        for _ in range(max_rounds):
            if before[0] == 0:
                break
            e = cut(_small_star(_large_star(e)))
            now = _mark(e)
            if now == before:
                break
            before = now
        else:
            raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = e.select("v").distinct().select(F.col("v").alias("id"), F.col("v").alias("component"))
    return e.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(roots)


def _mark(e: DataFrame) -> tuple[int, int]:
    row = e.agg(F.count("*"), F.coalesce(F.sum(F.shiftright(F.xxhash64("u", "v"), 16)), F.lit(0))).first()
    return row[0], row[1]


def _large_star(e: DataFrame) -> DataFrame:
    """Larger neighbours hook to the least one; a link may come twice, which the next fold does not mind."""
    both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")


def _small_star(e: DataFrame) -> DataFrame:
    least = e.groupBy("u").agg(F.min("v").alias("m"))
    hooked = e.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return least.select("u", F.col("m").alias("v")).unionByName(hooked).where("u <> v").distinct()
