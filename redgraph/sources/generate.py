"""Generated graphs: recursive-matrix, uniform and lattice.

All choices come from hashes of the edge number, so a graph is the same however it is partitioned.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from redgraph.operators.graph import PropertyGraph


def rmat(spark: SparkSession, scale: int, edge_factor: int, a: float = 0.5, b: float = 0.3, c: float = 0.09, seed: int = 1, numbers: DataFrame | None = None) -> PropertyGraph:
    """``2**scale`` vertices and ``edge_factor`` edges each; every bit of an edge picks a quadrant.

    The quadrants' shares are a, b, c and the rest.  Parallel edges and loops may occur.  With ``numbers``
    (``id``) there is one edge for each of its rows instead.
    """
    e = spark.range(edge_factor << scale) if numbers is None else numbers.select("id")
    bits = F.sequence(F.lit(0), F.lit(scale - 1))
    draw = lambda k: F.pmod(F.xxhash64("id", k, F.lit(seed)), F.lit(1_000_000)) / 1e6
    quadrants = F.transform(bits, lambda k: F.when(draw(k) < a, 0).when(draw(k) < a + b, 1).when(draw(k) < a + b + c, 2).otherwise(3))
    e = e.withColumn("q", quadrants)
    number = lambda part: F.aggregate("q", F.lit(0).cast("long"), lambda s, q: s * 2 + part(q))
    return PropertyGraph(e.select(number(lambda q: F.floor(q / 2)).alias("src"), number(lambda q: q % 2).alias("dst"), F.lit(1).cast("long").alias("w")), meta={"name": "rmat"})


def scale_of(edges: int, edge_factor: int) -> int:
    """The scale at which ``edges`` edges are ``edge_factor`` for each vertex, or fewer."""
    return max(1, (max(-(-edges // edge_factor), 1) - 1).bit_length())


def uniform(spark: SparkSession, n: int, m: int, seed: int = 1, numbers: DataFrame | None = None) -> PropertyGraph:
    """``m`` edges, or one for each row of ``numbers`` (``id``), between uniformly drawn ends among ``n`` vertices."""
    rows = spark.range(m) if numbers is None else numbers.select("id")
    pick = lambda k: F.pmod(F.xxhash64("id", F.lit(k), F.lit(seed)), F.lit(n))
    return PropertyGraph(rows.select(pick(0).alias("src"), pick(1).alias("dst"), F.lit(1).cast("long").alias("w")), meta={"name": "uniform"})


def lattice(spark: SparkSession, rows: int, columns: int) -> PropertyGraph:
    """A grid of ``rows`` by ``columns`` with edges both ways between neighbours."""
    v = spark.range(rows * columns)
    ends = F.array(F.when((F.col("id") + 1) % columns != 0, F.col("id") + 1), F.when(F.col("id") + columns < rows * columns, F.col("id") + columns))
    one = v.select("id", F.explode(ends).alias("to")).where("to IS NOT NULL")
    both = one.select(F.col("id").alias("src"), F.col("to").alias("dst")).unionByName(one.select(F.col("to").alias("src"), F.col("id").alias("dst")))
    return PropertyGraph(both.withColumn("w", F.lit(1).cast("long")), directed=False, meta={"name": "lattice"})
