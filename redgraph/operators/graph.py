"""Property graphs as DataFrames, and the operators that prepare them.

``edges`` has ``src, dst`` (long) and any number of properties; ``vertices`` has ``id`` and
properties.  Vertices may be left out: then they are the ends of the edges.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from redgraph.operators.components import connected_components


@dataclass(frozen=True)
class PropertyGraph:
    edges: DataFrame
    vertices: DataFrame | None = None
    directed: bool = True
    meta: dict = field(default_factory=dict)

    def ids(self) -> DataFrame:
        """All vertices, one row ``id`` each."""
        ends = self.edges.select(F.col("src").alias("id")).unionByName(self.edges.select(F.col("dst").alias("id")))
        if self.vertices is not None:
            ends = ends.unionByName(self.vertices.select("id"))
        return ends.distinct()


def from_edges(edges: DataFrame, src: str = "src", dst: str = "dst", **props: str) -> PropertyGraph:
    """A graph from any table: two id columns and, by keyword, property columns."""
    return PropertyGraph(edges.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"), *[F.col(c).alias(p) for p, c in props.items()]))


def symmetrize(g: PropertyGraph) -> PropertyGraph:
    """Every edge both ways; properties are copied."""
    rest = [c for c in g.edges.columns if c not in ("src", "dst")]
    back = g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *rest)
    return replace(g, edges=g.edges.unionByName(back), directed=False)


def simplify(g: PropertyGraph, how: str = "min") -> PropertyGraph:
    """One edge per ordered pair; numeric properties are folded with ``min``, ``max`` or ``sum``."""
    fold = {"min": F.min, "max": F.max, "sum": F.sum}[how]
    rest = [c for c in g.edges.columns if c not in ("src", "dst")]
    pairs = g.edges.groupBy("src", "dst").agg(*[fold(c).alias(c) for c in rest]) if rest else g.edges.distinct()
    return replace(g, edges=pairs)


def drop_loops(g: PropertyGraph) -> PropertyGraph:
    return replace(g, edges=g.edges.where("src <> dst"))


def reverse(g: PropertyGraph) -> PropertyGraph:
    rest = [c for c in g.edges.columns if c not in ("src", "dst")]
    return replace(g, edges=g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *rest))


def degrees(g: PropertyGraph) -> DataFrame:
    """``id, out_degree, in_degree`` of every vertex, zeros included: one shuffle of partial counts."""
    ends = g.edges.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("dst").alias("id"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("e")).select("e.*")
    if g.vertices is not None:
        ends = ends.unionByName(g.vertices.select("id", F.lit(0).alias("o"), F.lit(0).alias("i")))
    return ends.groupBy("id").agg(F.sum("o").cast("long").alias("out_degree"), F.sum("i").cast("long").alias("in_degree"))


def dangling(g: PropertyGraph) -> DataFrame:
    """Vertices without an out-edge."""
    return g.ids().join(g.edges.select(F.col("src").alias("id")), "id", "left_anti")


def hubs(g: PropertyGraph, k: int) -> DataFrame:
    """The ``k`` vertices of largest out-degree; ties go to the smaller id."""
    return degrees(g).orderBy(F.desc("out_degree"), "id").limit(k)


def encode_ids(edges: DataFrame, src: str, dst: str) -> tuple[DataFrame, DataFrame]:
    """Long ids for string ends: ``(edges with src and dst, dictionary name, id)``, dense in name order.

    Names are ranked by leading-digest buckets, so no task sorts all of them.
    """
    names = edges.select(F.col(src).alias("name")).unionByName(edges.select(F.col(dst).alias("name"))).where("name IS NOT NULL").distinct()
    bucketed = names.withColumn("b", F.substring(F.md5("name"), 1, 2))
    sizes = bucketed.groupBy("b").count()
    ahead = sizes.withColumn("ahead", F.coalesce(F.sum("count").over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("count")
    ids = bucketed.join(ahead, "b").select("name", (F.col("ahead") + F.row_number().over(Window.partitionBy("b").orderBy("name")) - 1).alias("id"))
    rest = [c for c in edges.columns if c not in (src, dst)]
    out = edges.join(ids.select(F.col("name").alias("__s"), F.col("id").alias("src")), F.col(src) == F.col("__s")).join(ids.select(F.col("name").alias("__d"), F.col("id").alias("dst")), F.col(dst) == F.col("__d"))
    return out.select("src", "dst", *rest), ids


def subgraph(g: PropertyGraph, where: Column) -> PropertyGraph:
    """Only the edges that satisfy a condition."""
    return replace(g, edges=g.edges.where(where))


def induced(g: PropertyGraph, keep: DataFrame) -> PropertyGraph:
    """The edges between the vertices of ``keep`` (column ``id``)."""
    e = g.edges.join(keep.select(F.col("id").alias("src")), "src", "left_semi").join(keep.select(F.col("id").alias("dst")), "dst", "left_semi")
    return replace(g, edges=e.select(*g.edges.columns), vertices=keep)


def adjacency(g: PropertyGraph) -> DataFrame:
    """``id, neighbours array<struct<dst, ...>>``; a hub's list is one row, so this is for bounded degrees."""
    rest = [c for c in g.edges.columns if c != "src"]
    return g.edges.groupBy(F.col("src").alias("id")).agg(F.array_sort(F.collect_list(F.struct(*rest))).alias("neighbours"))


def validate(g: PropertyGraph, weight: str | None = None) -> DataFrame:
    """Counts of what the algorithms refuse: null ends, null weights, negative weights; also loops and parallel edges."""
    e = g.edges
    w = F.col(weight) if weight else F.lit(0)
    pairs = e.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"), F.sum((w.isNull()).cast("long")).alias("nw"), F.sum(F.coalesce((w < 0).cast("long"), F.lit(0))).alias("neg"))
    return pairs.agg(
        F.coalesce(F.sum("n"), F.lit(0)).alias("edges"), F.coalesce(F.sum(F.when(F.col("src").isNull() | F.col("dst").isNull(), F.col("n"))), F.lit(0)).alias("null_ends"), F.coalesce(F.sum("nw"), F.lit(0)).alias("null_weights"),
        F.coalesce(F.sum("neg"), F.lit(0)).alias("negative_weights"), F.coalesce(F.sum(F.when(F.col("src") == F.col("dst"), F.col("n"))), F.lit(0)).alias("loops"), F.coalesce(F.sum(F.col("n") - 1), F.lit(0)).alias("parallel"),
    )


def require_valid(g: PropertyGraph, weight: str | None = None) -> None:
    row = validate(g, weight).first()
    for what in ("null_ends", "null_weights", "negative_weights"):
        if row[what]:
            raise ValueError(f"{row[what]} edges with {what.replace('_', ' ')}")


def connect(g: PropertyGraph, weight: int = 1) -> PropertyGraph:
    """Link the components of a graph to that of the smallest id, through their smallest ids."""
    roots = connected_components(g.edges).select("component").distinct()
    least = roots.agg(F.min("component").alias("src"))
    extra = roots.join(least, F.col("component") != F.col("src")).select("src", F.col("component").alias("dst"))
    both = extra.unionByName(extra.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    rest = [c for c in g.edges.columns if c not in ("src", "dst")]
    return replace(g, edges=g.edges.unionByName(both.select("src", "dst", *[F.lit(weight).cast(g.edges.schema[c].dataType).alias(c) for c in rest])))


def random_weights(g: PropertyGraph, low: int, high: int, seed: int = 0, name: str = "w") -> PropertyGraph:
    """Integer weights from a hash of the ends, so that both directions of an edge differ but reruns agree."""
    w = F.pmod(F.xxhash64("src", "dst", F.lit(seed)), F.lit(high - low + 1)) + low
    return replace(g, edges=g.edges.withColumn(name, w))


def compare_edge_sets(a: PropertyGraph, b: PropertyGraph) -> DataFrame:
    """How many ordered pairs are in both graphs, only in the first, only in the second."""
    left, right = a.edges.select("src", "dst"), b.edges.select("src", "dst")
    parts = [("both", left.intersect(right)), ("first", left.exceptAll(right).distinct()), ("second", right.exceptAll(left).distinct())]
    out = None
    for name, df in parts:
        row = df.agg(F.count(F.lit(1)).alias("pairs")).select(F.lit(name).alias("side"), "pairs")
        out = row if out is None else out.unionByName(row)
    return out
