"""Ownership: which part owns a vertex, and placing state and edges accordingly.

Rows of owner k are sent to task k exactly (``repartitionById``), once.  Joins and groupings on the
owner then need no exchange, however many rounds follow.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from redgraph.operators.graph import PropertyGraph
from redgraph.session import cut, cut_placed, told

Owner = Callable[[Column], Column]

#: Owners of a graph whose caller names no number, and the edges of one (some 70 bytes each in a fused round) beyond which there are more.
OWNERS, OWNED = 8, 1 << 21


def owner(scheme: str, parts: int, *, top: int | None = None, bounds: list[int] | None = None, by: Callable[[Column], Column] | None = None) -> Owner:
    """Owner number of an id column: ``block`` (equal id segments below ``top``), ``mod``, ``hash``, ``range`` (ends of segments), ``by_column`` (an attribute computed from the id)."""
    if scheme == "block":
        if top is None:
            raise ValueError("block ownership needs the largest id")
        return lambda c: F.expr("0").cast("int") if parts == 1 else F.least(F.floor(c * parts / F.lit(float(top + 1))).cast("int"), F.lit(parts - 1))
    if scheme == "mod":
        return lambda c: F.pmod(c, F.lit(parts)).cast("int")
    if scheme == "hash":
        return lambda c: F.pmod(F.xxhash64(c), F.lit(parts)).cast("int")
    if scheme == "range":
        ends = list(bounds or [])
        return lambda c: F.least(_below(c, ends, 0), F.lit(parts - 1)).cast("int")
    if scheme == "by_column":
        return lambda c: F.pmod(by(c), F.lit(parts)).cast("int")
    raise ValueError(f"unknown scheme {scheme}")


def _below(c: Column, ends: list[int], first: int) -> Column:
    """How many of the ascending ``ends`` lie below ``c``, plus ``first``: a search by halves, compiled into the plan."""
    if not ends:
        return F.lit(first)
    half = len(ends) // 2
    return F.when(c > F.lit(ends[half]), _below(c, ends[half + 1 :], first + half + 1)).otherwise(_below(c, ends[:half], first))


def working(owners: list[int] | None, *placed: DataFrame) -> list[DataFrame]:
    """The rows of the owners that have work; all rows if that is not known.  Rows stay where they are."""
    return list(placed) if owners is None else [df.where(F.col("part").isin([int(p) for p in owners])) for df in placed]


def range_bounds(g: PropertyGraph, parts: int) -> list[int]:
    """Ends of id segments with about equal numbers of out-edges, from a quantile sketch of bounded size."""
    return [int(x) for x in g.edges.approxQuantile("src", [k / parts for k in range(1, parts)], 0.001)]


def top_id(g: PropertyGraph) -> int:
    row = g.edges.agg(F.greatest(F.max("src"), F.max("dst"))).first()[0]
    if g.vertices is not None:
        row = max(row or 0, g.vertices.agg(F.max("id")).first()[0] or 0)
    return int(row or 0)


def bfs_grown(levels: DataFrame, parts: int) -> DataFrame:
    """Explicit owners ``id, part`` that follow the levels of a traversal: near vertices share an owner.

    ``levels`` has ``id, level``.  Levels are cut where the running number of vertices passes equal shares.
    """
    from pyspark.sql import Window

    sizes = levels.groupBy("level").agg(F.count(F.lit(1)).alias("n"))
    w = Window.orderBy("level")
    cutoff = sizes.select("level", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, -1)).alias("ahead"), F.sum("n").over(Window.partitionBy()).alias("all"))
    part = F.least(F.floor(F.coalesce("ahead", F.lit(0)) * parts / F.col("all")).cast("int"), F.lit(parts - 1))
    return levels.join(cutoff.select("level", part.alias("part")), "level").select("id", "part")


def degree_balanced(g: PropertyGraph, parts: int) -> DataFrame:
    """Explicit owners ``id, part``: vertices dealt in turn by falling out-degree, so hubs are spread.

    Ranked within degree classes, so no task sorts all vertices.
    """
    from pyspark.sql import Window

    from redgraph.operators.graph import degrees

    d = degrees(g).select("id", "out_degree", F.length(F.bin("out_degree")).alias("class"), F.pmod(F.xxhash64("id"), F.lit(64)).alias("salt"))
    place = F.row_number().over(Window.partitionBy("class", "salt").orderBy(F.desc("out_degree"), "id")) + F.col("salt")
    return d.select("id", F.pmod(place, F.lit(parts)).cast("int").alias("part"))


@dataclass(frozen=True)
class Placed:
    """Edges with the owners of both ends, sent to the owner of the source; ``parts`` owners."""

    edges: DataFrame  # part, src, dst, dst_part, w
    vertices: DataFrame  # id, part
    parts: int
    of: Owner | None


def assign(g: PropertyGraph, parts: int | None, scheme: str = "hash", *, weight: str | None = None, owners: DataFrame | None = None, by: Callable[[Column], Column] | None = None, check: bool = False) -> Placed:
    """Place a graph: one shuffle of the edges, kept by a reliable checkpoint.

    With ``owners`` (``id, part``) the owner of an end is looked up, else computed from the id.  ``check``
    refuses null ends and null or negative weights, counted while the edges are placed.  Without ``parts``
    there are ``OWNERS`` of them, or as many as an owner has ``OWNED`` edges; equal blocks of ids then give
    way to ranges of equally many edges, since a block of hubs would not fit a task.
    """
    w = F.col(weight).cast("long") if weight else F.lit(1).cast("long")
    source = g.edges.select("src", "dst", w.alias("w"))
    watch = Observation()
    if check:
        count = lambda c: F.sum(c.cast("long"))
        faults = [count(F.col("src").isNull() | F.col("dst").isNull()).alias("null ends"), count(F.col("w").isNull()).alias("null weights"), count(F.coalesce(F.col("w") < 0, F.lit(False))).alias("negative weights")]
        source = source.observe(watch, *faults)
    if parts is None:
        source = cut(source)
        n = source.count()
        parts = max(OWNERS, -(-n // OWNED))
        if parts > OWNERS and scheme == "block":
            scheme = "range"
        g = replace(g, edges=source)
    if owners is not None:
        e = source.join(owners.select(F.col("id").alias("src"), "part"), "src").join(owners.select(F.col("id").alias("dst"), F.col("part").alias("dst_part")), "dst")
        of = None
    else:
        if scheme in ("block", "range"):  # their bounds come from a pass over the ends before the edges are placed
            source = g.edges if source is g.edges else cut(source)
            g = replace(g, edges=source)
        of = owner(scheme, parts, top=top_id(g) if scheme == "block" else None, bounds=range_bounds(g, parts) if scheme == "range" else None, by=by)
        e = source.select("src", "dst", "w", of(F.col("src")).alias("part"), of(F.col("dst")).alias("dst_part"))
    e = cut_placed(e.select("part", "src", "dst", "dst_part", "w").repartitionById(parts, "part"), parts)
    if check:
        for what, n in (told(watch) or e.agg(*faults).first().asDict()).items():
            if n:
                raise ValueError(f"{n} edges with {what}")
    # columns keep their names and types from here on: a renamed or cast owner would hide the placement
    vertices = owners
    if owners is not None:
        kinds = dict(owners.dtypes)
        vertices = owners.select("id", "part") if (kinds["id"], kinds["part"]) == ("bigint", "int") else owners.select(F.col("id").cast("long"), F.col("part").cast("int"))
    if of is not None:
        ends = e.select("part", F.col("src").alias("id")).unionByName(e.select(F.col("dst_part").alias("part"), F.col("dst").alias("id")))
        if g.vertices is not None:
            ends = ends.unionByName(g.vertices.select(of(F.col("id")).alias("part"), "id"))
        vertices = ends.distinct().select("id", "part")
    return Placed(e, vertices, parts, of)


def partition_stats(p: Placed) -> DataFrame:
    """Per part: edges, cut edges (foreign far end) and source vertices."""
    return p.edges.groupBy("part").agg(F.count(F.lit(1)).alias("edges"), F.sum((F.col("part") != F.col("dst_part")).cast("long")).alias("cut"), F.count_distinct("src").alias("sources"))


def skew(p: Placed) -> DataFrame:
    """Largest part over the mean part (empty parts count) and the share of cut edges."""
    s = partition_stats(p)
    return s.agg((F.max("edges") * p.parts / F.sum("edges")).alias("skew"), (F.sum("cut") / F.sum("edges")).alias("cut_fraction"))
