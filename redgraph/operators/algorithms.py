"""Graph algorithms in every communication mode."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from redgraph.functions.reduce import MAX, MIN, OR, ReduceOp
from redgraph.operators import superstep
from redgraph.operators.graph import PropertyGraph, degrees, hubs, symmetrize
from redgraph.operators.partition import Placed, assign
from redgraph.operators.superstep import RunResult
from redgraph.session import cut, cut_placed, fixed, scoped, task_count, told

SCALE = 1_000_000_000_000


def _seeds(g: PropertyGraph, ids: list[int], val: int) -> DataFrame:
    spark = g.edges.sparkSession
    return spark.createDataFrame([(int(i), val) for i in ids], "id long, val long")


def fixed_point(g: PropertyGraph, start: DataFrame, *, op: ReduceOp = MIN, expression: str = "plus_weight", mode: str = "plain", parts: int | None = None, scheme: str = "block", weight: str | None = "w", placed: Placed | None = None, check: bool = False, **options) -> RunResult:
    """Any monotone reduction program from a first frontier ``id, val``."""
    p = placed or assign(g, parts, scheme, weight=weight, check=check)
    return superstep.run(p, start, op=op, expression=expression, mode=mode, **options)


def sssp(g: PropertyGraph, source: int | None = None, *, sources: list[int] | None = None, check: bool = True, **options) -> RunResult:
    """Shortest distances from one source, or from the nearest of several; unreached vertices have no row."""
    return fixed_point(g, _seeds(g, sources if sources is not None else [source], 0), check=check, **options)


def bad_seed_sssp(g: PropertyGraph, **options) -> RunResult:
    """The seeding defect found in a baseline: every id divisible by 100 starts at distance 0."""
    start = g.ids().where("id % 100 = 0").select("id", F.lit(0).cast("long").alias("val"))
    return fixed_point(g, start, **options)


def wcc(g: PropertyGraph, **options) -> RunResult:
    """Smallest id of each weakly connected component, by label reduction over both directions."""
    both = symmetrize(g) if g.directed else g
    return fixed_point(both, both.ids().select("id", F.col("id").alias("val")), expression="same", **({"weight": None} | options))


def bfs(g: PropertyGraph, root: int, **options) -> RunResult:
    """Levels as a reduction program."""
    return fixed_point(g, _seeds(g, [root], 0), expression="plus_one", **({"weight": None} | options))


def widest_path(g: PropertyGraph, source: int, **options) -> RunResult:
    """The largest weight w such that a path of edges of at least w leads to each vertex."""
    return fixed_point(g, _seeds(g, [source], (1 << 62)), op=MAX, expression="least_with_weight", **options)


def reachable(g: PropertyGraph, source: int, **options) -> RunResult:
    """1 for every vertex that a path leads to."""
    return fixed_point(g, _seeds(g, [source], 1), op=OR, expression="same", **({"weight": None} | options))


def bfs_levels(g: PropertyGraph, root: int, *, direction: str = "auto", alpha: float = 1 / 14, max_levels: int = 100_000, traversal_log: list | None = None) -> DataFrame:
    """``id, level, parent`` (smallest parent; the root has none), one exchange per level.

    ``push`` expands the frontier's out-edges, ``pull`` lets unvisited vertices look for a visited
    in-neighbour of the last level; ``auto`` pulls when the frontier's out-edges exceed ``alpha`` of
    the unvisited vertices' edges.
    """
    spark = g.edges.sparkSession
    e = cut(g.edges.select("src", "dst").distinct())
    deg = cut(e.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("deg")))
    total = deg.agg(F.sum("deg")).first()[0] or 0
    seen = spark.createDataFrame([(root, 0, None)], "id long, level long, parent long")
    left = total
    for level in range(max_levels):
        front = seen.where(F.col("level") == level).select("id")
        out = front.join(deg, "id").agg(F.sum("deg")).first()[0] or 0
        left -= out
        pull = direction == "pull" or direction == "auto" and out > alpha * max(left, 1)
        if traversal_log is not None:
            traversal_log.append("pull" if pull else "push")
        if pull:
            open_ = e.join(seen.select(F.col("id").alias("dst")), "dst", "left_anti")
            found = open_.join(front.select(F.col("id").alias("src")), "src", "left_semi").groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent"))
        else:
            reached = e.join(front.select(F.col("id").alias("src")), "src", "left_semi").groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent"))
            found = reached.join(seen.select("id"), "id", "left_anti")
        watch = Observation()
        new = found.select("id", F.lit(level + 1).cast("long").alias("level"), "parent").observe(watch, F.count(F.lit(1)).alias("n"))
        new = cut(new)
        counts = told(watch)
        if not (counts["n"] if counts else new.count()):
            return seen
        seen = seen.unionByName(new)
    raise RuntimeError(f"more than {max_levels} levels")


def wcc_levels(g: PropertyGraph, *, max_roots: int = 2, parts: int | None = None, **options) -> DataFrame:
    """Components by level-order sweeps from hubs, then label reduction on what is left: ``id, component``."""
    both = symmetrize(g) if g.directed else g
    rest, out = both, None
    left = cut(both.ids())
    for _ in range(max_roots):
        top = hubs(rest, 1).first()
        if top is None or not top["out_degree"]:
            break
        found = bfs_levels(rest, top["id"]).select("id")
        found = cut(found.withColumn("component", F.lit(found.agg(F.min("id")).first()[0])))
        out = found if out is None else out.unionByName(found)
        left = cut(left.join(found, "id", "left_anti"))
        rest = PropertyGraph(cut(rest.edges.join(found.select(F.col("id").alias("src")), "src", "left_anti").select(*rest.edges.columns)), directed=False)
        if left.isEmpty():
            break
    if not left.isEmpty():
        tail = wcc(PropertyGraph(rest.edges, vertices=left, directed=False), parts=parts, **options).df.select("id", F.col("val").alias("component"))
        out = tail if out is None else out.unionByName(tail)
    return out


def _shares(g: PropertyGraph) -> tuple[DataFrame, DataFrame, int, int]:
    """Edges with the out-degree of their source and vertices, each placed once, how many vertices, and in how many parts.

    Both are dealt by the id of the sending vertex and keep that placement, so a round ships folded shares only.
    """
    parts = task_count(g.edges.sparkSession)
    deg = g.edges.groupBy("src").agg(F.count(F.lit(1)).alias("outdeg"))
    e = cut_placed(g.edges.select("src", "dst").join(deg, "src").repartition(parts, "src"), parts)
    v = cut_placed(g.ids().repartition(parts, "id"), parts)
    return e, v, v.count(), parts


def _received(e: DataFrame, sent: DataFrame, share: Column) -> DataFrame:
    """``id, acc``: the sum of what comes in; ``sent`` is placed like the edges, so only folded shares move."""
    given = e.join(sent, F.col("src") == F.col("id")).select(F.col("dst").alias("to"), share.alias("part"))
    return given.groupBy("to").agg(F.sum("part").alias("acc"))


def pagerank_fixed(g: PropertyGraph, rounds: int = 10) -> DataFrame:
    """Ranks in units of 1e-12 with floor divisions, so no order of additions matters: ``id, rank``.

    Damping 85 of 100, start 1/N, the mass of vertices without out-edges is dropped.
    """
    e, v, n, parts = _shares(g)
    base = 150_000_000_000 // n if n else 0
    rank = v.withColumn("rank", F.lit(SCALE // max(n, 1)).cast("long"))
    for _ in range(rounds):
        with scoped(v.sparkSession, fixed(parts)):
            acc = _received(e, rank, F.expr("((rank div outdeg) * 85) div 100"))
            rank = v.join(acc, F.col("id") == F.col("to"), "left").select("id", (F.lit(base) + F.coalesce("acc", F.lit(0))).cast("long").alias("rank"))
            rank = cut_placed(rank, parts)
    return rank


def pagerank(g: PropertyGraph, *, damping: float = 0.85, stop: str = "l1", tol: float = 1e-6, max_iter: int = 50, dangling: str = "drop") -> RunResult:
    """Two phases per round: spread shares along out-edges into a separate buffer, then scale and add.

    ``stop`` is ``l1`` or ``linf`` (change below ``tol``) or ``fixed``; ``dangling`` mass is dropped or spread.
    """
    e, v, n, parts = _shares(g)
    rank = v.withColumn("rank", F.lit(1.0 / max(n, 1)))
    n = max(n, 1)
    sinks = cut(v.join(e.select(F.col("src").alias("id")), "id", "left_anti")) if dangling == "spread" else None
    result = RunResult(rank)
    for _ in range(max_iter):
        lost = 0.0
        if sinks is not None:
            lost = rank.join(sinks, "id", "left_semi").agg(F.sum("rank")).first()[0] or 0.0
        acc = _received(e, rank, F.col("rank") / F.col("outdeg"))
        new = rank.select("id", F.col("rank").alias("old")).join(acc, F.col("id") == F.col("to"), "left").withColumn("rank", F.lit((1 - damping) / n + damping * lost / n) + F.lit(damping) * F.coalesce("acc", F.lit(0.0)))
        watch = Observation()
        gap = F.abs(F.col("rank") - F.col("old"))
        rank = cut_placed(new.observe(watch, F.sum(gap).alias("l1"), F.max(gap).alias("linf"), F.sum("rank").alias("mass")).select("id", "rank"), parts)
        counts = told(watch)
        if not counts and not rank.isEmpty():
            raise RuntimeError("a round of ranks did not tell its change")
        result.rounds.append(counts)
        if stop != "fixed" and counts.get(stop, 0.0) < tol:
            break
    result.df = rank
    return result


def pagerank_delta(g: PropertyGraph, *, damping: float = 0.85, tol: float = 1e-9, max_iter: int = 200) -> RunResult:
    """Ranks by residuals: only vertices whose pending change exceeds ``tol`` send, until none does."""
    e, v, n, parts = _shares(g)
    n = max(n, 1)
    state = cut_placed(v.select("id", F.lit(0.0).alias("rank"), F.lit((1 - damping) / n).alias("residual")), parts)
    result = RunResult(state)
    for _ in range(max_iter):
        active = F.col("residual") > tol
        acc = _received(e, state.where(active).select("id", "residual"), F.lit(damping) * F.col("residual") / F.col("outdeg"))
        new = state.join(acc, F.col("id") == F.col("to"), "left").select("id", (F.col("rank") + F.when(active, F.col("residual")).otherwise(0.0)).alias("rank"), (F.when(active, 0.0).otherwise(F.col("residual")) + F.coalesce("acc", F.lit(0.0))).alias("residual"))
        watch = Observation()
        state = cut_placed(new.observe(watch, F.sum((F.col("residual") > tol).cast("long")).alias("active"), F.sum("residual").alias("pending")), parts)
        counts = told(watch) or {"active": state.where(active).count()}
        result.rounds.append(counts)
        if not counts["active"]:
            break
    result.df = state.select("id", (F.col("rank") + F.col("residual")).alias("rank"))
    return result


def nbr_accumulate(g: PropertyGraph, x: str, y: str) -> DataFrame:
    """``x(v) += y(v)`` for each neighbour: only the loop vertex is touched, so no update travels."""
    return g.vertices.join(degrees(PropertyGraph(g.edges)).select("id", "out_degree"), "id", "left").select("id", (F.col(x) + F.coalesce("out_degree", F.lit(0)) * F.col(y)).alias(x))


def edge_min(g: PropertyGraph, x: str, y: str) -> DataFrame:
    """The edge property ``y`` becomes the smaller of itself and the source's ``x``: edges are owned by their source."""
    return g.edges.join(g.vertices.select(F.col("id").alias("src"), F.col(x).alias("__x")), "src").withColumn(y, F.least(y, "__x")).select(*g.edges.columns)


def khop(g: PropertyGraph, source: int, k: int) -> DataFrame:
    """Vertices within ``k`` hops, in recursive SQL: ``id, hops``."""
    spark = g.edges.sparkSession
    g.edges.select("src", "dst").distinct().createOrReplaceTempView("redgraph_khop_edges")
    return spark.sql(f"""WITH RECURSIVE r(id, hops) AS (SELECT CAST({source} AS BIGINT), 0L UNION ALL SELECT e.dst, hops + 1 FROM r JOIN redgraph_khop_edges e ON r.id = e.src WHERE hops < {k}) SELECT id, min(hops) AS hops FROM r GROUP BY id""")


def triangles(g: PropertyGraph) -> DataFrame:
    """Triangles of the undirected simple graph, counted at their smallest-degree corner: one row ``triangles``.

    Edges point from the smaller to the larger degree, which bounds every vertex's out-edges by the square
    root of twice the edges, however large a hub is.
    """
    pair = g.edges.where("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    deg = pair.select(F.explode(F.array("a", "b")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("d"))
    ranked = pair.join(deg.select(F.col("id").alias("a"), F.col("d").alias("da")), "a").join(deg.select(F.col("id").alias("b"), F.col("d").alias("db")), "b")
    up = (F.col("da") < F.col("db")) | ((F.col("da") == F.col("db")) & (F.col("a") < F.col("b")))
    e = cut(ranked.select(F.when(up, F.col("a")).otherwise(F.col("b")).alias("u"), F.when(up, F.col("b")).otherwise(F.col("a")).alias("v")))
    wedge = e.join(e.select("u", F.col("v").alias("w")), "u").where("v <> w")
    return wedge.join(e.select(F.col("u").alias("v"), F.col("v").alias("w")), ["v", "w"]).agg(F.count(F.lit(1)).alias("triangles"))


def two_hop(g: PropertyGraph) -> DataFrame:
    """Per vertex, how many walks of two edges start there: degrees are folded first, no walk is listed."""
    deg = g.edges.groupBy(F.col("src").alias("dst")).agg(F.count(F.lit(1)).alias("n"))
    return g.edges.join(deg, "dst").groupBy(F.col("src").alias("id")).agg(F.sum("n").alias("walks"))


def match_path(g: PropertyGraph, k: int) -> DataFrame:
    """How many walks of ``k`` edges start at each vertex (subgraph matching of a path)."""
    count = g.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("walks"))
    for _ in range(k - 1):
        count = g.edges.join(count.withColumnRenamed("id", "dst"), "dst").groupBy(F.col("src").alias("id")).agg(F.sum("walks").alias("walks"))
    return count


def match_pattern(g: PropertyGraph, pattern: list[tuple[str, str]], *, ordered: list[tuple[str, str]] = (), induced: bool = False) -> DataFrame:
    """Subgraph matching: one row per image of a small directed pattern, a column per pattern vertex.

    ``pattern`` lists edges between named vertices, each after the first touching one that came before.
    Different names are different vertices; ``ordered`` pairs ``(a, b)`` demand a < b, which keeps one image
    of a symmetric pattern.  A pattern edge between known vertices is a semi-join, any other one a join
    along the edges.  With ``induced`` no other edge may join the matched vertices.
    """
    e = cut(g.edges.where("src <> dst").select("src", "dst").distinct())
    found, names = None, []
    for a, b in pattern:
        step = e.select(F.col("src").alias(a), F.col("dst").alias(b))
        new = [x for x in (a, b) if x not in names]
        on = [x for x in (a, b) if x in names]
        if found is None:
            found = step
        elif not on:
            raise ValueError(f"the edge {a}-{b} touches no vertex before it")
        else:
            found = found.join(step, on, "left_semi" if not new else "inner")
        for x in new:
            for y in names:
                if {x, y} != {a, b}:
                    found = found.where(F.col(x) != F.col(y))
            names.append(x)
        for x, y in ordered:
            if x in names and y in names and (x in new or y in new):
                found = found.where(F.col(x) < F.col(y))
    if induced:
        for x in names:
            for y in names:
                if x != y and (x, y) not in pattern:
                    found = found.join(e.select(F.col("src").alias(x), F.col("dst").alias(y)), [x, y], "left_anti")
    return found.select(*names)


def diamonds(g: PropertyGraph, per_row: int = 4096) -> DataFrame:
    """How many images of a-b, a-c, b-d, c-d with b < c and four different vertices start at each a: ``id, matches``.

    Two walks from a to the same d over different middles are one image, so each a needs the number of walks
    to every d only.  The middles' targets travel to a as lists of at most ``per_row`` and are counted there:
    no image and no walk is a row of its own.
    """
    e = cut(g.edges.where("src <> dst").select("src", "dst").distinct())
    slot = F.floor((F.row_number().over(Window.partitionBy("src").orderBy("dst")) - 1) / per_row)
    lists = e.withColumn("slot", slot).groupBy(F.col("src").alias("mid"), "slot").agg(F.collect_list("dst").alias("ds")).drop("slot")
    walks = e.select(F.col("src").alias("a"), F.col("dst").alias("mid")).join(lists, "mid").select("a", "ds")
    parts = task_count(e.sparkSession)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, open_, held = None, [], 0

        def folded(a: int, pieces: list) -> tuple[np.ndarray, np.ndarray]:
            d, n = np.concatenate([p for p, _ in pieces]), np.concatenate([m for _, m in pieces])
            ids, slot = np.unique(d, return_inverse=True)
            return ids, np.bincount(slot, n, len(ids)).astype(np.int64)

        def done(a: int, pieces: list) -> tuple[int, int]:
            ids, n = folded(a, pieces)
            n = n[ids != a]
            return a, int((n * (n - 1) // 2).sum())

        for batch in batches:
            a, lists_ = batch.column(0).to_numpy(), batch.column(1)
            d = lists_.flatten().to_numpy()
            edge = np.concatenate([[0], np.cumsum(lists_.value_lengths().to_numpy())])
            cuts = [0, *(np.flatnonzero(a[1:] != a[:-1]) + 1).tolist(), len(a)]
            out = []
            for p, q in zip(cuts, cuts[1:], strict=False):
                if p == q:
                    continue
                if last is not None and a[p] != last:
                    out.append(done(last, open_))
                    open_, held = [], 0
                last = int(a[p])
                piece = d[edge[p] : edge[q]]
                open_.append((piece, np.ones(len(piece), np.int64)))
                held += len(piece)
                if held > 1 << 22:  # a hub: fold what it has so far
                    open_ = [folded(last, open_)]
                    held = len(open_[0][0])
            out = [x for x in out if x[1]]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names=["id", "matches"])
        if last is not None and (row := done(last, open_))[1]:
            yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in row], names=["id", "matches"])

    return walks.repartition(parts, "a").sortWithinPartitions("a").mapInArrow(count, "id long, matches long")


def edge_of(g: PropertyGraph, pairs: DataFrame) -> DataFrame:
    """The edges of pairs ``src, dst``: the look-up that a neighbour loop without an edge variable has to make."""
    return pairs.select("src", "dst").join(g.edges, ["src", "dst"])


def weights_by_search(g: PropertyGraph, w: str = "w") -> DataFrame:
    """Per vertex the sum of its edges' ``w``, each edge searched by its two ends (the traversal that edge iteration replaces)."""
    neighbours = g.edges.groupBy("src").agg(F.collect_set("dst").alias("of")).select("src", F.explode("of").alias("dst"))
    return edge_of(g, neighbours).groupBy(F.col("src").alias("id")).agg(F.sum(w).alias("total"))


def weights_by_iteration(g: PropertyGraph, w: str = "w") -> DataFrame:
    """The same by going over the edges themselves: one grouping, no look-up."""
    return g.edges.groupBy(F.col("src").alias("id")).agg(F.sum(w).alias("total"))


def global_reduce(rows: DataFrame, column: str, op: str) -> DataFrame:
    """One value folded over all vertices or edges: sum, product, min, max, and, or; one row ``value``."""
    c = F.col(column)
    fold = {"sum": F.sum(c), "product": F.product(c), "min": F.min(c), "max": F.max(c), "and": F.bool_and(c), "or": F.bool_or(c)}
    if op not in fold:
        raise ValueError(f"unknown reduction {op}")
    return rows.agg(fold[op].alias("value"))
