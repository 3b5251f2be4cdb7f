"""Registered queries: every method, variant, baseline and measure on the given tables.

``QUERIES`` maps names to functions of a session and a table folder; ``ORACLES`` holds DuckDB SQL with
the same rows.  Iterative answers are checked by recursive SQL that keeps one row per key.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from redgraph.functions.reduce import MIN, ordered_fold
from redgraph.operators import algorithms as al
from redgraph.operators import baselines, mailbox, metrics, packed
from redgraph.operators import graph as gr
from redgraph.operators import partition as pt
from redgraph.operators.components import connected_components
from redgraph.plans import ir, lower, rewrite, text
from redgraph.plans.rewrite import CompileOptions
from redgraph.sources import generate, tables
from redgraph.sources.tables import edge_sql, graph
from redgraph.streaming import incremental

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


# oracles ---------------------------------------------------------------------------------------


def fixed_sql(edges: str, seeds: str, value: str, better: str = "<", fold: str = "min", out: str = "dist") -> str:
    """Least (or greatest) values reachable from ``seeds(v, d)`` along ``edges``; ``value`` is over r.d and e.w."""
    return f"""
    WITH RECURSIVE e AS MATERIALIZED ({edges}), r(v, d) USING KEY (v) AS (
        SELECT v, d FROM ({seeds}) s
        UNION
        SELECT n.v, n.d FROM (SELECT e.dst AS v, {fold}({value}) AS d FROM r JOIN e ON r.v = e.src GROUP BY e.dst) n LEFT JOIN recurring.r o ON o.v = n.v WHERE o.d IS NULL OR n.d {better} o.d)
    SELECT CAST(v AS BIGINT) AS id, CAST(d AS BIGINT) AS {out} FROM r"""


def sssp_sql(edges: str, seeds: str = "SELECT CAST(0 AS BIGINT) AS v, CAST(0 AS BIGINT) AS d") -> str:
    return fixed_sql(edges, seeds, "r.d + e.w")


def both_ways(edges: str) -> str:
    return f"SELECT src, dst, w FROM ({edges}) a UNION ALL SELECT dst AS src, src AS dst, w FROM ({edges}) b"


def wcc_sql(edges: str) -> str:
    e = both_ways(edges)
    return fixed_sql(e, f"SELECT DISTINCT src AS v, src AS d FROM ({e}) q", "r.d", out="component")


def pagerank_sql(edges: str, rounds: int = 10, real: bool = False, vertices: str | None = None) -> str:
    """The two-phase recurrence over all vertices; a zero row for each keeps those without in-edges."""
    ids = vertices or "SELECT src AS id FROM e UNION SELECT dst FROM e"
    start, share, base = ("1.0::DOUBLE / n", "rank / outdeg", "0.15::DOUBLE / n + 0.85 * sum(s)") if real else ("1000000000000 // n", "((rank // outdeg) * 85) // 100", "150000000000 // n + sum(s)")
    kind = "DOUBLE" if real else "BIGINT"
    return f"""
    WITH RECURSIVE e AS MATERIALIZED ({edges}), v AS MATERIALIZED ({ids}), c AS MATERIALIZED (SELECT count(*) AS n FROM v), deg AS MATERIALIZED (SELECT src, count(*) AS outdeg FROM e GROUP BY src),
    x AS MATERIALIZED (SELECT e.src, e.dst, outdeg FROM e JOIN deg USING (src) UNION ALL SELECT id, id, NULL FROM v),
    r(k, id, rank) AS (
        SELECT 0, id, CAST({start} AS {kind}) FROM v, c
        UNION ALL
        SELECT k + 1, id, CAST({base} AS {kind}) FROM (SELECT r.k, x.dst AS id, CASE WHEN outdeg IS NULL THEN 0 ELSE {share} END AS s FROM r JOIN x ON r.id = x.src WHERE r.k < {rounds}) q, c GROUP BY k, id, n)
    SELECT id, rank FROM r WHERE k = {rounds}"""


TRADE = edge_sql("trade")
GRID = edge_sql("grid")
USER_HOP = edge_sql("user_hop")
CUST_SUPP = edge_sql("cust_supp")
DOC_SHARE = edge_sql("doc_share")
TURN_CHAIN = edge_sql("turn_chain")
ORG_TREE = edge_sql("org_tree")
EVENT_CHAIN = edge_sql("event_chain")


def _dist(r, name: str = "dist") -> DataFrame:
    return r.df.select("id", F.col("val").alias(name))


# shortest paths --------------------------------------------------------------------------------

for _mode, _more in (("uncombined", {}), ("plain", {}), ("short_circuit", {}), ("pulse", {}), ("bounded2", {"max_local_rounds": 2})):
    _name = "bounded_pulse" if _mode == "bounded2" else _mode
    query(f"sssp_trade_{_mode}", sssp_sql(TRADE))(lambda s, d, m=_name, k=_more: _dist(al.sssp(graph(s, d, "trade"), 0, mode=m, **k)))
for _mode, _more in (("plain", {}), ("short_circuit", {}), ("bounded2", {"max_local_rounds": 2})):
    _name = "bounded_pulse" if _mode == "bounded2" else _mode
    query(f"sssp_{_mode}", sssp_sql(GRID))(lambda s, d, m=_name, k=_more: _dist(al.sssp(graph(s, d, "grid"), 0, mode=m, **k)))
query("sssp_pulse", sssp_sql(GRID))(lambda s, d: _dist(al.sssp(graph(s, d, "grid"), 0, mode="pulse")))
query("sssp_user_hop", sssp_sql(USER_HOP))(lambda s, d: _dist(al.sssp(graph(s, d, "user_hop"), 0, mode="pulse")))


@query("sssp_trade_mirror", sssp_sql(TRADE))
def sssp_trade_mirror(spark, d):
    g = graph(spark, d, "trade")
    return _dist(baselines.mirror_sync(g, al._seeds(g, [0], 0)))


@query("sssp_trade_mirror_push", sssp_sql(TRADE))
def sssp_trade_mirror_push(spark, d):
    g = graph(spark, d, "trade")
    return _dist(baselines.mirror_sync(g, al._seeds(g, [0], 0), style="push"))


@query("sssp_trade_master", sssp_sql(TRADE))
def sssp_trade_master(spark, d):
    g = graph(spark, d, "trade")
    return _dist(baselines.master_worker(packed.pack(g, 8, "block", weight="w"), al._seeds(g, [0], 0)))


@query("sssp_trade_predecessor", sssp_sql(TRADE))
def sssp_trade_predecessor(spark, d):
    g = graph(spark, d, "trade")
    return _dist(baselines.predecessor(pt.assign(g, 8, "block", weight="w"), al._seeds(g, [0], 0)))


query("sssp_multi_source", sssp_sql(TRADE, "SELECT * FROM (VALUES (0::BIGINT, 0::BIGINT), (1, 0), (8, 0)) t(v, d)"))(lambda s, d: _dist(al.sssp(graph(s, d, "trade"), sources=[0, 1, 8], mode="pulse")))
query("sssp_bad_seed", sssp_sql(TRADE, f"SELECT DISTINCT src AS v, CAST(0 AS BIGINT) AS d FROM ({TRADE}) q WHERE src % 100 = 0"))(lambda s, d: _dist(al.bad_seed_sssp(graph(s, d, "trade"), mode="pulse")))


@query("sssp_chain", "SELECT event_id AS id, CAST(date_diff('microsecond', min(ts) OVER (PARTITION BY user_id), ts) AS BIGINT) AS dist FROM events")
def sssp_chain(spark, d):
    """Time since each user's first event, along the chain of events; owners follow the users, so one pulse does."""
    events = tables.read_table(spark, d, "events").select("event_id", "user_id", "ts")
    owners = events.select(F.col("event_id").alias("id"), F.pmod("user_id", F.lit(8)).cast("int").alias("part"))
    first = events.groupBy("user_id").agg(F.min(F.struct("ts", "event_id"))["event_id"].alias("id")).select("id", F.lit(0).cast("long").alias("val"))
    placed = pt.assign(graph(spark, d, "event_chain"), 8, owners=owners, weight="w")
    return _dist(al.fixed_point(None, first, placed=placed, mode="pulse"))


@query("sssp_program", sssp_sql(TRADE))
def sssp_program(spark, d):
    """The same through a program text, its analyses and its rewrites."""
    program = text.parse("program sssp\nvertex val; edge w\nstart val[0] = 0\nwhile worklist\n  for v in vertices\n    for n of v\n      edge e = v-n\n      min n.val <- v.val + e.w\n")
    return _dist(lower.compile(program, graph(spark, d, "trade")).run())


@query("widest_path", fixed_sql(GRID, "SELECT CAST(0 AS BIGINT) AS v, 4611686018427387904::BIGINT AS d", "least(r.d, e.w)", ">", "max", "width"))
def widest_path(spark, d):
    return _dist(al.widest_path(graph(spark, d, "grid"), 0, mode="pulse"), "width")


query("reachable", fixed_sql(CUST_SUPP, "SELECT CAST(0 AS BIGINT) AS v, CAST(1 AS BIGINT) AS d", "r.d", ">", "max", "reached"))(lambda s, d: _dist(al.reachable(graph(s, d, "cust_supp"), 0, mode="pulse"), "reached"))
query("khop", f"WITH RECURSIVE e AS MATERIALIZED (SELECT DISTINCT src, dst FROM ({USER_HOP}) q), r(id, hops) AS (SELECT 0::BIGINT, 0::BIGINT UNION SELECT e.dst, hops + 1 FROM r JOIN e ON r.id = e.src WHERE hops < 2) SELECT id, min(hops) AS hops FROM r GROUP BY id")(
    lambda s, d: al.khop(graph(s, d, "user_hop"), 0, 2)
)

# components ------------------------------------------------------------------------------------

query("wcc_plain", wcc_sql(DOC_SHARE))(lambda s, d: _dist(al.wcc(graph(s, d, "doc_share"), mode="plain"), "component"))
query("wcc_short_circuit", wcc_sql(TRADE))(lambda s, d: _dist(al.wcc(graph(s, d, "trade"), mode="short_circuit"), "component"))
query("wcc_pulse", wcc_sql(GRID))(lambda s, d: _dist(al.wcc(graph(s, d, "grid"), mode="pulse"), "component"))
query("wcc_bfs", wcc_sql(DOC_SHARE))(lambda s, d: al.wcc_levels(graph(s, d, "doc_share"), mode="pulse"))
query("wcc_contract", wcc_sql(DOC_SHARE))(lambda s, d: connected_components(graph(s, d, "doc_share").edges))
query("wcc_chain", f"SELECT 1000 * conv_id + turn AS id, min(1000 * conv_id + turn) OVER (PARTITION BY conv_id) AS component FROM conversations WHERE conv_id IN (SELECT conv_id FROM conversations GROUP BY conv_id HAVING count(*) > 1)")(
    lambda s, d: _dist(al.wcc(graph(s, d, "turn_chain"), mode="pulse"), "component")
)

# level order -----------------------------------------------------------------------------------


def bfs_sql(edges: str, root: int = 0) -> str:
    levels = fixed_sql(edges, f"SELECT CAST({root} AS BIGINT) AS v, CAST(0 AS BIGINT) AS d", "r.d + 1", out="level")
    return f"WITH l AS ({levels}), e2 AS ({edges}) SELECT l.id, l.level, CAST(min(p.id) AS BIGINT) AS parent FROM l LEFT JOIN e2 ON e2.dst = l.id LEFT JOIN l p ON p.id = e2.src AND p.level = l.level - 1 GROUP BY l.id, l.level"


for _how in ("push", "pull", "auto"):
    query(f"bfs_{_how}", bfs_sql(TRADE))(lambda s, d, h=_how: al.bfs_levels(graph(s, d, "trade"), 0, direction=h))
query("bfs_tree", bfs_sql(ORG_TREE))(lambda s, d: al.bfs_levels(graph(s, d, "org_tree"), 0))
query("bfs_program", fixed_sql(TRADE, "SELECT CAST(0 AS BIGINT) AS v, CAST(0 AS BIGINT) AS d", "r.d + 1", out="level"))(lambda s, d: _dist(al.bfs(graph(s, d, "trade"), 0, mode="pulse"), "level"))

# ranks -----------------------------------------------------------------------------------------

query("pagerank_fixed10", pagerank_sql(CUST_SUPP))(lambda s, d: al.pagerank_fixed(graph(s, d, "cust_supp")))
query("pagerank_fixed10_trade", pagerank_sql(TRADE))(lambda s, d: al.pagerank_fixed(graph(s, d, "trade")))


def _rounded(df: DataFrame, digits: int = 8) -> DataFrame:
    return df.select("id", F.round("rank", digits).alias("rank"))


query("pagerank_two_phase", f"SELECT id, round(rank, 8) AS rank FROM ({pagerank_sql(TRADE, 10, True)}) q")(lambda s, d: _rounded(al.pagerank(graph(s, d, "trade"), stop="fixed", max_iter=10).df))
query("pagerank_l1", f"SELECT id, round(rank, 6) AS rank FROM ({pagerank_sql(CUST_SUPP, 40, True)}) q")(lambda s, d: _rounded(al.pagerank(graph(s, d, "cust_supp"), tol=1e-9).df, 6))
query("pagerank_delta", f"SELECT id, round(rank, 6) AS rank FROM ({pagerank_sql(CUST_SUPP, 40, True)}) q")(lambda s, d: _rounded(al.pagerank_delta(graph(s, d, "cust_supp"), tol=1e-12).df, 6))
query("pagerank_spread")(lambda s, d: _rounded(al.pagerank(graph(s, d, "cust_supp"), tol=1e-6, dangling="spread").df, 6))


_GAP = f"SELECT abs(a.rank - b.rank / 1e12::DOUBLE) AS g FROM ({pagerank_sql(CUST_SUPP, 10, True)}) a JOIN ({pagerank_sql(CUST_SUPP, 10)}) b USING (id)"


@query("pagerank_error", f"SELECT round(sum(g), 6) AS l1, round(max(g), 8) AS linf FROM ({_GAP}) q")
def pagerank_error(spark, d):
    """L1 and largest difference of double ranks to the exact fixed-point ones."""
    g = graph(spark, d, "cust_supp")
    exact = al.pagerank_fixed(g, 10).select("id", (F.col("rank") / 1e12).alias("rank"))
    return metrics.rank_error(al.pagerank(g, stop="fixed", max_iter=10).df, exact).select(F.round("l1", 6).alias("l1"), F.round("linf", 8).alias("linf"))


# motivating patterns ---------------------------------------------------------------------------


def _customers(spark, d) -> DataFrame:
    return tables.read_table(spark, d, "customer").select((2 * F.col("c_custkey")).alias("id"), F.lit(0).cast("long").alias("x"), F.col("c_nationkey").cast("long").alias("y"))


@query("nbr_accumulate", f"SELECT 2 * c_custkey AS id, coalesce(n, 0) * CAST(c_nationkey AS BIGINT) AS x FROM customer LEFT JOIN (SELECT src, count(*) AS n FROM ({CUST_SUPP}) q GROUP BY src) t ON t.src = 2 * c_custkey")
def nbr_accumulate(spark, d):
    g = graph(spark, d, "cust_supp")
    return al.nbr_accumulate(gr.PropertyGraph(g.edges, _customers(spark, d)), "x", "y")


@query("edge_min", f"SELECT src, dst, least(w, CAST(c_nationkey AS BIGINT)) AS w FROM ({CUST_SUPP}) q JOIN customer ON src = 2 * c_custkey")
def edge_min(spark, d):
    g = graph(spark, d, "cust_supp")
    return al.edge_min(gr.PropertyGraph(g.edges, _customers(spark, d)), "y", "w")


# mailbox: the first round of labels on trade, owners by remainder -----------------------------


def _first_mail(spark, d) -> DataFrame:
    p = pt.assign(graph(spark, d, "trade"), 8, "mod", weight="w")
    return mailbox.emit(p.vertices.select("part", "id", F.col("id").alias("val")), p, F.col("val"))


_MAIL = f"SELECT CAST(src % 8 AS INTEGER) AS from_part, CAST(dst % 8 AS INTEGER) AS to_part, dst, src AS val FROM ({TRADE}) q"
_FOLDED = f"SELECT from_part, to_part, dst, min(val) AS val FROM ({_MAIL}) m GROUP BY from_part, to_part, dst"
query("mailbox_raw", _MAIL)(_first_mail)
query("mailbox_combined", _FOLDED)(lambda s, d: mailbox.shorten(_first_mail(s, d), MIN))
query("mailbox_short_circuit", f"SELECT * FROM ({_FOLDED}) f WHERE from_part = to_part")(lambda s, d: mailbox.short_circuit(mailbox.shorten(_first_mail(s, d), MIN))[0])
query("mailbox_chunks", f"SELECT *, CAST((row_number() OVER (PARTITION BY from_part, to_part ORDER BY dst, val) - 1) // 64 AS BIGINT) AS chunk FROM ({_FOLDED}) f")(lambda s, d: mailbox.chunk(mailbox.shorten(_first_mail(s, d), MIN), 64))
query("batch_counts", f"SELECT from_part, to_part, count(*) AS entries, CAST(ceil(count(*) / 64.0) AS BIGINT) AS batches, count(*) * 16 AS bytes FROM ({_FOLDED}) f GROUP BY from_part, to_part")(lambda s, d: mailbox.batch_counts(mailbox.shorten(_first_mail(s, d), MIN), 64))
_MERGED = f"SELECT CAST(id % 8 AS INTEGER) AS part, id, least(id, val) AS val FROM (SELECT dst AS id, min(src) AS val FROM ({TRADE}) q GROUP BY dst) t"


def _state(spark, d) -> DataFrame:
    return graph(spark, d, "trade").ids().select(F.pmod("id", F.lit(8)).cast("int").alias("part"), "id", F.col("id").alias("val"))


query("sync_batched", _MERGED)(lambda s, d: mailbox.sync_batched(_first_mail(s, d), _state(s, d), MIN, 8))
query("sync_all_to_all", _MERGED)(lambda s, d: mailbox.sync_all_to_all(_first_mail(s, d), _state(s, d), MIN, 8))
query("sync_chunks", _MERGED)(lambda s, d: mailbox.sync_chunks(_first_mail(s, d), _state(s, d), MIN, 8, 256))
query("put_last", f"SELECT CAST(dst % 8 AS INTEGER) AS part, dst AS id, max(src) AS val FROM ({TRADE}) q GROUP BY dst")(
    lambda s, d: mailbox.put(_state(s, d), _first_mail(s, d).select(F.col("to_part").alias("part"), F.col("dst").alias("id"), F.col("val").alias("seq"), "val"))
)
query("ordered_fold", f"SELECT src AS id, list_reduce(list_prepend(0::BIGINT, list(w ORDER BY dst)), lambda a, b: (a * 31 + b) % 1000003) AS val FROM ({USER_HOP}) q GROUP BY src")(
    lambda s, d: ordered_fold(graph(s, d, "user_hop").edges, "src", "dst", "w", F.lit(0).cast("long"), lambda a, b: (a * 31 + b) % 1000003).select(F.col("src").alias("id"), F.col("w").alias("val"))
)

# measures --------------------------------------------------------------------------------------


@query("edge_search_cost", " UNION ALL ".join(f"SELECT '{n}' AS graph, CAST(sum(n * n) AS BIGINT) AS search_steps, CAST(sum(n) AS BIGINT) AS iteration_steps FROM (SELECT count(*) AS n FROM ({edge_sql(n)}) q GROUP BY src) t" for n in ("trade", "grid", "user_hop", "event_chain")))
def edge_search_cost(spark, d):
    out = None
    for n in ("trade", "grid", "user_hop", "event_chain"):
        row = metrics.edge_search_cost(graph(spark, d, n)).select(F.lit(n).alias("graph"), "search_steps", "iteration_steps")
        out = row if out is None else out.unionByName(row)
    return out


def _stats_sql(edges: str, part: str) -> str:
    return f"SELECT CAST({part.format(c='src')} AS INTEGER) AS part, count(*) AS edges, CAST(sum(CASE WHEN CAST({part.format(c='src')} AS INTEGER) <> CAST({part.format(c='dst')} AS INTEGER) THEN 1 ELSE 0 END) AS BIGINT) AS cut, count(DISTINCT src) AS sources FROM ({edges}) q GROUP BY 1"


query("partition_stats_mod", _stats_sql(TRADE, "{c} % 8"))(lambda s, d: pt.partition_stats(pt.assign(graph(s, d, "trade"), 8, "mod")))
query("partition_stats_block", f"WITH t AS MATERIALIZED ({TRADE}), m AS (SELECT max(greatest(src, dst)) + 1 AS m FROM t), o AS (SELECT src, dst, CAST(floor(src * 8 / CAST(m AS DOUBLE)) AS INTEGER) AS part, CAST(floor(dst * 8 / CAST(m AS DOUBLE)) AS INTEGER) AS far FROM t, m) SELECT part, count(*) AS edges, CAST(sum((part <> far)::INT) AS BIGINT) AS cut, count(DISTINCT src) AS sources FROM o GROUP BY part")(
    lambda s, d: pt.partition_stats(pt.assign(graph(s, d, "trade"), 8, "block"))
)


@query("partition_stats_by_user", f"SELECT CAST(user_id % 8 AS INTEGER) AS part, count(*) AS edges, CAST(0 AS BIGINT) AS cut, count(DISTINCT src) AS sources FROM ({EVENT_CHAIN}) q JOIN events ON event_id = src GROUP BY 1")
def partition_stats_by_user(spark, d):
    owners = tables.read_table(spark, d, "events").select(F.col("event_id").alias("id"), F.pmod("user_id", F.lit(8)).cast("int").alias("part"))
    return pt.partition_stats(pt.assign(graph(spark, d, "event_chain"), 8, owners=owners))


@query("partition_skew")
def partition_skew(spark, d):
    """Skew and cut of every ownership scheme on the hub-heavy graph."""
    g = graph(spark, d, "trade")
    out = None
    placed = {s: pt.assign(g, 8, s) for s in ("block", "mod", "hash", "range")}
    placed |= {"degree_balanced": pt.assign(g, 8, owners=pt.degree_balanced(g, 8)), "bfs_grown": pt.assign(g, 8, owners=pt.bfs_grown(al.bfs_levels(g, 0), 8))}
    for name, p in placed.items():
        row = pt.skew(p).select(F.lit(name).alias("scheme"), F.round("skew", 4).alias("skew"), F.round("cut_fraction", 4).alias("cut_fraction"))
        out = row if out is None else out.unionByName(row)
    return out




_CURVE = f"""
    WITH RECURSIVE e AS MATERIALIZED ({TRADE}), r(k, v, d, c) AS (
        SELECT 0::BIGINT, 0::BIGINT, 0::BIGINT, true
        UNION ALL
        SELECT k + 1, v, min(d), min(d) FILTER (old) IS NULL OR min(d) < min(d) FILTER (old)
        FROM (SELECT k, v, d, true AS old FROM r WHERE k < 40 UNION ALL SELECT k, e.dst, r.d + e.w, false FROM r JOIN e ON r.v = e.src WHERE r.c AND k < 40) q GROUP BY k, v),
    n AS (SELECT k, count(*) FILTER (c) AS accepted FROM r WHERE k > 0 GROUP BY k)
    SELECT k AS round, accepted FROM n WHERE k <= (SELECT min(k) FROM n WHERE accepted = 0)"""


@query("update_curve", _CURVE)
def update_curve(spark, d):
    """Vertices improved in each round of shortest paths without early updates."""
    return metrics.update_curve(al.sssp(graph(spark, d, "trade"), 0, mode="plain"))


@query("update_curve_shape")
def update_curve_shape(spark, d):
    """Cold start, tail and steepest rise of the curve, on the hub-heavy and on the lattice graph."""
    out = None
    for name in ("trade", "grid"):
        row = metrics.curve_shape(metrics.update_curve(al.sssp(graph(spark, d, name), 0, mode="plain"))).withColumn("graph", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


@query("sssp_costs")
def sssp_costs(spark, d):
    """Rounds, messages, bytes and modelled locks of each mode on the hub-heavy graph."""
    g = graph(spark, d, "trade")
    placed = packed.pack(g, 8, "block", weight="w")
    out = None
    for mode in ("uncombined", "plain", "short_circuit", "pulse"):
        row = metrics.cost_table(al.sssp(g, 0, mode=mode, placed=placed), placed).withColumn("mode", F.lit(mode))
        out = row if out is None else out.unionByName(row)
    return out


@query("counters_cube")
def counters_cube(spark, d):
    """Counters of two modes on two graphs, totalled by every subset of algorithm, mode and graph."""
    out = None
    for name in ("trade", "user_hop"):
        g = graph(spark, d, name)
        placed = packed.pack(g, None, weight="w", check=True)
        for mode in ("plain", "pulse"):
            c = al.sssp(g, 0, mode=mode, placed=placed).counters(algo="sssp", mode=mode, graph=name).where("name = 'generated'")
            out = c if out is None else out.unionByName(c)
    return metrics.counters_cube(out)


_RACES = (("click", "view"), ("click", "purchase"), ("view", "purchase"), ("signup", "error"))
_RUNS = "SELECT event_type AS system, CASE WHEN extract(day FROM ts) <= 15 THEN 1 ELSE 2 END AS setup, user_id AS graph, CAST(sum(round(value * 100)) AS DOUBLE) AS s FROM events WHERE value IS NOT NULL GROUP BY 1, 2, 3"


@query("speedup_table", f"WITH c AS ({_RUNS}), p(ours, other) AS (VALUES {', '.join(str(r) for r in _RACES)}) SELECT 'value' AS algo, CAST(a.setup AS INTEGER) AS setup, ours, other, round(avg(b.s) / avg(a.s), 4) AS speedup, CAST(sum((a.s < b.s)::INT) AS BIGINT) AS wins, count(*) AS graphs FROM p JOIN c a ON a.system = ours JOIN c b ON b.system = other AND b.setup = a.setup AND b.graph = a.graph GROUP BY a.setup, ours, other")
def speedup_table(spark, d):
    """How much less one kind of event takes than another, by user and half of the month: kinds are systems, users graphs."""
    e = tables.read_table(spark, d, "events").where("value IS NOT NULL")
    half = F.when(F.dayofmonth("ts") <= 15, 1).otherwise(2).alias("setup")
    t = e.groupBy(F.lit("value").alias("algo"), F.col("event_type").alias("system"), half, F.col("user_id").alias("graph")).agg(F.sum(F.round(F.col("value") * 100)).alias("seconds"))
    out = None
    for a, b in _RACES:
        row = metrics.speedup(t, a, b).select("algo", "setup", F.lit(a).alias("ours"), F.lit(b).alias("other"), F.round("speedup", 4).alias("speedup"), "wins", "graphs")
        out = row if out is None else out.unionByName(row)
    return out


@query("ablation")
def ablation(spark, d):
    """One program under every step of the option ladder: mode, rounds and mailbox rows; answers agree."""
    g = graph(spark, d, "user_hop")
    ladder = [("predecessor", rewrite.PREDECESSOR), ("combine", CompileOptions(pulse=False, short_circuit=False)), ("short_circuit", CompileOptions(pulse=False)), ("bounded", CompileOptions(max_local_rounds=2)), ("pulse", CompileOptions())]
    rows = []
    for name, options in ladder:
        plan = lower.compile(ir.sssp_program(), g, options)
        r = plan.run()
        total = r.df.agg(F.sum("val")).first()[0]
        rows.append((name, plan.mode, len(r.rounds), r.total("generated"), r.total("queued"), total))
    return spark.createDataFrame(rows, "options string, mode string, rounds long, generated long, queued long, checksum long")


# preparation -----------------------------------------------------------------------------------

query("degrees", f"SELECT id, CAST(sum(o) AS BIGINT) AS out_degree, CAST(sum(i) AS BIGINT) AS in_degree FROM (SELECT src AS id, 1 AS o, 0 AS i FROM ({CUST_SUPP}) a UNION ALL SELECT dst, 0, 1 FROM ({CUST_SUPP}) b) t GROUP BY id")(lambda s, d: gr.degrees(graph(s, d, "cust_supp")))
query("dangling", f"SELECT DISTINCT dst AS id FROM ({CUST_SUPP}) a WHERE dst NOT IN (SELECT src FROM ({CUST_SUPP}) b)")(lambda s, d: gr.dangling(graph(s, d, "cust_supp")))
query("hubs_topk", f"SELECT src AS id, count(*) AS out_degree, count(*) AS in_degree FROM ({TRADE}) q GROUP BY src ORDER BY out_degree DESC, id LIMIT 10")(lambda s, d: gr.hubs(graph(s, d, "trade"), 10))
query("symmetrize", both_ways(CUST_SUPP))(lambda s, d: gr.symmetrize(graph(s, d, "cust_supp")).edges)
query("simplify", "SELECT l_partkey AS src, l_suppkey AS dst, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS w FROM lineitem GROUP BY 1, 2")(
    lambda s, d: gr.simplify(gr.from_edges(tables.read_table(s, d, "lineitem").withColumn("q", F.col("l_quantity").cast("long")), "l_partkey", "l_suppkey", w="q"), "sum").edges
)
query("reverse", f"SELECT dst AS src, src AS dst, w FROM ({CUST_SUPP}) q")(lambda s, d: gr.reverse(graph(s, d, "cust_supp")).edges)
query("induced", f"SELECT src, dst, w FROM ({USER_HOP}) q WHERE src < 50 AND dst < 50")(lambda s, d: gr.induced(graph(s, d, "user_hop"), s.range(50)).edges)
query("validate", f"SELECT count(*) AS edges, 0::BIGINT AS null_ends, 0::BIGINT AS null_weights, 0::BIGINT AS negative_weights, 0::BIGINT AS loops, 0::BIGINT AS parallel FROM ({TRADE}) q")(lambda s, d: gr.validate(graph(s, d, "trade"), "w"))
query("compare_edge_sets", f"WITH a AS (SELECT src, dst FROM ({USER_HOP}) q), b AS (SELECT dst AS src, src AS dst FROM a) SELECT 'both' AS side, count(*) AS pairs FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'first', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'second', count(*) FROM (SELECT * FROM b EXCEPT SELECT * FROM a)")(
    lambda s, d: (lambda g: gr.compare_edge_sets(g, gr.reverse(g)))(graph(s, d, "user_hop"))
)
query("triangles", f"WITH p AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM ({USER_HOP}) q) SELECT count(*) AS triangles FROM p x JOIN p y ON x.b = y.a JOIN p z ON z.a = x.a AND z.b = y.b")(lambda s, d: al.triangles(graph(s, d, "user_hop")))
query("two_hop", f"WITH e AS ({USER_HOP}) SELECT x.src AS id, count(*) AS walks FROM e x JOIN e y ON x.dst = y.src GROUP BY x.src")(lambda s, d: al.two_hop(graph(s, d, "user_hop")))
query("match_path3", f"WITH e AS ({USER_HOP}), t AS (SELECT src AS id, count(*) AS n FROM e GROUP BY src), u AS (SELECT e.src AS id, sum(n) AS n FROM e JOIN t ON e.dst = t.id GROUP BY e.src) SELECT e.src AS id, CAST(sum(n) AS BIGINT) AS walks FROM e JOIN u ON e.dst = u.id GROUP BY e.src")(
    lambda s, d: al.match_path(graph(s, d, "user_hop"), 3)
)
query("page_links", r"""WITH l AS (SELECT DISTINCT 'p' || page_id AS a, b FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS b FROM pages) q), n AS (SELECT a AS name FROM l UNION SELECT b FROM l),
    i AS (SELECT name, row_number() OVER (ORDER BY substr(md5(name), 1, 2), name) - 1 AS id FROM n) SELECT x.id AS src, y.id AS dst FROM l JOIN i x ON x.name = a JOIN i y ON y.name = b""")(lambda s, d: tables.page_links(s, d)[0].edges)
for _name in ("trade", "cust_supp", "user_hop", "event_chain", "order_chain", "org_tree", "turn_chain", "grid", "doc_share"):
    query(f"edges_{_name}", edge_sql(_name))(lambda s, d, n=_name: graph(s, d, n).edges)
query("embed_sim", "WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings) SELECT a.vec_id AS src, b.vec_id AS dst, CAST(1 AS BIGINT) AS w FROM e a JOIN e b ON a.vec_id <> b.vec_id AND list_cosine_similarity(a.v, b.v) >= 0.4")(lambda s, d: tables.similar_embeddings(s, d).edges)


def _rmat(spark, d, edge_factor: int):
    """A recursive-matrix graph with an edge for every event."""
    numbers = tables.read_table(spark, d, "events").select(F.col("event_id").alias("id"))
    return generate.rmat(spark, generate.scale_of(numbers.count(), edge_factor), edge_factor, numbers=numbers)


@query("uniform_edges")
def uniform_edges(spark, d):
    """A uniform graph with an edge for every order, eight to a vertex."""
    numbers = tables.read_table(spark, d, "orders").select(F.col("o_orderkey").alias("id"))
    n = numbers.count()
    return generate.uniform(spark, max(1, n // 8), n, numbers=numbers).edges


query("rmat_edges")(lambda s, d: _rmat(s, d, 8).edges)
query("connected_rmat", "SELECT CAST(count(*) > 0 AS BIGINT) AS components FROM events")(lambda s, d: connected_components(gr.connect(_rmat(s, d, 2)).edges).agg(F.count_distinct("component").alias("components")))
query("random_weights")(lambda s, d: gr.random_weights(graph(s, d, "user_hop"), 1, 100, 3, "r").edges)

query("global_reduce", f"SELECT CAST(sum(w) AS BIGINT) AS value FROM ({TRADE}) q")(lambda s, d: al.global_reduce(graph(s, d, "trade").edges, "w", "sum"))
query("weights_by_search", f"SELECT src AS id, CAST(sum(w) AS BIGINT) AS total FROM ({CUST_SUPP}) q GROUP BY src")(lambda s, d: al.weights_by_search(graph(s, d, "cust_supp")))
query("weights_by_iteration", f"SELECT src AS id, CAST(sum(w) AS BIGINT) AS total FROM ({CUST_SUPP}) q GROUP BY src")(lambda s, d: al.weights_by_iteration(graph(s, d, "cust_supp")))
query("edge_of", f"SELECT src, dst, w FROM ({USER_HOP}) q WHERE dst = (src + 1) % 150")(lambda s, d: (lambda g: al.edge_of(g, g.ids().select(F.col("id").alias("src"), ((F.col("id") + 1) % 150).alias("dst"))))(graph(s, d, "user_hop")))
query("match_diamond", f"WITH e AS MATERIALIZED ({USER_HOP}) SELECT p.src AS id, count(*) AS matches FROM e p JOIN e q ON q.src = p.src AND p.dst < q.dst JOIN e r ON r.src = p.dst JOIN e s ON s.src = q.dst AND s.dst = r.dst WHERE r.dst <> p.src AND r.dst <> q.dst AND r.dst <> p.dst GROUP BY p.src")(
    lambda s, d: al.diamonds(graph(s, d, "user_hop"))
)
query("within_hour", "SELECT x.user_id AS src, y.user_id AS dst, count(*) AS n FROM events x JOIN events y ON y.ts > x.ts AND y.ts <= x.ts + INTERVAL '3600' SECOND AND x.user_id <> y.user_id GROUP BY 1, 2")(lambda s, d: tables.within(s, d, 3600))


@query("latest_before", "SELECT o_orderkey AS id, o_custkey AS user_id, max(event_id) FILTER (ts = top) AS event_id FROM (SELECT o_orderkey, o_custkey, event_id, ts, max(ts) OVER (PARTITION BY o_orderkey) AS top FROM orders LEFT JOIN events ON user_id = o_custkey AND ts <= o_orderdate) q GROUP BY 1, 2")
def latest_before(spark, d):
    """As-of join: each order with the last event before it of the user that has the customer's number."""
    orders = tables.read_table(spark, d, "orders").select(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("ts"), F.col("o_orderkey").alias("id"))
    return tables.latest_before(orders, tables.read_table(spark, d, "events").select("user_id", "ts", "event_id"), "user_id", "ts", "event_id")


query("degree_quantiles", f"SELECT CAST(quantile_cont(n, 0.5) AS DOUBLE) AS p50, CAST(quantile_cont(n, 0.9) AS DOUBLE) AS p90, CAST(quantile_cont(n, 0.99) AS DOUBLE) AS p99 FROM (SELECT count(*) AS n FROM ({CUST_SUPP}) q GROUP BY src) t")(
    lambda s, d: gr.degrees(graph(s, d, "cust_supp")).where("out_degree > 0").agg(*[F.percentile("out_degree", F.lit(p)).alias(f"p{round(100 * p)}") for p in (0.5, 0.9, 0.99)])
)
query("vertices_sketch", f"SELECT count(DISTINCT src) AS exact, true AS close FROM ({EVENT_CHAIN}) q")(
    lambda s, d: graph(s, d, "event_chain").edges.agg(F.count_distinct("src").alias("exact"), F.hll_sketch_estimate(F.hll_sketch_agg("src", F.lit(12))).alias("about")).select("exact", (F.abs(F.col("about") - F.col("exact")) <= 0.05 * F.col("exact")).alias("close"))
)
query("page_hosts", "SELECT regexp_extract(url, '://([^/?#:]+)', 1) AS host, count(*) AS pages FROM pages GROUP BY 1")(lambda s, d: tables.read_table(s, d, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count(F.lit(1)).alias("pages")))
query("event_props", "SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS k, count(DISTINCT CAST(json_extract(props, '$.k') AS BIGINT)) AS kinds FROM events GROUP BY 1")(
    lambda s, d: tables.read_table(s, d, "events").select("event_type", F.from_json("props", "k long").alias("p")).groupBy("event_type").agg(F.sum("p.k").alias("k"), F.count_distinct("p.k").alias("kinds"))
)


# streams ---------------------------------------------------------------------------------------

query("stream_activity", "SELECT time_bucket(INTERVAL '1 day', ts, TIMESTAMP '1970-01-01') AS start, user_id, count(*) AS n FROM events GROUP BY 1, 2")(
    lambda s, d: incremental.drained(incremental.event_stream(s, d).groupBy(F.window("ts", "1 day"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "user_id", "n"), "complete")
)
query("stream_edges", f"SELECT src, dst FROM ({EVENT_CHAIN}) q")(lambda s, d: incremental.drained(incremental.last_seen_edges(incremental.event_stream(s, d).select("event_id", "ts", "user_id"))))


@query("stream_labels", "SELECT event_id AS id, min(event_id) OVER (PARTITION BY user_id) AS component FROM events WHERE user_id IN (SELECT user_id FROM events GROUP BY user_id HAVING count(*) > 1)")
def stream_labels(spark, d):
    """Labels kept up to date by edge insertions equal the components of all edges."""
    from redgraph.session import staged

    e = staged(graph(spark, d, "event_chain").edges.select("src", "dst").repartition(3), "stream-source")
    path = e.inputFiles()[0].rsplit("/", 1)[0]
    return incremental.incremental_labels(spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(path))
