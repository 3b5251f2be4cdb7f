"""Graphs on the given tables, each as ``edges(src, dst, w)`` of longs.

Two kinds of keys in one graph are told apart by ``2 k`` and ``2 k + 1``; five kinds by ``8 k + kind``.
Only the columns named are read.  Every builder has the same graph as a DuckDB query in ``SQL``.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from redgraph.operators.graph import PropertyGraph, encode_ids
from redgraph.operators.packed import _narrow, _wide
from redgraph.session import staged, task_count

#: Users and events of a block, and event pairs handled at once when pairs within a time are counted.
_USERS, _EVENTS, _PAIRS = 4096, 1 << 22, 1 << 21


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Builders as SQL that Spark and DuckDB read alike.
SQL = {
    "trade": """
        WITH p AS (SELECT 2 * l_partkey AS a, 2 * l_suppkey + 1 AS b, CAST(min(l_quantity) AS BIGINT) AS w FROM lineitem GROUP BY l_partkey, l_suppkey)
        SELECT a AS src, b AS dst, w FROM p UNION ALL SELECT b AS src, a AS dst, w FROM p""",
    "cust_supp": """
        SELECT 2 * o_custkey AS src, 2 * l_suppkey + 1 AS dst, CAST(min(l_quantity) AS BIGINT) AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey, l_suppkey""",
    "user_hop": """
        SELECT user_id AS src, nxt AS dst, CAST(min(round(value * 100)) AS BIGINT) + 1 AS w
        FROM (SELECT user_id, value, lead(user_id) OVER (PARTITION BY 1 ORDER BY ts, event_id) AS nxt FROM events) q WHERE nxt IS NOT NULL AND nxt <> user_id GROUP BY user_id, nxt""",
    "order_chain": """
        SELECT o_orderkey AS src, nxt AS dst, CAST({days} AS BIGINT) + 1 AS w
        FROM (SELECT o_orderkey, o_orderdate, lead(o_orderkey) OVER k AS nxt, lead(o_orderdate) OVER k AS nd FROM orders WINDOW k AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)) q WHERE nxt IS NOT NULL""",
    "event_chain": """
        SELECT event_id AS src, nxt AS dst, CAST({micros} AS BIGINT) AS w
        FROM (SELECT event_id, ts, lead(event_id) OVER k AS nxt, lead(ts) OVER k AS nt FROM events WINDOW k AS (PARTITION BY user_id ORDER BY ts, event_id)) q WHERE nxt IS NOT NULL""",
    "org_tree": """
        SELECT CAST(8 * n_regionkey AS BIGINT) AS src, CAST(8 * n_nationkey + 1 AS BIGINT) AS dst, CAST(1 AS BIGINT) AS w FROM nation
        UNION ALL SELECT CAST(8 * c_nationkey + 1 AS BIGINT), 8 * c_custkey + 2, CAST(1 AS BIGINT) FROM customer
        UNION ALL SELECT CAST(8 * s_nationkey + 1 AS BIGINT), 8 * s_suppkey + 3, CAST(1 AS BIGINT) FROM supplier
        UNION ALL SELECT 8 * o_custkey + 2, 8 * o_orderkey + 4, CAST(1 AS BIGINT) FROM orders""",
    "turn_chain": """
        SELECT 1000 * conv_id + turn AS src, nxt AS dst, CAST(1 AS BIGINT) AS w
        FROM (SELECT conv_id, turn, lead(1000 * conv_id + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) q WHERE nxt IS NOT NULL""",
    "grid": """
        WITH c AS (SELECT c_custkey AS k, CAST(round(c_acctbal * 100) AS BIGINT) AS m FROM customer {where}),
        p AS (SELECT x.k AS a, y.k AS b, 1 + abs(x.m + y.m) % 100 AS w FROM c x JOIN c y ON y.k = x.k + 1 WHERE (x.k + 1) % {width} <> 0
              UNION ALL SELECT x.k, y.k, 1 + abs(x.m + y.m) % 100 FROM c x JOIN c y ON y.k = x.k + {width})
        SELECT a AS src, b AS dst, w FROM p UNION ALL SELECT b AS src, a AS dst, w FROM p""",
    "doc_share": r"""
        WITH l AS (SELECT DISTINCT doc_id, {trim} AS line FROM (SELECT doc_id, {unnest} AS line FROM documents) q WHERE length({trim}) >= 20),
        f AS (SELECT line, min(doc_id) AS first FROM l GROUP BY line)
        SELECT DISTINCT doc_id AS src, first AS dst, CAST(1 AS BIGINT) AS w FROM l JOIN f ON l.line = f.line WHERE doc_id <> first""",
}

_SPARK = {"days": "datediff(nd, o_orderdate)", "micros": "cast(cast(nt - ts as interval second) as decimal(18, 6)) * 1000000", "trim": "trim(line)", "unnest": "explode(split(text, '\\n'))"}
_DUCK = {"days": "date_diff('day', o_orderdate, nd)", "micros": "date_diff('microsecond', ts, nt)", "trim": "trim(line)", "unnest": "unnest(string_split(text, chr(10)))"}


def edge_sql(name: str, duck: bool = True, *, width: int = 30, first: int | None = None) -> str:
    words = (_DUCK if duck else _SPARK) | {"width": str(width), "where": f"WHERE c_custkey < {first}" if first else ""}
    text = SQL[name]
    for k, v in words.items():
        text = text.replace("{" + k + "}", v)
    return text


def followed(rows: DataFrame, by: list[str], value: str, name: str) -> DataFrame:
    """``rows`` with ``name``: the ``value`` of the next row of the whole order ``by``.

    The order is cut into ranges, one per task; each finds the next row inside, and the last row of a
    range takes the first one of the next range that has rows.  That table has one row per task.
    """
    spark = rows.sparkSession
    parts = staged(rows.repartitionByRange(task_count(spark), *by).withColumn("__part", F.spark_partition_id()), "order-ranges")
    firsts = parts.groupBy("__part").agg(F.min_by(value, F.struct(*by)).alias("__first"))
    after = firsts.select("__part", F.lead("__first").over(Window.orderBy("__part")).alias("__after"))  # one row per task
    inside = parts.withColumn(name, F.lead(value).over(Window.partitionBy("__part").orderBy(*by)))
    return inside.join(F.broadcast(after), "__part").withColumn(name, F.coalesce(name, "__after")).drop("__part", "__after")


def hops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The edges of ``user_hop`` without a sort in one task."""
    events = followed(read_table(spark, sf_dir, "events").select("user_id", "value", "ts", "event_id"), ["ts", "event_id"], "user_id", "nxt")
    kept = events.where("nxt IS NOT NULL AND nxt <> user_id")
    return kept.groupBy(F.col("user_id").alias("src"), F.col("nxt").alias("dst")).agg((F.min(F.round(F.col("value") * 100)).cast("long") + 1).alias("w"))


def within(spark: SparkSession, sf_dir: str, seconds: int) -> DataFrame:
    """Interval join: users whose event follows another user's by at most ``seconds``, and how often: ``src, dst, n``.

    Pairs of events are counted, never listed: users are dealt into blocks of about ``_USERS``, and all events of one
    block, packed and in the order of time, meet those of another in one task.  There the counts of a slice of pairs
    go into a table of users by users, so a pair of users is counted in one place and no count is exchanged.
    """
    import numpy as np

    reach = seconds * 1_000_000
    e = read_table(spark, sf_dir, "events").select("user_id", F.expr("cast(cast(cast(ts - timestamp_ntz '1970-01-01 00:00:00' as interval second) as decimal(18, 6)) * 1000000 as long)").alias("t")).where("user_id IS NOT NULL AND t IS NOT NULL")
    users, rows = e.agg(F.count_distinct("user_id"), F.count(F.lit(1))).first()
    if not rows:
        return e.select(F.col("user_id").alias("src"), F.col("user_id").alias("dst"), F.lit(1).cast("long").alias("n"))
    # two cells for each task at least, as far as there are users
    blocks = max(-(-users // _USERS), -(-rows // _EVENTS), min(users, math.ceil(math.sqrt(2 * task_count(spark)))))

    def packed(block: pa.Table) -> pa.Table:
        who, t = (block.column(c).to_numpy() for c in ("user_id", "t"))
        order = np.argsort(t, kind="stable")
        ids, who = np.unique(who[order], return_inverse=True)
        t = t[order]
        cells = [block.column("b")[0].as_py(), len(t), ids.astype(np.int64).tobytes(), _narrow(who), int(t[0]), _narrow(np.diff(t, prepend=t[0]))]
        return pa.table({f: pa.array([c], k) for f, c, k in zip(("b", "n", "ids", "who", "first", "gaps"), cells, (pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.int64(), pa.binary()), strict=True)})

    def unpacked(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        who, gaps = (_wide(pa.scalar(row[c], pa.binary()), row["n"]) for c in ("who", "gaps"))
        return np.frombuffer(row["ids"], np.int64), who.astype(np.int64), row["first"] + np.cumsum(gaps, dtype=np.int64)

    def count(met: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sides = {row["early"]: unpacked(row) for batch in met for row in batch.to_pylist()}
        if len(sides) < 2:  # no user hashes to one of the blocks
            return
        (a, ia, ta), (b, ib, tb) = sides[True], sides[False]
        low, high = np.searchsorted(tb, ta, side="right"), np.searchsorted(tb, ta + reach, side="right")
        table = np.zeros(len(a) * len(b), np.int64)
        many = high - low
        done = np.concatenate([[0], np.cumsum(many)])
        # one early event after another group of them, each group with a bounded number of pairs
        at = 0
        while at < len(ta):
            to = max(at + 1, int(np.searchsorted(done, done[at] + _PAIRS, side="right")) - 1)
            for p in range(int(low[at]), int(high[at]), _PAIRS) if to == at + 1 else [None]:
                if p is None:
                    n = many[at:to]
                    j = np.arange(done[to] - done[at]) - np.repeat(done[at:to] - done[at] - low[at:to], n)
                    slot = np.repeat(ia[at:to] * len(b), n) + ib[j]
                else:
                    slot = ia[at] * len(b) + ib[p : min(p + _PAIRS, int(high[at]))]
                np.add.at(table, slot, 1)
            at = to
        for p in range(0, len(table), _PAIRS):
            hit = np.flatnonzero(table[p : p + _PAIRS]) + p
            src, dst = a[hit // len(b)], b[hit % len(b)]
            keep = src != dst
            if keep.any():
                yield pa.RecordBatch.from_arrays([pa.array(c[keep]) for c in (src, dst, table[hit])], names=["src", "dst", "n"])

    own = F.pmod(F.xxhash64("user_id"), F.lit(blocks)).cast("int")
    packs = staged(e.withColumn("b", own).groupBy("b").applyInArrow(packed, "b int, n long, ids binary, who binary, first long, gaps binary"), "events-packed")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    rest = [c for c in packs.columns if c != "b"]
    early = packs.select(F.col("b").alias("x"), every.alias("y"), F.lit(True).alias("early"), *rest)
    late = packs.select(every.alias("x"), F.col("b").alias("y"), F.lit(False).alias("early"), *rest)
    cells = early.unionByName(late).repartition(task_count(spark), "x", "y")
    return cells.groupBy("x", "y").applyInArrow(count, "src long, dst long, n long")


def latest_before(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """As-of join: rows ``key, time, id`` of ``left`` with the ``value`` of the last row of ``right`` at or before that time.

    Both sides are put in one order per key; equal times count as before, of equal ones the largest value.
    """
    both = right.select(key, time, F.lit(0).alias("__side"), F.col(value).alias("__seen"), F.lit(None).cast("long").alias("id")).unionByName(left.select(key, time, F.lit(1).alias("__side"), F.lit(None).cast(dict(right.dtypes)[value]).alias("__seen"), "id"))
    order = Window.partitionBy(key).orderBy(time, "__side", "__seen").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last("__seen", ignorenulls=True).over(order)).where("__side = 1").select("id", key, value)


def graph(spark: SparkSession, sf_dir: str, name: str, **options) -> PropertyGraph:
    """A graph of ``SQL`` by name; ``grid`` takes ``width`` and ``first`` (only smaller customer keys)."""
    if name == "user_hop":
        return PropertyGraph(hops(spark, sf_dir), meta={"name": name})
    text = edge_sql(name, duck=False, **options)
    for table in ("lineitem", "orders", "events", "customer", "supplier", "nation", "conversations", "documents"):
        if table in text:
            read_table(spark, sf_dir, table).createOrReplaceTempView(f"redgraph_{table}")
            for lead in ("FROM ", "JOIN "):
                text = text.replace(f"{lead}{table}", f"{lead}redgraph_{table}")
    return PropertyGraph(spark.sql(text), directed=name not in ("trade", "grid"), meta={"name": name})


def page_links(spark: SparkSession, sf_dir: str) -> tuple[PropertyGraph, DataFrame]:
    """Pages to the distinct paths that they link, from string ids; returns the dictionary of ids too."""
    read_table(spark, sf_dir, "pages").createOrReplaceTempView("redgraph_pages")
    pairs = spark.sql(r"""SELECT DISTINCT concat('p', page_id) AS a, b FROM (SELECT page_id, explode(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS b FROM redgraph_pages)""")
    edges, names = encode_ids(pairs, "a", "b")
    return PropertyGraph(edges, meta={"name": "page_link"}), names


def similar_embeddings(spark: SparkSession, sf_dir: str, least: float = 0.4, per_block: int = 256) -> PropertyGraph:
    """Pairs of vectors with a cosine of at least ``least``, both ways.

    All pairs are asked for, so the work is quadratic in the vectors (2,000 at sf0.1): meant for tables of
    up to some hundred thousand.  Blocks of vectors meet blocks: each pair of blocks is one matrix product
    in one task, and only its entries above the bound leave it.
    """
    import numpy as np
    import pandas as pd

    rows = read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    n = rows.count()
    blocks = max(1, -(-n // per_block))
    rows = rows.withColumn("b", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    to = F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda k: F.struct(F.least("b", k).alias("x"), F.greatest("b", k).alias("y")))
    cells = rows.withColumn("cell", F.explode(F.array_distinct(to)))

    def products(key, part: pd.DataFrame) -> pd.DataFrame:
        m = np.stack(part["v"].to_numpy())
        m = m / np.sqrt((m * m).sum(axis=1, keepdims=True))
        side, ids = part["b"].to_numpy(), part["id"].to_numpy()
        left, right = np.flatnonzero(side == key[0]), np.flatnonzero(side == key[1])
        i, j = np.nonzero(m[left] @ m[right].T >= least)
        a, b = ids[left[i]], ids[right[j]]
        keep = a < b if key[0] == key[1] else np.ones(len(a), bool)
        return pd.DataFrame({"src": np.concatenate([a[keep], b[keep]]), "dst": np.concatenate([b[keep], a[keep]])})

    edges = cells.groupBy("cell.x", "cell.y").applyInPandas(products, "src long, dst long")
    return PropertyGraph(edges.withColumn("w", F.lit(1).cast("long")), directed=False, meta={"name": "embed_sim"})
