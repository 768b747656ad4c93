"""Relational operators that users need around graphs, each with its SQL."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellgraph import fixtures, oracles
from cellgraph.scratch import Scratch
from cellgraph.streaming.edges import components_of_stream, drain, event_stream, sessions, succession, windowed_degree

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def _q(name: str, sql: str | None):
    def keep(f):
        QUERIES[name] = lambda s, d: f(lambda t: s.read.parquet(f"{d}/{t}.parquet"))
        if sql:
            SQL[name] = sql
        return f

    return keep


def _g(name: str, sql: str | None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


@_q("scan_lineitem_pruned", "SELECT l_orderkey, l_suppkey FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'")
def _(t):
    return t("lineitem").where("l_quantity > 45 and l_returnflag = 'R'").select("l_orderkey", "l_suppkey")


@_q("edge_projection", "SELECT l_orderkey * 10 AS src, l_suppkey * 10 + 1 AS dst, l_quantity AS weight FROM lineitem")
def _(t):
    return t("lineitem").select((F.col("l_orderkey") * 10).alias("src"), (F.col("l_suppkey") * 10 + 1).alias("dst"), F.col("l_quantity").alias("weight"))


@_q("join_broadcast", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def _(t):  # nation has 25 rows at every scale
    return t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


for _kind in ("merge", "shuffle_hash"):

    @_q(f"join_{_kind}", "SELECT o_custkey, l_suppkey, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2")
    def _(t, kind=_kind):
        return t("orders").select("o_orderkey", "o_custkey").hint(kind).join(t("lineitem").select("l_orderkey", "l_suppkey"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey", "l_suppkey").agg(F.count("*").alias("n"))


@_q("join_full", "SELECT coalesce(p_partkey, l_partkey) AS part, count(l_orderkey) AS n FROM part FULL JOIN lineitem ON p_partkey = l_partkey GROUP BY 1")
def _(t):
    lines = t("lineitem").groupBy("l_partkey").agg(F.count("l_orderkey").alias("n"))
    return t("part").join(lines, F.col("p_partkey") == F.col("l_partkey"), "full").select(F.coalesce("p_partkey", "l_partkey").alias("part"), F.coalesce("n", F.lit(0)).alias("n"))


@_g("frontier_semi", f"SELECT DISTINCT e.src FROM ({oracles.arcs('hub_tree')}) e WHERE e.dst IN (5, 6)")
def _(s, d):
    g = fixtures.hub_tree(s, d)
    return g.arcs().join(s.createDataFrame([(5,), (6,)], "dst long"), "dst", "left_semi").select("src").distinct()


@_g("dangling_vertices", f"SELECT vid FROM ({oracles.vertices_sql('user_chain')}) WHERE vid NOT IN (SELECT src FROM ({oracles.arcs('user_chain', True)}))")
def _(s, d):
    g = fixtures.user_chain(s, d, True)
    return g.vertices.join(g.edges.select(F.col("src").alias("vid")), "vid", "left_anti").select("vid")


@_g("induced_subgraph", f"SELECT src, dst FROM ({oracles.arcs('part_flow', True)}) WHERE src <= 200 AND dst <= 200")
def _(s, d):
    return fixtures.part_flow(s, d).filter_vertices("vid <= 200").edges.select("src", "dst")


@_g("two_hop", f"SELECT a.src, count(DISTINCT b.dst) AS n FROM ({oracles.arcs('conv_turns', True)}) a JOIN ({oracles.arcs('conv_turns', True)}) b ON a.dst = b.src GROUP BY a.src")
def _(s, d):
    """Sort-merge, so that adaptive execution can split a hub's paths among tasks."""
    e = fixtures.conv_turns(s, d).edges.select("src", "dst")
    return e.hint("merge").join(e.select(F.col("src").alias("dst"), F.col("dst").alias("far")), "dst").groupBy("src").agg(F.countDistinct("far").alias("n"))


@_g("triangle_count", f"WITH e AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM ({oracles.arcs('part_flow', True)})) SELECT count(*) AS triangles FROM e x JOIN e y ON x.b = y.a JOIN e z ON z.a = x.a AND z.b = y.b")
def _(s, d):
    """Edges point from the end of less degree to that of more, so that no vertex starts more wedges than the square root of twice the edges, hubs included."""
    e = fixtures.part_flow(s, d).edges.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    degree = e.select(F.explode(F.array("a", "b")).alias("v")).groupBy("v").agg(F.count("*").alias("n"))
    end = lambda c: degree.select(F.col("v").alias(c), F.struct("n", "v").alias(f"{c}_order"))
    up = e.join(end("a"), "a").join(end("b"), "b")
    up = up.select(F.least("a_order", "b_order")["v"].alias("low"), F.greatest("a_order", "b_order").alias("high"))
    wedge = up.select("low", F.col("high").alias("x")).join(up.select("low", F.col("high").alias("y")), "low").where("x < y")
    closing = up.select(F.col("low").alias("xv"), F.col("high")["v"].alias("yv"))
    return wedge.select(F.col("x.v").alias("xv"), F.col("y.v").alias("yv")).join(closing, ["xv", "yv"]).agg(F.count("*").alias("triangles"))


@_g("reciprocal_edges", f"SELECT e.src, e.dst FROM ({oracles.arcs('part_flow', True)}) e JOIN ({oracles.arcs('part_flow', True)}) r ON r.src = e.dst AND r.dst = e.src")
def _(s, d):
    e = fixtures.part_flow(s, d).edges.select("src", "dst")
    return e.join(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"])


@_q("interval_edges", "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.event_type = 'purchase' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def _(t):
    """Events within ten minutes: equal or next ten-minute bucket, then the exact test."""
    e = t("events").where("event_type = 'purchase'").select("event_id", "ts").withColumn("bucket", F.floor(fixtures._micros() / 600_000_000))
    left = e.select(F.col("event_id").alias("src"), F.col("ts").alias("t0"), F.explode(F.array("bucket", F.col("bucket") + 1)).alias("bucket"))
    return left.join(e, "bucket").where("ts > t0 and ts <= t0 + interval 10 minutes").select("src", F.col("event_id").alias("dst"))


@_q("asof_edges", "SELECT a.event_id AS src, b.event_id AS dst FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF JOIN (SELECT * FROM events WHERE event_type = 'view') b ON a.user_id = b.user_id AND a.ts >= b.ts")
def _(t):
    """The user's latest view up to each purchase: one window over both, no range join."""
    e = t("events").where("event_type in ('purchase', 'view')")
    w = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") == "purchase", "event_id")
    seen = e.withColumn("dst", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), True).over(w))
    return seen.where("event_type = 'purchase' and dst is not null").select(F.col("event_id").alias("src"), "dst")


_CUT = f"SELECT * FROM ({oracles.placed('order_supplier', '({v} % 4)::INT')}) WHERE src_pid <> dst_pid"


def _cut(s, d):
    pid = lambda c: F.pmod(c, F.lit(4)).cast("int")
    return fixtures.order_supplier(s, d).arcs().select(pid(F.col("src")).alias("src_pid"), pid(F.col("dst")).alias("dst_pid")).where("src_pid <> dst_pid")


@_g("cut_cube", f"SELECT src_pid, dst_pid, count(*) AS n FROM ({_CUT}) GROUP BY CUBE (src_pid, dst_pid)")
def _(s, d):
    return _cut(s, d).cube("src_pid", "dst_pid").agg(F.count("*").alias("n"))


@_g("cut_rollup", f"SELECT src_pid, dst_pid, count(*) AS n FROM ({_CUT}) GROUP BY ROLLUP (src_pid, dst_pid)")
def _(s, d):
    return _cut(s, d).rollup("src_pid", "dst_pid").agg(F.count("*").alias("n"))


@_g("cut_grouping_sets", f"SELECT src_pid, dst_pid, count(*) AS n FROM ({_CUT}) GROUP BY GROUPING SETS ((src_pid), (dst_pid), ())")
def _(s, d):
    return _cut(s, d).groupingSets([["src_pid"], ["dst_pid"], []], "src_pid", "dst_pid").agg(F.count("*").alias("n"))


_WIDE = ", ".join(f"count(*) FILTER (WHERE dst_pid = {p}) AS to{p}" for p in range(4))


def _wide(s, d):
    wide = _cut(s, d).groupBy("src_pid").pivot("dst_pid", [0, 1, 2, 3]).count()
    return wide.select("src_pid", *[F.coalesce(str(p), F.lit(0)).alias(f"to{p}") for p in range(4)])


@_g("cut_pivot", f"SELECT src_pid, {_WIDE} FROM ({_CUT}) GROUP BY src_pid")
def _(s, d):
    return _wide(s, d)


@_g("cut_unpivot", f"SELECT p.src_pid, q.dst_pid, (SELECT count(*) FROM ({_CUT}) c WHERE c.src_pid = p.src_pid AND c.dst_pid = q.dst_pid) AS n FROM (SELECT DISTINCT src_pid FROM ({_CUT})) p, (SELECT 'to' || i AS col, i AS dst_pid FROM (SELECT unnest(range(4))::INT AS i)) q")
def _(s, d):
    return _wide(s, d).unpivot("src_pid", [f"to{p}" for p in range(4)], "col", "n").select("src_pid", F.substring("col", 3, 1).cast("int").alias("dst_pid"), "n")


@_g("adjacency_lists", f"SELECT src AS vid, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS adjacent FROM ({oracles.arcs('conv_turns')}) GROUP BY src")
def _(s, d):
    return fixtures.conv_turns(s, d).arcs().groupBy(F.col("src").alias("vid")).agg(F.array_join(F.transform(F.array_sort(F.collect_list("dst")), lambda x: x.cast("string")), ",").alias("adjacent"))


@_q("topk_per_customer", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def _(t):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t("orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


@_q("moving_gap", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS mean5 FROM events")
def _(t):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return t("events").select("event_id", F.round(F.avg("value").over(w), 6).alias("mean5"))


@_g("top_degrees", f"SELECT src AS vid, count(*) AS degree FROM ({oracles.arcs('hub_tree')}) GROUP BY src ORDER BY degree DESC, vid LIMIT 20")
def _(s, d):
    return fixtures.hub_tree(s, d).degrees().orderBy(F.desc("degree"), "vid").limit(20)


@_q("edge_diff", "SELECT l_orderkey, l_suppkey FROM lineitem WHERE l_returnflag = 'R' EXCEPT SELECT l_orderkey, l_suppkey FROM lineitem WHERE l_returnflag = 'A'")
def _(t):
    pick = lambda f: t("lineitem").where(F.col("l_returnflag") == f).select("l_orderkey", "l_suppkey")
    return pick("R").subtract(pick("A"))


@_q("fn_string_hosts", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages")
def _(t):
    return t("pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))


@_q("fn_array_cosine", "SELECT a.vec_id, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cosine FROM embeddings a, embeddings b WHERE b.vec_id = 0")
def _(t):
    first = F.broadcast(t("embeddings").where("vec_id = 0").select(F.col("embedding").alias("e0")))  # one row
    dot = F.aggregate(F.zip_with("embedding", "e0", lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda x, y: x + y)
    return t("embeddings").join(first).select("vec_id", F.round(dot, 6).alias("cosine"))



@_q("udf_edge_weight", "SELECT event_id, round(ln(1 + abs(value)), 6) AS weight FROM events WHERE value IS NOT NULL")
def _(t):
    @F.pandas_udf("double")
    def weigh(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        import numpy as np

        for v in batches:
            yield np.log1p(v.abs())

    return t("events").where("value is not null").select("event_id", F.round(weigh("value"), 6).alias("weight"))


@_g("component_revenue", f"SELECT component, round(sum(o_totalprice), 2) AS revenue FROM ({oracles.components('hub_tree')}) c JOIN orders ON c.vid = o_orderkey * 10 GROUP BY component")
def _(s, d):
    from cellgraph.algorithms.traversal import components_vertex

    labels = components_vertex(fixtures.hub_tree(s, d))[0]
    orders = s.read.parquet(f"{d}/orders.parquet").select((F.col("o_orderkey") * 10).alias("vid"), "o_totalprice")
    return orders.join(labels, "vid").groupBy("component").agg(F.round(F.sum("o_totalprice"), 2).alias("revenue"))


@_g("stream_tumbling_degree", "SELECT date_trunc('hour', ts) AS start, user_id, count(*) AS n FROM events GROUP BY 1, 2")
def _(s, d):
    return drain(s, windowed_degree(event_stream(s, f"{d}/events.parquet"), "1 hour"), "complete", "tumbling")


_GAPS = "SELECT user_id, ts, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 30 MINUTE, true)::INT AS opens FROM events"


@_g("stream_session_users", f"SELECT min(ts) AS start, user_id, count(*) AS n FROM (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM ({_GAPS})) GROUP BY user_id, session")
def _(s, d):
    return drain(s, sessions(event_stream(s, f"{d}/events.parquet"), "30 minutes"), "complete", "sessions")


@_g("stream_sliding_degree", "SELECT start, user_id, count(*) AS n FROM (SELECT user_id, unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS start FROM events) GROUP BY start, user_id")
def _(s, d):
    return drain(s, windowed_degree(event_stream(s, f"{d}/events.parquet"), "1 hour", "30 minutes"), "complete", "sliding")


@_g("stream_edges", "SELECT user_id * 2 AS src, event_id * 2 + 1 AS dst, value AS weight FROM events WHERE event_type = 'purchase'")
def _(s, d):
    bought = event_stream(s, f"{d}/events.parquet").where("event_type = 'purchase'")
    return drain(s, bought.select((F.col("user_id") * 2).alias("src"), (F.col("event_id") * 2 + 1).alias("dst"), F.col("value").alias("weight")), "append", "edges")


@_g("stream_succession", f"SELECT src, dst FROM ({oracles.arcs('user_chain', True)})")
def _(s, d):
    return drain(s, succession(event_stream(s, f"{d}/events.parquet")), "append", "succession")


@_g("stream_dedup", "SELECT DISTINCT date_trunc('hour', ts) AS hour, user_id, event_type FROM events")
def _(s, d):
    """One row per hour, user and type; state older than the watermark is let go."""
    rows = event_stream(s, f"{d}/events.parquet").select(F.date_trunc("hour", "ts").alias("hour"), "user_id", "event_type")
    once = rows.withWatermark("hour", "2 hours").dropDuplicates(["hour", "user_id", "event_type"])
    return drain(s, once.select(F.col("hour").cast("timestamp_ntz").alias("hour"), "user_id", "event_type"), "append", "dedup")


@_g("stream_join_static", "SELECT e.event_id, c.c_mktsegment FROM events e JOIN customer c ON c.c_custkey = e.user_id")
def _(s, d):
    customers = s.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_mktsegment")
    return drain(s, event_stream(s, f"{d}/events.parquet").join(customers, F.col("c_custkey") == F.col("user_id")).select("event_id", "c_mktsegment"), "append", "static")


@_g("stream_components", f"SELECT v AS vid, lab AS component FROM ({oracles.spread(oracles.arcs('conv_turns'), 'SELECT src AS vid FROM (' + oracles.arcs('conv_turns') + ') UNION SELECT dst FROM (' + oracles.arcs('conv_turns') + ')', False)})")
def _(s, d):
    """Edge files taken in one at a time; labels are the least vertex seen."""
    files = Scratch(s, "stream-edges").save(fixtures.conv_turns(s, d).edges.select("src", "dst").repartition(3, "src"))
    return components_of_stream(s, files._scratch_path).select(F.col("v").alias("vid"), F.col("label").alias("component"))
