"""More relational operators around graphs, scalar functions, user-defined functions and work on results, each with its SQL."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellgraph import fixtures, oracles
from cellgraph.algorithms import ranks, traversal
from cellgraph.operators.relational import _g, _q
from cellgraph.scratch import Scratch
from cellgraph.sources.slices import read_edge_list

_LABELS = oracles.components("conv_turns")


def _labels(s: SparkSession, d: str) -> DataFrame:
    return traversal.components_vertex(fixtures.conv_turns(s, d))[0]


@_g("edge_filter", f"SELECT src, dst, weight FROM ({oracles.arcs('road_hour', True)}) WHERE weight BETWEEN 10 AND 60 AND src % 3 IN (0, 1)")
def _(s, d):
    return fixtures.road_hour(s, d).filter_edges("weight between 10 and 60 and src % 3 in (0, 1)").edges


@_q("scan_nulls_and_patterns", "SELECT event_id FROM events WHERE props IS NOT NULL AND event_type LIKE 'p%'")
def _(t):
    return t("events").where("props is not null and event_type like 'p%'").select("event_id")


@_q("join_right", "SELECT n_nationkey, count(s_suppkey) AS n FROM supplier RIGHT JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")
def _(t):
    return t("supplier").join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey"), "right").groupBy("n_nationkey").agg(F.count("s_suppkey").alias("n"))


@_g("state_update_left", f"SELECT v.vid, coalesce(m.new, v.vid) AS value FROM ({oracles.vertices_sql('part_flow')}) v LEFT JOIN (SELECT dst, max(src) AS new FROM ({oracles.arcs('part_flow', True)}) WHERE src % 5 = 0 GROUP BY dst) m ON m.dst = v.vid")
def _(s, d):
    """One step in which vertices without a message keep their value."""
    g = fixtures.part_flow(s, d)
    sent = g.edges.where("src % 5 = 0").groupBy(F.col("dst").alias("vid")).agg(F.max("src").alias("new"))
    return g.vertices.join(sent, "vid", "left").select("vid", F.coalesce("new", "vid").alias("value"))


@_q("theta_join", "SELECT a.n_nationkey AS src, b.n_nationkey AS dst FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey <= b.n_regionkey")
def _(t):
    """The table of nations has 25 rows at every scale."""
    n = t("nation")
    other = F.broadcast(n.select(F.col("n_nationkey").alias("dst"), F.col("n_regionkey").alias("r")))
    return n.join(other, (F.col("n_nationkey") < F.col("dst")) & (F.col("n_regionkey") <= F.col("r"))).select(F.col("n_nationkey").alias("src"), "dst")


@_g("knn_edges", f"SELECT src, dst FROM ({fixtures.EDGES_SQL['knn']})")
def _(s, d):
    return fixtures.knn(s, d).edges.select("src", "dst")


@_g("component_count", f"SELECT count(DISTINCT component) AS n FROM ({_LABELS})")
def _(s, d):
    return _labels(s, d).agg(F.countDistinct("component").alias("n"))


@_g("approx_components", None)
def _(s, d):
    return _labels(s, d).agg(F.approx_count_distinct("component", 0.02).alias("n"))


@_g("topk_per_component", f"SELECT component, vid, degree FROM (SELECT c.component, c.vid, g.degree, row_number() OVER (PARTITION BY c.component ORDER BY g.degree DESC, c.vid) AS r FROM ({_LABELS}) c JOIN (SELECT src AS vid, count(*) AS degree FROM ({oracles.arcs('conv_turns')}) GROUP BY src) g USING (vid)) WHERE r <= 2")
def _(s, d):
    w = Window.partitionBy("component").orderBy(F.desc("degree"), "vid")
    held = _labels(s, d).join(fixtures.conv_turns(s, d).degrees().where("degree > 0"), "vid")
    return held.withColumn("r", F.row_number().over(w)).where("r <= 2").select("component", "vid", "degree")


_BY_NATION = "OVER (PARTITION BY c_nationkey ORDER BY floor(c_acctbal / 100))"
_ORDERED = "OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)"


@_q("rank_variants", f"SELECT c_custkey, rank() {_BY_NATION} AS r, dense_rank() {_BY_NATION} AS dr, round(percent_rank() {_BY_NATION}, 9) AS pr, round(cume_dist() {_BY_NATION}, 9) AS cd, ntile(4) {_ORDERED} AS quarter FROM customer")
def _(t):
    w = Window.partitionBy("c_nationkey").orderBy(F.floor(F.col("c_acctbal") / 100))
    full = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    return t("customer").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.ntile(4).over(full).alias("quarter"))


_USER = "(PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"


@_q("succession_edges", f"SELECT event_id AS src, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, first_value(event_id) OVER {_USER} AS first, last_value(event_id) OVER {_USER} AS last, nth_value(event_id, 2) OVER {_USER} AS second FROM events")
def _(t):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t("events").select(F.col("event_id").alias("src"), F.lead("event_id").over(w).alias("dst"), F.lag("event_id").over(w).alias("before"), F.first("event_id").over(whole).alias("first"), F.last("event_id").over(whole).alias("last"), F.nth_value("event_id", 2).over(whole).alias("second"))


@_q("running_degree", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def _(t):
    """Events of the user in the last hour, by time and not by rows."""
    e = t("events").withColumn("us", fixtures._micros())
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("n"))


@_q("edge_common", "SELECT l_orderkey, l_suppkey FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_orderkey, l_suppkey FROM lineitem WHERE l_returnflag = 'A'")
def _(t):
    pick = lambda f: t("lineitem").where(F.col("l_returnflag") == f).select("l_orderkey", "l_suppkey")
    return pick("R").intersect(pick("A"))


@_q("edge_diff_all", "SELECT l_suppkey FROM lineitem WHERE l_returnflag = 'N' EXCEPT ALL SELECT l_suppkey FROM lineitem WHERE l_returnflag = 'A'")
def _(t):
    pick = lambda f: t("lineitem").where(F.col("l_returnflag") == f).select("l_suppkey")
    return pick("N").exceptAll(pick("A"))


@_g("symmetrise", f"SELECT DISTINCT src, dst FROM ({oracles.arcs('part_flow')})")
def _(s, d):
    return fixtures.part_flow(s, d).weak().arcs().select("src", "dst").distinct()


@_g("ranked_page", f"SELECT src AS vid, count(*) AS degree FROM ({oracles.arcs('hub_tree')}) GROUP BY src ORDER BY degree DESC, vid LIMIT 10 OFFSET 20")
def _(s, d):
    return fixtures.hub_tree(s, d).degrees().orderBy(F.desc("degree"), "vid").offset(20).limit(10)


@_g("sample_sources", None)
def _(s, d):
    """Sources for sampled measures: a share of the vertices by seed."""
    return fixtures.road_hour(s, d).vertices.sample(0.02, seed=7)


@_q("sample_by_type", None)
def _(t):
    return t("events").sampleBy("event_type", {"purchase": 0.2, "view": 0.01}, seed=3).select("event_id", "event_type")


def _view(df: DataFrame) -> str:
    name = f"v_{uuid.uuid4().hex[:12]}"
    df.createOrReplaceTempView(name)
    return name


@_g("sql_edges", f"SELECT src % 10 AS kind, count(*) AS n, count(DISTINCT dst) AS targets FROM ({oracles.arcs('hub_tree', True)}) GROUP BY 1")
def _(s, d):
    """The edge table by name, in SQL."""
    return s.sql(f"SELECT src % 10 AS kind, count(*) AS n, count(DISTINCT dst) AS targets FROM {_view(fixtures.hub_tree(s, d).edges)} GROUP BY 1")


@_g("sql_subquery", f"WITH g AS (SELECT src, count(*) AS n FROM ({oracles.arcs('part_flow', True)}) GROUP BY src) SELECT src, n FROM g WHERE n > (SELECT avg(n) FROM g) AND EXISTS (SELECT 1 FROM ({oracles.arcs('part_flow', True)}) e WHERE e.dst = g.src)")
def _(s, d):
    e = _view(fixtures.part_flow(s, d).edges)
    return s.sql(f"WITH g AS (SELECT src, count(*) AS n FROM {e} GROUP BY src) SELECT src, n FROM g WHERE n > (SELECT avg(n) FROM g) AND EXISTS (SELECT 1 FROM {e} e WHERE e.dst = g.src)")


_REACH = "WITH RECURSIVE r(src, dst, depth) AS (SELECT src, dst, 1 FROM {e} UNION ALL SELECT r.src, e.dst, r.depth + 1 FROM r JOIN {e} e ON r.dst = e.src) SELECT src, count(*) AS reached, max(depth) AS depth FROM r GROUP BY src"


@_g("sql_recursive_reach", _REACH.format(e=f"({oracles.arcs('conv_turns', True)})"))
def _(s, d):
    """Only for short paths without cycles: recursion in SQL has a depth limit and no test for vertices seen."""
    return s.sql(_REACH.format(e=_view(fixtures.conv_turns(s, d).edges)))


@_q("fn_date_gaps", "SELECT event_id, date_trunc('day', ts) AS day, date_diff('day', DATE '2024-01-01', ts::DATE) AS days, epoch_us(ts) // 1000000 AS seconds FROM events")
def _(t):
    c = F.col("ts")
    return t("events").select("event_id", F.date_trunc("day", c.cast("timestamp_ntz")).cast("timestamp_ntz").alias("day"), F.datediff(F.to_date(c), F.lit("2024-01-01").cast("date")).cast("long").alias("days"), F.floor(fixtures._micros() / 1_000_000).alias("seconds"))


@_q("fn_math_bins", "SELECT p_partkey, floor(log2(p_retailprice))::BIGINT AS bin, least(p_size, 10) AS small, greatest(p_size, 40) AS large, round(sqrt(p_retailprice), 6) AS root, p_partkey % 7 AS rest, abs(p_size - 25) AS off FROM part")
def _(t):
    return t("part").select("p_partkey", F.floor(F.log2("p_retailprice")).alias("bin"), F.least("p_size", F.lit(10)).alias("small"), F.greatest("p_size", F.lit(40)).alias("large"), F.round(F.sqrt("p_retailprice"), 6).alias("root"), F.pmod("p_partkey", F.lit(7)).alias("rest"), F.abs(F.col("p_size") - 25).alias("off"))


@_q("fn_map_attrs", "SELECT p_brand, count(*) FILTER (WHERE p_size < 20) AS small, count(*) FILTER (WHERE p_size >= 20) AS large FROM part GROUP BY p_brand")
def _(t):
    """Sparse attributes as a map, read by key."""
    sizes = t("part").withColumn("kind", F.when(F.col("p_size") < 20, "small").otherwise("large")).groupBy("p_brand", "kind").agg(F.count("*").alias("n"))
    attrs = sizes.groupBy("p_brand").agg(F.map_from_entries(F.collect_list(F.struct("kind", "n"))).alias("m"))
    doubled = F.transform_values("m", lambda _, v: v + 0)
    return attrs.select("p_brand", *[F.coalesce(F.element_at(doubled, k), F.lit(0)).alias(k) for k in ("small", "large")])


@_q("fn_json_props", "SELECT event_id, json_keys(props)[1] AS first_key, len(json_keys(props)) AS n FROM events WHERE props IS NOT NULL")
def _(t):
    keys = F.json_object_keys("props")
    return t("events").where("props is not null").select("event_id", F.get(keys, F.lit(0)).alias("first_key"), F.size(keys).cast("long").alias("n"))


@_g("udaf_weighted_mean_gap", f"SELECT src % 5 AS line, round(sum(weight * (dst - src)) / sum(dst - src), 6) AS gap FROM ({oracles.arcs('road_hour', True)}) GROUP BY 1")
def _(s, d):
    @F.pandas_udf("double")
    def weighted(value: pd.Series, weight: pd.Series) -> float:
        return float((value * weight).sum() / weight.sum())

    e = fixtures.road_hour(s, d).edges
    return e.groupBy((F.col("src") % 5).alias("line")).agg(F.round(weighted(F.col("weight").cast("double"), (F.col("dst") - F.col("src")).cast("double")), 6).alias("gap"))


@_g("udtf_expand_adjacency", f"SELECT src AS vid, dst FROM ({oracles.arcs('conv_turns')})")
def _(s, d):
    """Adjacency lists back to edges, by a table function."""

    @F.udtf(returnType="vid long, dst long")
    class Expand:
        def eval(self, vid: int, adjacent: list):
            for dst in adjacent:
                yield vid, dst

    name = f"expand_{uuid.uuid4().hex[:8]}"
    s.udtf.register(name, Expand)
    lists = _view(fixtures.conv_turns(s, d).arcs().groupBy(F.col("src").alias("vid")).agg(F.collect_list("dst").alias("adjacent")))
    return s.sql(f"SELECT x.vid, x.dst FROM {lists} l, LATERAL {name}(l.vid, l.adjacent) x")


@_q("udf_batch_rewrite", "SELECT event_id, round(value * value, 6) AS square FROM events WHERE value IS NOT NULL")
def _(t):
    import pyarrow as pa
    import pyarrow.compute as pc

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.multiply(b.column(1), b.column(1))], names=["event_id", "square"])

    return t("events").where("value is not null").select("event_id", "value").mapInArrow(run, "event_id long, square double").select("event_id", F.round("square", 6).alias("square"))


_FLOW_RANK = oracles.ranks("part_flow", 30, True)


@_g("rank_join_parts", f"SELECT p_partkey, p_name, round(rank, 9) AS rank FROM part JOIN ({_FLOW_RANK}) r ON r.vid = p_partkey")
def _(s, d):
    parts = s.read.parquet(f"{d}/part.parquet").select("p_partkey", "p_name")
    return parts.join(ranks.pagerank_vertex(fixtures.part_flow(s, d))[0], F.col("vid") == F.col("p_partkey")).select("p_partkey", "p_name", F.round("rank", 9).alias("rank"))


@_g("rank_percentiles", f"SELECT round(quantile_cont(rank, 0.5), 9) AS median, round(quantile_cont(rank, 0.9), 9) AS p90, round(max(rank), 9) AS top FROM ({_FLOW_RANK})")
def _(s, d):
    found = ranks.pagerank_vertex(fixtures.part_flow(s, d))[0]
    return found.agg(F.round(F.percentile("rank", 0.5), 9).alias("median"), F.round(F.percentile("rank", 0.9), 9).alias("p90"), F.round(F.max("rank"), 9).alias("top"))


@_g("reachability", f"SELECT v.vid, d.dist IS NOT NULL AS reached FROM ({oracles.vertices_sql('road_hour')}) v LEFT JOIN ({oracles.distances('road_hour', [0])}) d USING (vid)")
def _(s, d):
    g = fixtures.road_hour(s, d)
    found = traversal.sssp_cell(fixtures.in_blocks(g), [0])[0]
    return g.vertices.join(found, "vid", "left").select("vid", F.col("dist").isNotNull().alias("reached"))


_SIZES = f"SELECT component, count(*) AS n FROM ({oracles.components('page_host')}) GROUP BY component"


@_g("largest_component", f"SELECT c.vid FROM ({oracles.components('page_host')}) c JOIN (SELECT component FROM ({_SIZES}) ORDER BY n DESC, component LIMIT 1) b USING (component)")
def _(s, d):
    labels = Scratch(s, "largest").save(traversal.components_vertex(fixtures.page_host(s, d))[0])
    best = traversal.component_stats(labels).orderBy(F.desc("n"), "component").limit(1).select("component")
    return labels.join(F.broadcast(best), "component").select("vid")


def _edge_file(form: str):
    @_g(f"load_{form}", f"SELECT src, dst, weight FROM ({oracles.arcs('road_hour', True)})" if form != "text" else f"SELECT src, dst FROM ({oracles.arcs('road_hour', True)})")
    def _(s, d):
        """Written and read again as an edge list of that format."""
        path = f"{Scratch(s, 'edge-files').root}/{form}"
        edges = fixtures.road_hour(s, d).edges.select("src", "dst", "weight")
        if form == "text":
            edges.select(F.concat_ws("\t", "src", "dst").alias("value")).write.text(path)
        else:
            edges.write.format(form).save(path)
        return read_edge_list(s, path, form, "src long, dst long, weight long")


for _form in ("csv", "json", "orc", "text", "parquet"):
    _edge_file(_form)
