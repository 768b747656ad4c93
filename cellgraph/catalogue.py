"""Queries of the graph engine and their SQL: one entry per method, variant, baseline and measure."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellgraph import experiments, fixtures, metrics, oracles, planner
from cellgraph.algorithms import betweenness as bc
from cellgraph.algorithms import ranks as rk
from cellgraph.algorithms import traversal as tr
from cellgraph.cells import CellGraph, discover_cells
from cellgraph.operators import analysis, relational  # noqa: F401
from cellgraph.graph import Graph
from cellgraph.partition import MIX, balance_cells, partition_blocks, partition_hash, partition_mincut, partition_modulo, partition_range
from cellgraph.scratch import Scratch
from cellgraph.sources.slices import SliceStore

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        _QUERIES[name] = f
        if sql:
            _SQL[name] = sql
        return f

    return keep


def _space(g: Graph) -> int:
    return (g.vertices.agg(F.max("vid")).first()[0] or 0) + 1


_blocks = fixtures.in_blocks


def _modulo(g: Graph, k: int = 4) -> CellGraph:
    return discover_cells(g, partition_modulo(g, k))


def _rounded(df: DataFrame, column: str = "rank") -> DataFrame:
    return df.withColumn(column, F.round(column, 9))


BLOCK4 = "(least({{v}} * 4 // (SELECT max(vid) + 1 FROM ({vertices})), 3))::INT"
MOD4 = "({v} % 4)::INT"


def _block_pid(name: str) -> str:
    return BLOCK4.format(vertices=oracles.vertices_sql(name))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tr.components_cell(_blocks(fixtures.road_hour(spark, sf_dir)))[0]


# --- preparation -------------------------------------------------------------------------------------


@query("partition_modulo_stats", f"SELECT {MOD4.format(v='vid')} AS pid, count(*) AS n FROM ({oracles.vertices_sql('order_supplier')}) GROUP BY 1")
def _(s, d):
    return partition_modulo(fixtures.order_supplier(s, d), 4).groupBy("pid").agg(F.count(F.lit(1)).alias("n"))


@query("partition_hash_stats", f"SELECT (((vid % 2147483648 + vid // 2147483648) * {MIX}) % 4294967296 // 4096 % 4)::INT AS pid, count(*) AS n FROM ({oracles.vertices_sql('order_supplier')}) GROUP BY 1")
def _(s, d):
    return partition_hash(fixtures.order_supplier(s, d), 4).groupBy("pid").agg(F.count(F.lit(1)).alias("n"))


@query("partition_range_stats", f"SELECT {_block_pid('event_road').format(v='vid')} AS pid, count(*) AS n FROM ({oracles.vertices_sql('event_road')}) GROUP BY 1")
def _(s, d):
    g = fixtures.event_road(s, d)
    return partition_blocks(g, 4, _space(g)).groupBy("pid").agg(F.count(F.lit(1)).alias("n"))


@query("partition_quantile_stats")
def _(s, d):
    return partition_range(fixtures.hub_tree(s, d), 4).groupBy("pid").agg(F.count(F.lit(1)).alias("n"))


@query("partition_balanced_stats")
def _(s, d):
    cg = _blocks(fixtures.hub_tree(s, d), 8)
    return balance_cells(cg.cell_of, 4, 2).groupBy("pid").agg(F.count(F.lit(1)).alias("n"))


@query("partition_mincut_stats")
def _(s, d):
    g = fixtures.event_road(s, d)
    return metrics.balance(discover_cells(g, partition_mincut(g, 8)))


@query("cells_summary", f"SELECT pid, count(*) AS n_vertices, count(DISTINCT cell_id) AS n_cells FROM ({oracles.cell_of('event_road', _block_pid('event_road'))}) GROUP BY pid")
def _(s, d):
    return metrics.balance(_blocks(fixtures.event_road(s, d))).select("pid", "n_vertices", "n_cells")


@query("cut_edges_by_part", f"SELECT src_pid, dst_pid, count(*) AS n FROM ({oracles.placed('road_hour', _block_pid('road_hour'))}) WHERE src_pid <> dst_pid GROUP BY 1, 2")
def _(s, d):
    return metrics.cut_by_part(_blocks(fixtures.road_hour(s, d)))


@query("cell_graph_edges", f"SELECT src_cell AS src, dst_cell AS dst, count(*) AS n, min(weight) AS min_weight FROM ({oracles.links('road_hour', _block_pid('road_hour'))}) WHERE src_pid <> dst_pid GROUP BY 1, 2")
def _(s, d):
    return _blocks(fixtures.road_hour(s, d)).cell_edges()


@query("remote_refs", f"SELECT src, dst, dst_pid, dst_cell FROM ({oracles.links('order_supplier', MOD4)}) WHERE src_pid <> dst_pid")
def _(s, d):
    return _modulo(fixtures.order_supplier(s, d)).cut_edges.select("src", "dst", "dst_pid", "dst_cell")


@query("boundary_vertices", f"SELECT DISTINCT src AS vid, src_pid AS pid FROM ({oracles.placed('road_hour', _block_pid('road_hour'))}) WHERE src_pid <> dst_pid")
def _(s, d):
    return _blocks(fixtures.road_hour(s, d)).cut_edges.select(F.col("src").alias("vid"), F.col("src_pid").alias("pid")).distinct()


@query("slice_roundtrip", oracles.arcs("road_hour"))
def _(s, d):
    store = SliceStore(s, f"{Scratch(s, 'slices').root}/road")
    store.write(_blocks(fixtures.road_hour(s, d)), partitioner="blocks")
    return store.read_topology().select("src", "dst", "weight")


@query("attribute_slice_pruned", "SELECT event_id AS vid, value FROM events")
def _(s, d):
    store = SliceStore(s, f"{Scratch(s, 'slices').root}/attr")
    events = s.read.parquet(f"{d}/events.parquet").withColumnRenamed("event_id", "vid")
    store.write(_blocks(fixtures.event_road(s, d)), {"event": events})
    return store.read_attributes("event", ["value"]).select("vid", "value")


#: Graph builders by the way they find their edges.
for _name, _graph in (("foreign_key", "hub_tree"), ("succession", "part_flow"), ("bipartite", "order_supplier"), ("equal", "doc_copies"), ("similarity", "knn")):
    query(f"graph_{_name}", f"SELECT src, dst FROM ({oracles.arcs(_graph, True)})")(lambda s, d, g=_graph: getattr(fixtures, g)(s, d).edges.select("src", "dst"))


# --- maximum value and components ----------------------------------------------------------------------


def _doubled(g: Graph) -> DataFrame:
    """A value that is not monotone in the id."""
    return g.vertices.select("vid", ((F.col("vid") * 7919) % 10007).alias("value"))


def _max_sql(name: str) -> str:
    return f"SELECT v AS vid, lab AS value FROM ({oracles.spread(oracles.arcs(name), oracles.vertices_sql(name), True, '(vid * 7919) % 10007')})"


@query("max_value_vertex", _max_sql("hub_tree"))
def _(s, d):
    g = fixtures.hub_tree(s, d)
    return tr.max_value_vertex(g, _doubled(g))[0]


@query("max_value_cell", _max_sql("event_road"))
def _(s, d):
    g = fixtures.event_road(s, d)
    return tr.max_value_cell(_blocks(g, 16), _doubled(g))[0]


@query("max_value_cell_program", _max_sql("hub_tree"))
def _(s, d):
    g = fixtures.hub_tree(s, d)
    return tr.max_value_program(_blocks(g), _doubled(g))[0]


@query("max_value_vertex_road_hour", _max_sql("road_hour"))
def _(s, d):
    g = fixtures.road_hour(s, d)
    return tr.max_value_vertex(g, _doubled(g))[0]


def _cc_vertex(name: str, build) -> None:
    query(f"cc_vertex_{name}", oracles.components(build))(lambda s, d: tr.components_vertex(getattr(fixtures, build)(s, d))[0])


def _cc_cell(name: str, build: str, place) -> None:
    query(f"cc_{name}" if name == "knn" else f"cc_cell_{name}", oracles.components(build))(lambda s, d: tr.components_cell(place(getattr(fixtures, build)(s, d)))[0])


for _name in ("hub_tree", "order_supplier", "part_flow", "conv_turns"):
    _cc_vertex(_name, _name)
_cc_cell("road", "event_road", lambda g: discover_cells(g := g.stored(), partition_mincut(g, 16)))
_cc_cell("road_range", "event_road", lambda g: _blocks(g, 16))
_cc_cell("road_hour_hash", "road_hour", lambda g: discover_cells(g, partition_hash(g, 4)))
_cc_cell("user_chain", "user_chain", _blocks)
_cc_cell("order_supplier", "order_supplier", _blocks)
_cc_cell("doc_copies", "doc_copies", _blocks)
_cc_cell("conversations", "conv_turns", _blocks)
_cc_cell("hub_tree", "hub_tree", _modulo)
_cc_cell("knn", "knn", _blocks)
_cc_cell("page_host", "page_host", _blocks)


@query("cc_cell_balanced", oracles.components("road_hour"))
def _(s, d):
    cg = _blocks(fixtures.road_hour(s, d), 8)
    return tr.components_cell(discover_cells(cg.graph, balance_cells(cg.cell_of, 8)))[0]


@query("cc_contraction", oracles.components("event_road").replace("lab AS component", "lab AS component").replace("max(u.lab)", "min(u.lab)").replace("u.lab > r.lab", "u.lab < r.lab"))
def _(s, d):
    from cellgraph.algorithms.contraction import components

    g = fixtures.event_road(s, d)
    found = components(s, g.edges, "src", "dst").withColumnRenamed("v", "vid")
    return g.vertices.join(found, "vid", "left").select("vid", F.coalesce("component", "vid").alias("component"))


@query("component_sizes_road", f"SELECT component, count(*) AS n FROM ({oracles.components('event_road')}) GROUP BY component")
def _(s, d):
    return tr.component_stats(tr.components_cell(_blocks(fixtures.event_road(s, d), 16))[0])


# --- shortest paths --------------------------------------------------------------------------------------


@query("bfs_road", oracles.distances("event_road", [0]))
def _(s, d):
    return tr.sssp_cell(_blocks(fixtures.event_road(s, d), 16), [0])[0]


@query("sssp_cell_road_weighted", oracles.distances("event_road", [0], weighted=True))
def _(s, d):
    return tr.sssp_cell(_blocks(fixtures.event_road(s, d), 16), [0], weight=True)[0]


@query("sssp_vertex_hub", oracles.distances("hub_tree", [5]))
def _(s, d):
    return tr.sssp_vertex(fixtures.hub_tree(s, d), [5])[0]


@query("sssp_cell_hub", oracles.distances("hub_tree", [5]))
def _(s, d):
    return tr.sssp_cell(_blocks(fixtures.hub_tree(s, d)), [5])[0]


@query("sssp_cell_order_supplier", oracles.distances("order_supplier", [0]))
def _(s, d):
    return tr.sssp_cell(_blocks(fixtures.order_supplier(s, d)), [0])[0]


@query("sssp_cell_part_flow", oracles.distances("part_flow", [0], directed=True))
def _(s, d):
    return tr.sssp_cell(_blocks(fixtures.part_flow(s, d)), [0])[0]


@query("sssp_vertex_part_flow", oracles.distances("part_flow", [0], directed=True))
def _(s, d):
    return tr.sssp_vertex(fixtures.part_flow(s, d), [0])[0]


@query("sssp_multi_source", oracles.distances("hub_tree", [5, 6, 10]))
def _(s, d):
    return tr.sssp_cell(_modulo(fixtures.hub_tree(s, d)), [5, 6, 10])[0]


@query(
    "sssp_parents",
    f"""WITH dist AS MATERIALIZED ({oracles.distances("hub_tree", [5])})
  SELECT a.vid, a.dist, (SELECT min(e.src) FROM ({oracles.arcs("hub_tree")}) e JOIN dist b ON b.vid = e.src WHERE e.dst = a.vid AND b.dist + 1 = a.dist) AS parent FROM dist a""",
)
def _(s, d):
    g = fixtures.hub_tree(s, d)
    return tr.with_parents(g, tr.sssp_vertex(g, [5])[0])


_FRACTION = {"kind": "DOUBLE", "weighted": True}


@query("sssp_vertex_fraction", oracles.distances("road_fraction", [0], **_FRACTION))
def _(s, d):
    return tr.sssp_vertex(fixtures.road_fraction(s, d).filter_edges("src % 2 >= 0"), [0], weight=True)[0]


@query("sssp_cell_fraction", oracles.distances("road_fraction", [0], **_FRACTION))
def _(s, d):
    return tr.sssp_cell(_blocks(fixtures.road_fraction(s, d), 8), [0], weight=True)[0]


@query("sssp_cell_heap", oracles.distances("road_hour", [0], weighted=True))
def _(s, d):
    return tr.sssp_cell(_blocks(fixtures.road_hour(s, d)), [0], weight=True, local="heap")[0]


@query("sssp_vertex_road_hour", oracles.distances("road_hour", [0]))
def _(s, d):
    return tr.sssp_vertex(fixtures.road_hour(s, d), [0])[0]


@query("sssp_vertex_order_supplier", oracles.distances("order_supplier", [0]))
def _(s, d):
    return tr.sssp_vertex(fixtures.order_supplier(s, d), [0])[0]


@query(
    "sssp_parents_fraction",
    f"""WITH dist AS MATERIALIZED ({oracles.distances("road_fraction", [0], **_FRACTION)})
  SELECT a.vid, a.dist, (SELECT min(e.src) FROM ({oracles.arcs("road_fraction")}) e JOIN dist b ON b.vid = e.src WHERE e.dst = a.vid AND b.dist + e.weight = a.dist) AS parent FROM dist a""",
)
def _(s, d):
    g = fixtures.road_fraction(s, d)
    return tr.with_parents(g, tr.sssp_cell(_blocks(g, 8), [0], weight=True)[0], weight=True)


@query("distance_histogram", f"SELECT dist, count(*) AS n FROM ({oracles.distances('order_supplier', [0])}) GROUP BY dist")
def _(s, d):
    return tr.sssp_vertex(fixtures.order_supplier(s, d), [0])[0].groupBy("dist").agg(F.count(F.lit(1)).alias("n"))


@query("eccentricity_hub", f"SELECT 5::BIGINT AS source, max(dist) AS ecc FROM ({oracles.distances('hub_tree', [5])})")
def _(s, d):
    return tr.sssp_vertex(fixtures.hub_tree(s, d), [5])[0].agg(F.lit(5).cast("long").alias("source"), F.max("dist").alias("ecc"))


@query("eccentricity_road_hour", f"SELECT 0::BIGINT AS source, max(dist) AS ecc FROM ({oracles.distances('road_hour', [0])})")
def _(s, d):
    return tr.sssp_cell(_blocks(fixtures.road_hour(s, d)), [0])[0].agg(F.lit(0).cast("long").alias("source"), F.max("dist").alias("ecc"))


_FAR = f"SELECT vid AS v FROM ({oracles.distances('order_supplier', [0])}) ORDER BY dist DESC, vid DESC LIMIT 1"


@query("diameter_bound", f"SELECT 'order_supplier' AS graph, greatest((SELECT max(dist) FROM ({oracles.distances('order_supplier', [0])})), (SELECT max(dist) FROM ({oracles.distances('order_supplier', _FAR)}))) AS at_least")
def _(s, d):
    return s.createDataFrame([("order_supplier", tr.diameter_lower_bound(fixtures.order_supplier(s, d), 0))], "graph string, at_least long")


@query(
    "betweenness_exact_conv",
    "SELECT conv_id * 1048576 + turn AS vid, 2.0::DOUBLE * (row_number() OVER w - 1) * (count(*) OVER (PARTITION BY conv_id) - row_number() OVER w) AS score FROM (SELECT DISTINCT conv_id, turn FROM conversations) WINDOW w AS (PARTITION BY conv_id ORDER BY turn)",
)
def _(s, d):
    return _rounded(bc.betweenness(fixtures.conv_turns(s, d)), "score")


# --- ranks -------------------------------------------------------------------------------------------------


def _rank_sql(name: str, rounds: int = 30, directed: bool = False, leak: bool = False) -> str:
    return f"SELECT vid, round(rank, 9) AS rank FROM ({oracles.ranks(name, rounds, directed, leak)})"


@query("pagerank_vertex_part_flow", _rank_sql("part_flow", directed=True))
def _(s, d):
    return _rounded(rk.pagerank_vertex(fixtures.part_flow(s, d))[0])


@query("pagerank_cell_part_flow", _rank_sql("part_flow", directed=True))
def _(s, d):
    return _rounded(rk.pagerank_cell(_blocks(fixtures.part_flow(s, d)))[0])


@query("pagerank_cell_hub", _rank_sql("hub_tree"))
def _(s, d):
    return _rounded(rk.pagerank_cell(_blocks(fixtures.hub_tree(s, d)))[0])


@query("pagerank_cell_order_supplier", _rank_sql("order_supplier"))
def _(s, d):
    return _rounded(rk.pagerank_cell(_blocks(fixtures.order_supplier(s, d)))[0])


@query("pagerank_vertex_road_hour", _rank_sql("road_hour"))
def _(s, d):
    return _rounded(rk.pagerank_vertex(fixtures.road_hour(s, d))[0])


@query("pagerank_cell_road_hour", _rank_sql("road_hour"))
def _(s, d):
    return _rounded(rk.pagerank_cell(_blocks(fixtures.road_hour(s, d)))[0])


@query("pagerank_vertex_order_supplier", _rank_sql("order_supplier"))
def _(s, d):
    return _rounded(rk.pagerank_vertex(fixtures.order_supplier(s, d))[0])


@query("pagerank_cell_redistribute_user_chain", _rank_sql("user_chain", directed=True))
def _(s, d):
    return _rounded(rk.pagerank_cell(_blocks(fixtures.user_chain(s, d, True)))[0])


@query("block_rank_cell_part_flow", f"SELECT vid, round(rank, 8) AS rank FROM ({oracles.ranks('part_flow', 60, True)})")
def _(s, d):
    return rk.block_rank(_blocks(fixtures.part_flow(s, d), 16), tol=1e-12, engine="cell")[0].withColumn("rank", F.round("rank", 8))


@query("pagerank_leak_user_chain", _rank_sql("user_chain", directed=True, leak=True).replace("round(rank, 9)", "round(rank + 1e-12, 9)"))
def _(s, d):
    return rk.pagerank_vertex(fixtures.user_chain(s, d, True), dangling="leak")[0].withColumn("rank", F.round(F.col("rank") + 1e-12, 9))


@query("pagerank_redistribute_user_chain", _rank_sql("user_chain", directed=True))
def _(s, d):
    return _rounded(rk.pagerank_vertex(fixtures.user_chain(s, d, True))[0])


@query("local_rank_road_hour", f"SELECT vid, cell_id, round(rank, 9) AS rank FROM ({oracles.local_ranks('road_hour', _block_pid('road_hour'), 30)})")
def _(s, d):
    return _rounded(rk.local_rank(_blocks(fixtures.road_hour(s, d))))


@query("cell_rank_road_hour", f"SELECT cell_id, round(rank, 9) AS rank FROM ({oracles.cell_ranks('road_hour', _block_pid('road_hour'), 30, 30)})")
def _(s, d):
    cg = _blocks(fixtures.road_hour(s, d))
    return _rounded(rk.cell_rank(cg, cg.scratch.save(rk.local_rank(cg))))


@query("block_rank_part_flow", f"SELECT vid, round(rank, 8) AS rank FROM ({oracles.ranks('part_flow', 60, True)})")
def _(s, d):
    return rk.block_rank(_blocks(fixtures.part_flow(s, d), 16), tol=1e-12)[0].withColumn("rank", F.round("rank", 8))


@query("rank_convergence", f"SELECT b.round::BIGINT AS round, round(sum(abs(b.rank - a.rank)), 9) AS l1_delta FROM ({oracles.ranks('part_flow', 10, True, every_round=True)}) a JOIN ({oracles.ranks('part_flow', 10, True, every_round=True)}) b ON b.vid = a.vid AND b.round = a.round + 1 GROUP BY b.round")
def _(s, d):
    _, _, deltas = rk.pagerank_vertex(fixtures.part_flow(s, d), 10, tol=0.0)
    return s.createDataFrame([(i + 1, round(x, 9)) for i, x in enumerate(deltas)], "round long, l1_delta double")


def _top_sql(rounds: int) -> str:
    return f"SELECT vid FROM ({oracles.ranks('part_flow', rounds, True)}) ORDER BY round(rank, 12) DESC, vid LIMIT 100"


@query("rank_topk_overlap", f"SELECT 100::BIGINT AS k, count(*) AS overlap FROM ({_top_sql(2)}) a JOIN ({_top_sql(30)}) b USING (vid)")
def _(s, d):
    g = fixtures.part_flow(s, d)
    return rk.topk_overlap(rk.pagerank_vertex(g, 2)[0], rk.pagerank_vertex(g)[0], 100)


@query("top_ranked", f"SELECT vid, round(rank, 9) AS rank FROM ({oracles.ranks('part_flow', 30, True)}) ORDER BY round(rank, 9) DESC, vid LIMIT 20")
def _(s, d):
    return _rounded(rk.pagerank_vertex(fixtures.part_flow(s, d))[0]).orderBy(F.desc("rank"), "vid").limit(20)


# --- measures ------------------------------------------------------------------------------------------------


def _supersteps_sql() -> str:
    """Greatest ids that travel an arc a round change for the last time in round n; one more superstep tells that, and one more finds nothing new."""
    parts = []
    for name in experiments.GRAPHS:
        parts.append(f"SELECT '{name}' AS graph, 'vertex' AS engine, n + 2 AS supersteps FROM ({oracles.last_change(oracles.arcs(name), 'SELECT vid AS v, vid AS lab FROM (' + oracles.vertices_sql(name) + ')')})")
        links = oracles.links(name, _block_pid(name))
        cells = f"SELECT cell_id AS v, max(vid) AS lab FROM ({oracles.cell_of(name, _block_pid(name))}) GROUP BY cell_id"
        parts.append(f"SELECT '{name}', 'cell', n + 2 FROM ({oracles.last_change('SELECT src_cell AS src, dst_cell AS dst FROM (' + links + ') WHERE src_pid <> dst_pid', cells)})")
    return " UNION ALL ".join(parts)


@query("metric_supersteps", _supersteps_sql())
def _(s, d):
    return experiments.component_runs(s, d).select("graph", "engine", "supersteps")


@query("metric_messages")
def _(s, d):
    return experiments.component_runs(s, d)


@query("metric_r2")
def _(s, d):
    return experiments.speedup_against_diameter(s, d)


@query("placement_ablation")
def _(s, d):
    return experiments.placement_table(s, d)


@query("block_rank_rounds")
def _(s, d):
    return experiments.block_rank_table(s, d)


@query("metric_local_work")
def _(s, d):
    return experiments.local_work(s, d)


def _profile_sql(name: str) -> str:
    v, e, c = oracles.vertices_sql(name), oracles.arcs(name), oracles.components(name)
    return f"SELECT '{name}' AS graph, (SELECT count(*) FROM ({v})) AS vertices, (SELECT count(*) // 2 FROM ({e})) AS edges, (SELECT count(DISTINCT component) FROM ({c})) AS components, (SELECT max(n) FROM (SELECT count(*) AS n FROM ({e}) GROUP BY src)) AS max_degree"


_PROFILED = ("road_hour", "hub_tree", "order_supplier", "page_host")


@query("graph_profile", " UNION ALL ".join(map(_profile_sql, _PROFILED)))
def _(s, d):
    rows = []
    for name in _PROFILED:
        g = getattr(fixtures, name)(s, d)
        labels = tr.components_cell(_blocks(g))[0]
        rows.append((name, g.vertices.count(), g.edges.count(), labels.select("component").distinct().count(), g.degrees().agg(F.max("degree")).first()[0]))
    return s.createDataFrame(rows, "graph string, vertices long, edges long, components long, max_degree long")


@query("diameter_cells")
def _(s, d):
    """Lower bounds of the diameter of a graph and of its cell graph."""
    cg = _blocks(fixtures.road_hour(s, d))
    return s.createDataFrame([("road_hour", tr.diameter_lower_bound(cg.graph, 0, 2, cg), tr.cell_diameter(cg))], "graph string, diameter long, cell_diameter long")


@query("engine_choice")
def _(s, d):
    rows = []
    for name in ("road_hour", "hub_tree", "order_supplier"):
        cg = _blocks(getattr(fixtures, name)(s, d))
        rows += [(name, algorithm, planner.plan(cg, algorithm)) for algorithm in ("components", "rank")]
        cg.unpersist()
    return s.createDataFrame(rows, "graph string, algorithm string, engine string")


@query("rank_error", f"SELECT round(sum(abs(a.rank - b.rank)), 9) AS l1, round(max(abs(a.rank - b.rank)), 9) AS max_error FROM ({oracles.ranks('part_flow', 3, True)}) a JOIN ({oracles.ranks('part_flow', 30, True)}) b USING (vid)")
def _(s, d):
    g = fixtures.part_flow(s, d)
    return rk.rank_error(rk.pagerank_vertex(g, 3)[0], rk.pagerank_vertex(g)[0]).select(F.round("l1", 9).alias("l1"), F.round("max_error", 9).alias("max_error"))


@query("slice_meta", f"SELECT 4::BIGINT AS parts, (SELECT count(*) FROM events) AS vertices, (SELECT count(*) FROM ({oracles.arcs('road_hour')})) AS arcs, (SELECT count(DISTINCT cell_id) FROM ({oracles.cell_of('road_hour', _block_pid('road_hour'))}) WHERE pid = 1) AS cells_of_1, 'vid,value' AS columns")
def _(s, d):
    store = SliceStore(s, f"{Scratch(s, 'slices').root}/meta")
    values = s.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("vid"), "value")
    store.write(_blocks(fixtures.road_hour(s, d)), {"event": values}, "blocks")
    meta = store.meta()
    row = (meta["parts"], meta["vertices"], meta["arcs"], store.cells(1).count(), ",".join(store.schema("event").fieldNames()))
    return s.createDataFrame([row], "parts long, vertices long, arcs long, cells_of_1 long, columns string")


@query("cc_uncached", oracles.components("order_supplier"))
def _(s, d):
    """The baseline without a cache: every round reads the edges from their tables again."""
    return tr.components_uncached(lambda: fixtures.order_supplier(s, d))


_DENSE_WORK = f"SELECT c.pid, c.cell_id, count(l.src) AS work FROM ({oracles.cell_of('order_supplier', _block_pid('order_supplier'))}) c LEFT JOIN ({oracles.arcs('order_supplier')}) l ON l.src = c.vid GROUP BY 1, 2"


@query("metric_work_quartiles_dense", f"SELECT pid, min(work)::DOUBLE AS w_min, quantile_cont(work, 0.25)::DOUBLE AS w_q1, quantile_cont(work, 0.5)::DOUBLE AS w_median, quantile_cont(work, 0.75)::DOUBLE AS w_q3, max(work)::DOUBLE AS w_max FROM ({_DENSE_WORK}) GROUP BY pid")
def _(s, d):
    return metrics.work_quartiles(_blocks(fixtures.order_supplier(s, d)))


@query("metric_straggler_dense", f"SELECT w[1]::BIGINT AS slowest, w[2]::BIGINT AS second, round(w[1] / w[2], 9) AS factor FROM (SELECT list(work ORDER BY work DESC) AS w FROM (SELECT pid, sum(work)::BIGINT AS work FROM ({_DENSE_WORK}) GROUP BY pid))")
def _(s, d):
    return metrics.straggler(_blocks(fixtures.order_supplier(s, d)))


_HUB_WORK = f"SELECT c.pid, c.cell_id, count(l.src) AS work FROM ({oracles.cell_of('hub_tree', MOD4)}) c LEFT JOIN ({oracles.arcs('hub_tree')}) l ON l.src = c.vid GROUP BY 1, 2"


@query("metric_cut", f"SELECT count(*) AS edges, count(*) FILTER (WHERE src_pid <> dst_pid) AS cut_edges, round(count(*) FILTER (WHERE src_pid <> dst_pid) / count(*), 9) AS cut_ratio FROM ({oracles.placed('order_supplier', MOD4)})")
def _(s, d):
    return metrics.cut(_modulo(fixtures.order_supplier(s, d)))


@query("metric_balance", f"SELECT pid, sum(n)::BIGINT AS n_vertices, count(*) AS n_cells, max(n) AS largest_cell, round(stddev_pop(n), 9) AS cell_size_spread FROM (SELECT pid, cell_id, count(*) AS n FROM ({oracles.cell_of('order_supplier', MOD4)}) GROUP BY 1, 2) GROUP BY pid")
def _(s, d):
    return metrics.balance(_modulo(fixtures.order_supplier(s, d)))


@query("metric_work_quartiles", f"SELECT pid, min(work)::DOUBLE AS w_min, quantile_cont(work, 0.25)::DOUBLE AS w_q1, quantile_cont(work, 0.5)::DOUBLE AS w_median, quantile_cont(work, 0.75)::DOUBLE AS w_q3, max(work)::DOUBLE AS w_max FROM ({_HUB_WORK}) GROUP BY pid")
def _(s, d):
    return metrics.work_quartiles(_modulo(fixtures.hub_tree(s, d)))


@query("metric_straggler", f"SELECT w[1]::BIGINT AS slowest, w[2]::BIGINT AS second, round(w[1] / w[2], 9) AS factor FROM (SELECT list(work ORDER BY work DESC) AS w FROM (SELECT pid, sum(work)::BIGINT AS work FROM ({_HUB_WORK}) GROUP BY pid))")
def _(s, d):
    return metrics.straggler(_modulo(fixtures.hub_tree(s, d)))


@query("metric_idle", f"SELECT round(1 - avg(work) / max(work), 9) AS idle_parts, round(avg(1 - work / (8 * greatest(largest, work / 8))), 9) AS idle_cores FROM (SELECT pid, sum(work)::BIGINT AS work, max(work) AS largest FROM ({_HUB_WORK}) GROUP BY pid)")
def _(s, d):
    return metrics.idle(_modulo(fixtures.hub_tree(s, d)), 8)


for _name, _graph in (("hub", "hub_tree"), ("road", "event_road")):
    query(f"degree_distribution_{_name}", f"SELECT degree, count(*) AS n FROM (SELECT v.vid, count(e.src) AS degree FROM ({oracles.vertices_sql(_graph)}) v LEFT JOIN ({oracles.arcs(_graph)}) e ON e.src = v.vid GROUP BY v.vid) GROUP BY degree")(
        lambda s, d, g=_graph: getattr(fixtures, g)(s, d).degrees().groupBy("degree").agg(F.count(F.lit(1)).alias("n"))
    )


for _name, _end in (("out", "src"), ("in", "dst")):
    query(f"degree_{_name}", f"SELECT {_end} AS vid, count(*) AS degree FROM ({oracles.arcs('part_flow', True)}) GROUP BY 1")(
        lambda s, d, e=_end: fixtures.part_flow(s, d).edges.groupBy(F.col(e).alias("vid")).agg(F.count(F.lit(1)).alias("degree"))
    )


def queries() -> dict[str, Query]:
    return _QUERIES | relational.QUERIES


def oracle_sql() -> dict[str, str]:
    return _SQL | relational.SQL
