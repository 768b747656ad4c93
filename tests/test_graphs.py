"""Weights, awkward graphs, placements, the cell API, slices and streams."""

import os
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from cellgraph import fixtures, metrics, planner
from cellgraph.algorithms import ranks, traversal
from cellgraph.cells import discover_cells, local_components
from cellgraph.engine.cellprog import CellProgram, run_cell_program
from cellgraph.graph import Graph, from_similarity
from cellgraph.scratch import Scratch
from cellgraph.partition import balance_cells, partition_hash, partition_mincut, partition_modulo, partition_range
from cellgraph.sources.slices import SliceStore, read_edge_list
from cellgraph.streaming.edges import components_of_stream, drain, event_stream, succession, windowed_degree

DIR = "/root/testdata/sf0.001"


def _graph(spark, edges, kind="double", directed=False, vertices=None):
    df = spark.createDataFrame(edges, f"src long, dst long, weight {kind}")
    return Graph.from_edges(df, None if vertices is None else spark.createDataFrame([(v,) for v in vertices], "vid long"), directed)


def _distances(edges, sources, directed=False):
    arcs = [(a, b, w) for a, b, w in edges if w is not None] + ([] if directed else [(b, a, w) for a, b, w in edges if w is not None])
    dist = {s: 0 for s in sources}
    while True:
        new = {b: min([dist.get(b, float("inf"))] + [dist[a] + w for a, c, w in arcs if c == b and a in dist]) for _, b, _ in arcs}
        new = {v: d for v, d in new.items() if d < dist.get(v, float("inf"))}
        if not new:
            return dist
        dist.update(new)


def test_fractional_weights_on_both_engines(spark):
    edges = [(0, 1, 0.5), (1, 2, 0.5), (0, 2, 1.5), (2, 3, 0.75), (3, 4, None), (3, 3, 0.1), (5, 6, 0.25), (0, 1, 0.625)]
    g = _graph(spark, edges)
    want = _distances(edges, [0])
    assert want == {0: 0, 1: 0.5, 2: 1.0, 3: 1.75}
    cg = discover_cells(g, partition_modulo(g, 2))
    assert {r["vid"]: r["dist"] for r in traversal.sssp_vertex(g, [0], weight=True)[0].collect()} == want
    for local in ("relax", "heap"):
        by_cell, _ = traversal.sssp_cell(cg, [0], weight=True, local=local)
        assert {r["vid"]: r["dist"] for r in by_cell.collect()} == want, local
    parents = {r["vid"]: r["parent"] for r in traversal.with_parents(g, by_cell, weight=True).collect()}
    assert parents == {0: None, 1: 0, 2: 1, 3: 2}


def test_large_whole_weights_are_exact(spark):
    big = (1 << 53) + 1
    g = _graph(spark, [(0, 1, big), (1, 2, big)], "long")
    for found in (traversal.sssp_vertex(g, [0], weight=True)[0], traversal.sssp_cell(discover_cells(g, partition_modulo(g, 2)), [0], weight=True)[0]):
        assert {r["vid"]: r["dist"] for r in found.collect()} == {0: 0, 1: big, 2: 2 * big}


def test_negative_weights_are_refused(spark):
    g = _graph(spark, [(0, 1, -0.5)])
    with pytest.raises(ValueError):
        traversal.sssp_vertex(g, [0], weight=True)
    with pytest.raises(ValueError):
        traversal.sssp_cell(discover_cells(g, partition_modulo(g, 1)), [0], weight=True)


@pytest.mark.parametrize("seed", [1])
def test_random_directed_graphs(spark, seed):
    rng = random.Random(seed)
    edges = [(rng.randrange(40), rng.randrange(40), rng.randrange(8) / 8) for _ in range(90)]
    g = _graph(spark, edges, directed=True)
    want = _distances(edges, [edges[0][0], edges[1][0]], True)
    for k in (1, 4):
        found, run = traversal.sssp_cell(discover_cells(g, partition_modulo(g, k)), [edges[0][0], edges[1][0]], weight=True)
        assert {r["vid"]: r["dist"] for r in found.collect()} == want
        assert (k > 1) == (sum(run.combined) > 0)
    cg = discover_cells(g, partition_hash(g, 3))
    a = {r["vid"]: r["rank"] for r in ranks.pagerank_vertex(g, 6)[0].collect()}
    b = {r["vid"]: r["rank"] for r in ranks.pagerank_cell(cg, 6)[0].collect()}
    assert a.keys() == b.keys() and max(abs(a[v] - b[v]) for v in a) < 1e-12 and abs(sum(a.values()) - 1) < 1e-9
    c, run, moved = ranks.pagerank_cell(cg, None, tol=1e-2)
    d, run_v, moved_v = ranks.pagerank_vertex(g, None, tol=1e-2)
    assert len(moved_v) == run_v.supersteps and abs(ranks.rank_error(c, d).first()["l1"]) < 0.02


def test_awkward_graphs(spark):
    g = _graph(spark, [(0, 0, 1.0), (1, 2, 1.0), (1, 2, 1.0), (None, 3, 1.0), (3, None, 1.0)], vertices=[0, 1, 2, 9])
    cg = discover_cells(g, partition_modulo(g, 2))
    want = {0: 0, 1: 2, 2: 2, 9: 9}
    assert {r["vid"]: r["component"] for r in traversal.components_vertex(g)[0].collect()} == want
    assert {r["vid"]: r["component"] for r in traversal.components_cell(cg)[0].collect()} == want
    assert {r["vid"]: r["component"] for r in traversal.components_uncached(lambda: g).collect()} == want
    empty = _graph(spark, [])
    none = discover_cells(empty, partition_modulo(empty, 3))
    assert traversal.components_vertex(empty)[0].count() == traversal.components_cell(none)[0].count() == traversal.sssp_cell(none, [0])[0].count() == 0
    assert ranks.pagerank_vertex(empty)[0].count() == ranks.pagerank_cell(none)[0].count() == traversal.cell_diameter(none) == 0
    assert planner.plan(none, "components") == "vertex" and partition_mincut(empty, 4).count() == 0


def test_vectorised_components():
    rng = np.random.default_rng(5)
    for n in (1, 7, 60):
        src, dst = rng.integers(0, n, n), rng.integers(0, n, n)
        label = list(range(n))
        for a, b in zip(src, dst, strict=True):
            low, high = sorted((label[a], label[b]))
            label = [low if x == high else x for x in label]
        assert local_components(src, dst, n).tolist() == label
    chain = np.arange(100_000)
    assert not local_components(chain[:-1], chain[1:], len(chain)).any()


@pytest.mark.parametrize("name, most_cut, clusters", [("event_road", 0.15, 200_000), ("hub_tree", 0.5, 200)])
def test_mincut_is_balanced_and_cuts_less(spark, name, most_cut, clusters):
    """With 200 clusters for the driver the clusters of the hub graph are contracted again."""
    g = getattr(fixtures, name)(spark, DIR)
    place = partition_mincut(g, 4, driver_clusters=clusters, refine=2)
    sizes = [r["count"] for r in place.groupBy("pid").count().collect()]
    assert sum(sizes) == g.vertices.count() and max(sizes) <= int(1.05 * sum(sizes) / 4) + 1
    assert metrics.cut(discover_cells(g, place)).first()["cut_ratio"] < (most_cut if clusters > 200 else 0.75)


def test_balanced_cells_stay_whole(spark):
    cg = fixtures.in_blocks(fixtures.hub_tree(spark, DIR), 8)
    place = balance_cells(cg.cell_of, 4, cores=2)
    both = cg.cell_of.select("vid", "cell_id").join(place, "vid")
    assert both.groupBy("cell_id").agg(F.countDistinct("pid").alias("n")).where("n > 1").count() == 0
    loads = [r["count"] for r in place.groupBy("pid").count().collect()]
    largest = max(r["n_vertices"] for r in cg.cells().collect())
    assert len(loads) == 4 and sum(loads) == g_size(cg) and max(loads) <= max(largest, 1.25 * sum(loads) / 4)


def g_size(cg):
    return cg.cell_of.count()


def test_quantile_ranges(spark):
    g = fixtures.hub_tree(spark, DIR)
    rows = partition_range(g, 4).groupBy("pid").agg(F.count("*").alias("n"), F.min("vid").alias("lo"), F.max("vid").alias("hi")).orderBy("pid").collect()
    assert all(a["hi"] < b["lo"] for a, b in zip(rows, rows[1:], strict=False)) and max(r["n"] for r in rows) < 1.1 * sum(r["n"] for r in rows) / 4


def _gossip():
    """A program defined in a function travels to the workers by value."""

    class Gossip(CellProgram):
        """The greatest number of local vertices of any cell: told to all at first, then to one neighbour by address; cells stay awake for a third superstep."""

        dtype = "bigint"

        def start(self, part):
            return np.zeros(len(part.ids))

        def compute(self, part, ctx):
            for cell in part.cells():
                own = np.flatnonzero(part.cell == cell)
                if ctx.superstep == 1:
                    ctx.send_all(float(len(own)))
                    ctx.report(1.0)
                elif ctx.superstep == 2:
                    part.value[own] = int(ctx.told_all) * 1000 + int(ctx.reported[0])
                    ctx.keep_awake(cell)
                    if cell == 0:
                        ctx.send_neighbors(part, cell, 5)
                elif ctx.superstep == 3:
                    part.value[own] += 100_000 * sum(v for c, v in part.cell_messages if c == cell)

    return Gossip()


def test_cell_api(spark):
    g = _graph(spark, [(0, 2, 1.0), (2, 4, 1.0), (4, 1, 1.0), (3, 5, 1.0)])
    found, run = run_cell_program(_gossip(), discover_cells(g, partition_modulo(g, 2)))
    assert run.supersteps == 3 and run.messages == [0, 1, 0]
    # cells 0-2-4, 1, 3-5: the largest has 3 vertices, three cells reported; cell 1 heard from cell 0
    assert {r["vid"]: r["value"] for r in found.collect()} == {0: 3003, 2: 3003, 4: 3003, 1: 503003, 3: 3003, 5: 3003}


def test_supersteps_follow_the_cell_graph(spark):
    """Published behaviour: with few cut arcs the supersteps follow the cell graph's diameter, not the graph's."""
    path = _graph(spark, [(i, i + 1, 1.0) for i in range(24)])
    cg = fixtures.in_blocks(path, 4)
    vertex, cell = traversal.components_vertex(path)[1], traversal.components_cell(cg)[1]
    assert (vertex.supersteps, cell.supersteps) == (26, 5) and traversal.cell_diameter(cg) == 3
    assert traversal.sssp_cell(cg, [0])[1].supersteps <= traversal.cell_diameter(cg) + 2 and planner.plan(cg, "components") == planner.plan(cg, "rank") == "cell"


def test_block_rank_needs_fewer_rounds_on_closed_cells(spark):
    rows = []
    rng = random.Random(3)
    for block in range(8):  # eight dense blocks of their own sizes, one edge between neighbours
        base, size = block * 100, 20 + 5 * block
        rows += [(base + rng.randrange(size), base + rng.randrange(size), 1.0) for _ in range(size * 4)]
        rows.append((base, (block + 1) % 8 * 100, 1.0))
    g = _graph(spark, rows)
    cg = discover_cells(g, g.vertices.select("vid", F.floor(F.col("vid") / 100).cast("int").alias("pid")))
    classic, run, _ = ranks.pagerank_vertex(g, None, tol=1e-3)
    for engine in ("vertex", "cell"):
        block, blocked, moved = ranks.block_rank(cg, 1e-3, engine=engine)
        assert len(moved) <= run.supersteps and ranks.rank_error(block, classic).first()["l1"] < 0.01


def test_slices(spark, tmp_path):
    cg = fixtures.in_blocks(fixtures.road_hour(spark, DIR))
    store = SliceStore(spark, str(tmp_path))
    store.write(cg, {"event": spark.read.parquet(f"{DIR}/events.parquet").withColumnRenamed("event_id", "vid")}, "blocks")
    again = store.load(spark)
    assert again.graph.edges.count() == cg.graph.edges.count() and again.cell_of.count() == cg.cell_of.count()
    a = {tuple(r) for r in traversal.sssp_cell(again, [0], weight=True)[0].collect()}
    assert a == {tuple(r) for r in traversal.sssp_cell(cg, [0], weight=True)[0].collect()}
    assert {r["src_pid"] for r in store.read_topology([1, 2]).select("src_pid").distinct().collect()} == {1, 2}
    assert store.meta()["partitioner"] == "blocks" and store.cells(1).agg(F.sum("n_vertices")).first()[0] == cg.cell_of.where("pid = 1").count()
    plan = store.read_attributes("event", ["value"])._jdf.queryExecution().executedPlan().toString()
    assert "props" not in plan


def test_edge_lists(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# comment\n1\t2\n 3  4 \n\n")
    (tmp_path / "e.csv").write_text("1;2;0.5\n3;4;\n")
    (tmp_path / "e.json").write_text('{"src": 1, "dst": 2, "weight": 0.5}\n')
    assert sorted(map(tuple, read_edge_list(spark, str(tmp_path / "e.txt"), "text").collect())) == [(1, 2), (3, 4)]
    assert sorted(map(tuple, read_edge_list(spark, str(tmp_path / "e.csv"), sep=";").collect())) == [(1, 2, 0.5), (3, 4, None)]
    assert [tuple(r) for r in read_edge_list(spark, str(tmp_path / "e.json"), "json").collect()] == [(1, 2, 0.5)]


def test_similarity_edges(spark):
    rng = np.random.default_rng(4)
    x = rng.integers(-2, 3, (40, 5)).astype(float)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)] + [(99, None)], "id long, v array<double>")
    for blocks in (1, 3, 60):
        got = {(r["src"], r["dst"]) for r in from_similarity(df, "id", "v", 6.0, blocks).collect()}
        assert got == {(i, j) for i in range(40) for j in range(i + 1, 40) if x[i] @ x[j] >= 6.0}


def _events(spark, path, name, rows):
    df = spark.createDataFrame(rows, "event_id long, ts string, user_id long").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    df.coalesce(1).write.mode("append").parquet(f"{path}/{name}")


def test_succession_and_components_across_batches(spark, tmp_path):
    _events(spark, tmp_path, "events.parquet", [(1, "2024-01-01 00:00:00", 7), (3, "2024-01-01 00:02:00", 7), (2, "2024-01-01 00:01:00", 7), (9, "2024-01-01 00:00:00", 8)])
    assert sorted(map(tuple, drain(spark, succession(event_stream(spark, f"{tmp_path}/events.parquet")), "append", "next").collect())) == [(1, 2), (2, 3)]
    edges = [(i, i + 1) for i in range(0, 30)] + [(50, 51)]
    spark.createDataFrame(edges, "src long, dst long").repartition(4).write.parquet(f"{tmp_path}/edges")
    got = {r["v"]: r["label"] for r in components_of_stream(spark, f"{tmp_path}/edges").collect()}
    assert got == {i: 0 for i in range(31)} | {50: 50, 51: 50}


def test_late_events_are_left_out(spark, tmp_path):
    batches = [
        [(1, "2024-01-01 10:00:00", 7)],
        [(2, "2024-01-01 10:05:00", 7)],  # the bound that batch 1 moved is applied after this batch
        [(3, "2024-01-01 08:00:00", 7), (4, "2024-01-01 09:30:00", 7)],  # two hours late, and half an hour: only one hour is waited for
        [(5, "2024-01-01 13:00:00", 7)],
    ]
    for i, rows in enumerate(batches):
        _events(spark, tmp_path, "late", rows)
        for f in (tmp_path / "late").glob("*.parquet"):
            if f.stat().st_mtime > 2000:
                os.utime(f, (1000 + i, 1000 + i))
    stream = event_stream(spark, f"{tmp_path}/late", files_per_batch=1)
    got = drain(spark, windowed_degree(stream, "10 minutes", late="1 hour"), "append", "late").collect()
    assert sorted((r["start"].strftime("%H:%M"), r["n"]) for r in got) == [("09:30", 1), ("10:00", 2)]


def test_drain_of_nothing(spark, tmp_path):
    (tmp_path / "none").mkdir()
    stream = spark.readStream.schema("a long").parquet(str(tmp_path / "none"))
    assert drain(spark, stream, "append", "none").count() == 0


def test_experiments_make_a_graph_once(spark, monkeypatch):
    from cellgraph import experiments

    calls = []
    in_blocks = fixtures.in_blocks
    monkeypatch.setattr(fixtures, "in_blocks", lambda g, k=4: calls.append(g.kept) or in_blocks(g, k))
    found = experiments.diameters(spark, "/root/testdata/sf0.001", ["conv_turns"]).collect()
    longest = spark.read.parquet("/root/testdata/sf0.001/conversations.parquet").select("conv_id", "turn").distinct().groupBy("conv_id").count().agg({"count": "max"}).first()[0]
    assert calls == [True] and found[0]["diameter"] <= longest - 1
    cuts = []
    monkeypatch.setattr(experiments, "partition_mincut", lambda g, k: cuts.append(k) or "mincut")
    monkeypatch.setattr(experiments, "balance_cells", lambda cells, k, cores: (cells, k, cores))
    monkeypatch.setattr(experiments, "discover_cells", lambda g, place: type("Cells", (), {"cell_of": place})())
    arms = experiments.placements(None, 8)
    assert arms["mincut"]().cell_of == "mincut" and arms["balanced"]().cell_of == ("mincut", 8, 2) and cuts == [8]


def test_clusters_grow_alike_in_one_task_and_by_jobs(spark):
    from cellgraph.partition import _grow, hash_of

    numbers = np.array([0, 1, -1, 7, 1 << 40, -(1 << 63), (1 << 63) - 1])
    seed = spark.range(1).select(F.xxhash64(F.lit(5))).first()[0]
    assert hash_of(numbers, seed).tolist() == [r[0] for r in spark.createDataFrame([(int(x),) for x in numbers], "v long").coalesce(1).select(F.xxhash64(F.lit(5), "v")).collect()]
    rng = random.Random(9)
    arcs = [(a, b, rng.randrange(1, 4)) for a, b in ((rng.randrange(70), rng.randrange(70)) for _ in range(150)) if a != b] + [(3, 900, 5), (900, 3, 5)]  # 900 is no vertex
    arcs, sizes = spark.createDataFrame(arcs, "src long, dst long, n long"), spark.createDataFrame([(i, i % 3 + 1) for i in range(75)], "vid long, size long")
    for cap in (6, 25):
        one, many = ({tuple(r) for r in _grow(arcs, sizes, cap, 3, 11, Scratch(spark, "test"), n).collect()} for n in (1000, 0))
        assert one == many and len({label for _, label in one}) < 75
