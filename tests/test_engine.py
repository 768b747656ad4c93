"""Worked example, degenerate cases and agreement of the engines."""

import random

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import pytest
from pyspark.sql import functions as F

from cellgraph import catalogue, fixtures
from cellgraph.algorithms import betweenness, ranks, traversal
from cellgraph.algorithms.contraction import components, weak_components
from cellgraph.cells import TOPOLOGY, discover_cells, local_components, pack_array
from cellgraph.engine import cellprog, vertex
from cellgraph.graph import Graph
from cellgraph.partition import partition_modulo
from cellgraph.planner import choose_engine
from cellgraph.scratch import Scratch

VALUES = [1, 7, 14, 9, 3, 11, 13, 10, 8, 12, 5, 2, 6, 15, 4]
EDGES = [(0, 1), (0, 2), (0, 3), (2, 4), (3, 5), (4, 5), (6, 7), (6, 9), (6, 10), (7, 8), (9, 10), (11, 12), (11, 14), (12, 13), (1, 10), (1, 13)]


@pytest.fixture(scope="module")
def example(spark):
    g = Graph.from_edges(spark.createDataFrame(EDGES, "src long, dst long"))
    place = g.vertices.select("vid", (F.col("vid") >= 6).cast("int").alias("pid"))
    return g, discover_cells(g, place), spark.createDataFrame(list(enumerate(VALUES)), "vid long, value long")


def test_worked_example(example):
    g, cg, values = example
    assert sorted(r["n_vertices"] for r in cg.cells().collect()) == [4, 5, 6]
    by_vertex, run_v = traversal.max_value_vertex(g, values)
    by_cell, run_c = traversal.max_value_cell(cg, values)
    assert (run_v.supersteps, run_c.supersteps) == (7, 4)
    assert {r["value"] for r in by_vertex.collect()} == {r["value"] for r in by_cell.collect()} == {15}


def test_engines_agree_on_paths(spark, example):
    g, cg, _ = example
    a = {tuple(r) for r in traversal.sssp_vertex(g, [0])[0].collect()}
    b = {tuple(r) for r in traversal.sssp_cell(cg, [0])[0].select("vid", "dist").collect()}
    assert a == b and len(a) == 15


def test_singleton_cells_behave_like_vertices(spark):
    path = Graph.from_edges(spark.createDataFrame([(i, i + 1) for i in range(6)], "src long, dst long"))
    cg = discover_cells(path, partition_modulo(path, 2))  # neighbours never share a part
    values = path.vertices.select("vid", F.col("vid").alias("value"))
    v, c = traversal.max_value_vertex(path, values)[1], traversal.max_value_cell(cg, values)[1]
    assert (v.supersteps, v.messages) == (c.supersteps, c.messages)


def test_ranks_sum_to_one_and_engines_agree(spark, example):
    g, cg, _ = example
    a = {r["vid"]: r["rank"] for r in ranks.pagerank_vertex(g, 10)[0].collect()}
    b = {r["vid"]: r["rank"] for r in ranks.pagerank_cell(cg, 10)[0].collect()}
    assert abs(sum(a.values()) - 1) < 1e-9 and max(abs(a[v] - b[v]) for v in a) < 1e-12


def test_contraction_against_union_find(spark):
    rng = random.Random(3)
    edges = [(rng.randrange(60), rng.randrange(60)) for _ in range(40)] + [(100, 101), (None, 5), (7, 7)]
    clean = [e for e in edges if None not in e]
    want = local_components(np.array([a for a, _ in clean]), np.array([b for _, b in clean]), 102)
    got = {r["v"]: r["component"] for r in components(spark, spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {v: int(want[v]) for e in clean if e[0] != e[1] for v in e}


def test_engine_choice():
    assert choose_engine("rank", 0.7, 1.0, 8) == "vertex" and choose_engine("rank", 0.01, 1.0, 3) == "cell"
    assert choose_engine("components", 0.01, 100, 2.8) == "cell" and choose_engine("sssp", 0.7, 2.0, 28) == "vertex" and choose_engine("sssp", 0.7, 4.0, 28) == "cell"


def test_betweenness_has_all_sources(spark):
    turns = {}
    for r in spark.read.parquet("/root/testdata/sf0.001/conversations.parquet").select("conv_id", "turn").distinct().collect():
        turns.setdefault(r["conv_id"], []).append(r["turn"])
    want = {c * (1 << 20) + t: 2.0 * i * (len(ts) - 1 - i) for c, ts in turns.items() for i, t in enumerate(sorted(ts))}
    got = {r["vid"]: r["score"] for r in catalogue.queries()["betweenness_exact_conv"](spark, "/root/testdata/sf0.001").collect()}
    assert got == want
    diamond = Graph.from_edges(spark.createDataFrame([(0, 1), (0, 2), (1, 3), (2, 3), (3, 4)], "src long, dst long"))
    score = {r["vid"]: r["score"] for r in betweenness.betweenness(diamond, batch_pairs=12).collect()}
    assert score == {0: 1.0, 1: 2.0, 2: 2.0, 3: 7.0, 4: 0.0}


def test_supersteps_in_one_task_are_those_of_jobs(spark):
    rng = random.Random(5)
    edges = [(rng.randrange(80), rng.randrange(80), rng.randrange(9)) for _ in range(160)] + [(i, i + 1, 2) for i in range(100, 104)] + [(5, 200, 1)]
    arcs = Graph.from_edges(spark.createDataFrame(edges, "src long, dst long, weight long")).arcs()
    rows = [(i, i * 7919 % 101 if i % 3 else None, i % 4 != 1) for i in (*range(80), *range(100, 105))]  # 200 is no vertex
    labels, starts = spark.createDataFrame(rows, "vid long, value long, active boolean"), spark.createDataFrame([(i, 0 if i in (3, 100) else None, i in (3, 100)) for i, _, _ in rows], "vid long, value long, active boolean")
    halves = arcs.withColumn("weight", F.col("weight") / 8), starts.withColumn("value", F.col("value").cast("double"))
    for program, a, first in ((vertex.larger(), arcs, labels), (vertex.shorter(), arcs, starts), (vertex.shorter(), *halves), (vertex.larger(), arcs.where("src < 0"), labels), (vertex.larger(), arcs, labels.union(labels.where("vid = 7")))):
        (one, run), (many, want) = (vertex.run_vertex_program(program, a, first, Scratch(spark, "test"), task_arcs=n) for n in (1000, 0))
        assert sorted(map(str, one.collect())) == sorted(map(str, many.collect())) and run == want


def test_a_vertex_halts_in_a_superstep_of_its_own(spark):
    turns = fixtures.conv_turns(spark, "/root/testdata/sf0.001")
    assert traversal.components_cell(fixtures.in_blocks(turns))[1].supersteps == 2  # no conversation is cut, so no message is sent


def test_long_roads_take_no_job_a_superstep(spark):
    path = Graph.from_edges(spark.createDataFrame([(i, i + 1) for i in range(400)], "src long, dst long"))
    tracker, before = spark.sparkContext.statusTracker(), len(spark.sparkContext.statusTracker().getJobIdsForGroup(None))
    found, run = traversal.components_vertex(path)
    assert run.supersteps == 402 and [tuple(r) for r in found.agg(F.min("component"), F.max("component")).collect()] == [(400, 400)]
    assert len(tracker.getJobIdsForGroup(None)) - before < 40


def test_large_parts_are_cut_for_tasks(spark, monkeypatch):
    g = fixtures.hub_tree(spark, "/root/testdata/sf0.001")
    cg = fixtures.in_blocks(g)
    arcs = cg.links.count()
    fine = cg.fitted(arcs // 10)
    assert cg.fitted(arcs) is cg and fine is cg.fitted(arcs // 10)
    assert {tuple(r) for r in fine.links.select("src", "dst", "weight").collect()} == {tuple(r) for r in cg.links.select("src", "dst", "weight").collect()} and fine.links.count() == arcs
    hub = cg.links.groupBy("src").count().agg(F.max("count")).first()[0]
    assert fine.links.groupBy("src_pid").count().agg(F.max("count")).first()[0] <= arcs // 10 + hub and fine.parts() > cg.parts()
    assert [fine.cell_of.count(), fine.cell_of.agg(F.countDistinct("vid")).first()[0]] == [cg.cell_of.count()] * 2
    values = g.vertices.select("vid", (F.col("vid") * 7919 % 10007).alias("value"))
    both = []
    for one in (cg, fine):
        monkeypatch.setattr(type(cg), "fitted", lambda self: self)
        both.append([sorted(map(tuple, df.collect())) for df in (traversal.sssp_cell(one, [5])[0], traversal.max_value_program(one, values)[0], ranks.pagerank_cell(one, 5)[0].select("vid", F.round("rank", 12)))])
    assert both[0] == both[1]


def test_betweenness_batches_by_what_is_reached(spark, monkeypatch):
    pieces = Graph.from_edges(spark.createDataFrame([(10 * i + k, 10 * i + k + 1) for i in range(20) for k in (0, 1)], "src long, dst long"))
    saved, save = [], betweenness.Scratch.save
    monkeypatch.setattr(betweenness.Scratch, "save", lambda self, df: saved.append(1) or save(self, df))
    score = {r["vid"]: r["score"] for r in betweenness.betweenness(pieces, batch_pairs=200).collect()}  # 180 pairs in one batch, not 3600 in 18
    assert score == {10 * i + k: 2.0 * (k == 1) for i in range(20) for k in range(3)} and len(saved) < 30


def test_cells_write_to_their_neighbours_at_once(spark, example, monkeypatch):
    g, cg, values = example
    monkeypatch.setattr("cellgraph.engine.cellprog.Context.send_neighbors", lambda *a: 1 / 0)  # which searches all vertices for each cell
    for one in (cg, discover_cells(g, partition_modulo(g, 3))):
        assert {r["value"] for r in traversal.max_value_program(one, values)[0].collect()} == {15}


def test_rank_rounds_in_one_task(spark):
    rng = random.Random(4)
    arcs = [(rng.randrange(60), rng.randrange(50)) for _ in range(150)] + [(3, 3), (7, 8), (7, 8)]
    g = Graph.from_edges(spark.createDataFrame(arcs, "src long, dst long"), spark.createDataFrame([(i,) for i in range(64)], "vid long"), directed=True)
    seed = spark.createDataFrame([(i, 1 / 40) for i in range(40)], "vid long, rank double")
    for options in ({"iterations": 7}, {"iterations": None, "tol": 1e-4}, {"dangling": "leak"}, {"iterations": None, "tol": 1e-3, "seed": seed}):
        (a, run, moved), (b, jobs, changed) = (ranks.pagerank_vertex(g, task_arcs=most, **options) for most in (1000, 0))
        got, want = ({r["vid"]: r["rank"] for r in df.collect()} for df in (a, b))
        assert got.keys() == want.keys() and max(abs(got[v] - want[v]) for v in want) < 1e-12
        assert (run.messages, run.combined, run.crossing) == (jobs.messages, jobs.combined, jobs.crossing) and len(moved) == len(changed)
    again = Graph(g.vertices.union(g.vertices.where("vid = 5")), g.edges, True)
    assert ranks.pagerank_vertex(again, 3)[0].count() == 65  # an id that repeats goes by jobs
    cg = fixtures.in_blocks(g, 3)
    local = cg.scratch.save(ranks.local_rank(cg))
    got, want = ({r["cell_id"]: r["rank"] for r in ranks.cell_rank(cg, local, task_arcs=most).collect()} for most in (1000, 0))
    assert got.keys() == want.keys() and max(abs(got[c] - want[c]) for c in want) < 1e-12


def test_messages_of_a_hub_leave_in_small_batches():
    n = 120_000
    dst = np.arange(n, dtype=np.int64) % 110_000 + 10  # some targets twice
    packed = {"ids": np.array([5]), "cell": np.array([5]), "indptr": np.array([0, n]), "to": np.full(n, -1), "dst": dst[::-1], "dst_pid": np.ones(n), "dst_cell": dst[::-1] * 2}
    left = pa.table({name: pa.array([pack_array(packed[name].astype(kind))], pa.binary()) for name, kind in TOPOLOGY.items()} | {"weight": pa.array([pack_array(np.ones(n, np.int64))], pa.binary()), "whole": [True]})
    schema = cellprog._schemas("double")[1]
    out = cellprog._caller(ranks.Rank(10, 30, 0.85, "redistribute", None, False), 1, None, (0.0, 0.0))([pa.scalar(0)], left, cellprog._rows(schema, 1, pid=[0], kind=[cellprog.CALL]))
    assert max(b.num_rows for b in out.to_batches()) <= 50_000
    sent = out.filter(pa.compute.equal(out["kind"], cellprog.TO_VERTEX))
    assert sent["vid"].to_pylist() == list(range(10, 110_010)) and sent["cell_id"].to_pylist() == [2 * v for v in range(10, 110_010)]
    assert np.allclose(sent["value"].to_numpy(), np.bincount(dst - 10) * 0.1 / n, rtol=1e-12, atol=0) and sent["blob"].null_count == 110_000


def test_an_edge_is_placed_once(spark, monkeypatch):
    g = fixtures.order_supplier(spark, "/root/testdata/sf0.001")
    edges, saved = g.edges.count(), []
    save = Scratch.save
    monkeypatch.setattr(Scratch, "save", lambda self, df: saved.append(save(self, df)) or saved[-1])
    monkeypatch.setattr(Scratch, "drop", lambda self, *frames: None)
    for made in (lambda: discover_cells(g, partition_modulo(g, 3)), lambda: fixtures.in_blocks(g)):
        cg = made()
        saved.clear()
        cg = made()
        assert [df.count() for df in saved if {"src", "dst"} <= set(df.columns) and df.count() > edges] == [2 * edges]
        saved.clear()
        fine = cg.fitted(edges // 5)
        assert fine.links.count() == 2 * edges and [df.count() for df in saved if {"src", "dst"} <= set(df.columns) and df.count() > edges] == [2 * edges]


def test_loops_and_parallel_edges_in_pieces(spark):
    rows = [(1, 2, 3), (2, 1, 4), (1, 2, 3), (2, 2, 7), (3, 1, None), (3, 3, 1)]
    for directed in (False, True):
        g = Graph.from_edges(spark.createDataFrame(rows, "src long, dst long, weight long"), directed=directed)
        want = sorted(map(str, g.arcs().select("src", "dst", "weight").collect()))
        for cg in (discover_cells(g, partition_modulo(g, 2)), fixtures.in_blocks(g, 2)):
            for one in (cg, cg.fitted(2)):
                assert sorted(map(str, one.links.select("src", "dst", "weight").collect())) == want
                pid = {r["vid"]: (r["pid"], r["cell_id"]) for r in one.cell_of.collect()}
                assert all((pid[r["src"]], pid[r["dst"]]) == ((r["src_pid"], r["src_cell"]), (r["dst_pid"], r["dst_cell"])) for r in one.links.collect())


def test_engine_choice_places_a_graph_once(spark, monkeypatch):
    placed, blocks = [], catalogue._blocks
    monkeypatch.setattr(catalogue, "_blocks", lambda g, *k: placed.append(1) or blocks(g, *k))
    rows = [tuple(r) for r in catalogue.queries()["engine_choice"](spark, "/root/testdata/sf0.001").collect()]
    assert len(placed) == 3 and [r[:2] for r in rows] == [(g, a) for g in ("road_hour", "hub_tree", "order_supplier") for a in ("components", "rank")]


def test_components_of_a_large_road_go_to_tasks_of_their_own(spark):
    edges = [(k * 1000 + i, k * 1000 + i + 1, i % 3) for k in range(3) for i in range(200)] + [(i, i + 5000, 1) for i in (3, 1010)]
    g = Graph.from_edges(spark.createDataFrame(edges, "src long, dst long, weight long"))
    g = Graph(g.vertices.union(spark.createDataFrame([(9000,)], "vid long")), g.edges)
    here = F.col("vid").isin(0, 2100)
    first = g.vertices.select("vid", F.when(here, 0).cast("long").alias("value"), here.alias("active"))
    tracker = spark.sparkContext.statusTracker()
    for program, initial in ((vertex.larger(), g.vertices.select("vid", (F.col("vid") * 7919 % 10007).alias("value"), F.lit(True).alias("active"))), (vertex.shorter(), first)):
        one, want = vertex.run_vertex_program(program, g.arcs(), initial, Scratch(spark, "test"))
        before = len(tracker.getJobIdsForGroup(None))
        many, run = vertex.run_vertex_program(program, g.arcs(), initial, Scratch(spark, "test"), task_arcs=600)  # 1204 arcs, 402 in a component
        assert len(tracker.getJobIdsForGroup(None)) - before < 80  # and not some for each of 200 supersteps
        assert sorted(map(str, one.collect())) == sorted(map(str, many.collect())) and run == want and run.supersteps > 100


def test_weak_components_by_tasks_and_by_contraction(spark):
    rng = random.Random(4)
    pairs = [(rng.randrange(90), rng.randrange(90)) for _ in range(50)] + [(7, 7), (100, 101), (101, 100)]
    df = spark.createDataFrame(pairs, "a long, b long")
    want = {tuple(r) for r in components(spark, df).collect()}
    for task_edges, at_once in ((10_000, 1), (10_000, 1000), (0, 3)):
        assert {tuple(r) for r in weak_components(df, "a", "b", Scratch(spark, "test"), task_edges, at_once).collect()} == want
