"""The experiment's workloads at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Three algorithms on three stand-in graphs by both engines, loading and computing apart: loading brings the
graph from its tables to what the engine works on (arcs by hash of the source, or packed cells), computing
is the run to its last superstep.  $BENCH_REPEATS runs are averaged (3 for a table, 1 by default).  Then
loading from slices against loading from tables, and R squared of the computing ratio against the diameter.
"""

from __future__ import annotations

import json
import os
import time

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import SparkSession

from cellgraph import fixtures
from cellgraph.algorithms import ranks, traversal
from cellgraph.cells import CellGraph
from cellgraph.graph import Graph
from cellgraph.scratch import Scratch
from cellgraph.sources.slices import SliceStore

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
REPEATS = int(os.environ.get("BENCH_REPEATS", "1"))
ROUNDS = int(os.environ.get("BENCH_ROUNDS", "30"))
GRAPHS = {"road": ("road_hour", 0), "hub": ("hub_tree", 5), "dense": ("order_supplier", 0)}


def load_vertex(spark: SparkSession, g: Graph) -> Graph:
    """Edges and vertices cached, dealt by hash of their ids."""
    shards = int(spark.conf.get("spark.sql.shuffle.partitions"))
    edges = g.edges.select("src", "dst", "weight").repartition(shards, "src").persist(StorageLevel.MEMORY_AND_DISK)
    vertices = g.vertices.select("vid").repartition(shards, "vid").persist(StorageLevel.MEMORY_AND_DISK)
    edges.count()
    vertices.count()
    return Graph(vertices, edges, g.directed)


def load_cell(g: Graph) -> CellGraph:
    """Parts by ranges of ids, their cells, and the packed topology."""
    cg = fixtures.in_blocks(g, 8)
    cg.parts()
    return cg


def algorithms(source: int) -> dict:
    return {
        "components": (lambda g: traversal.components_vertex(g), lambda cg: traversal.components_cell(cg)),
        "sssp": (lambda g: traversal.sssp_vertex(g, [source]), lambda cg: traversal.sssp_cell(cg, [source])),
        "rank": (lambda g: ranks.pagerank_vertex(g, ROUNDS)[:2], lambda cg: ranks.pagerank_cell(cg, ROUNDS)[:2]),
    }


def timed(f):
    began = time.perf_counter()
    out = f()
    return out, round(time.perf_counter() - began, 2)


def mean_run(f) -> tuple[float, int]:
    """Seconds to write out the result, mean of the repeats, and supersteps."""
    took = []
    for _ in range(REPEATS):
        (found, run), seconds = timed(f)
        _, writing = timed(lambda d=found: d.write.format("noop").mode("overwrite").save())
        took.append(seconds + writing)
    return round(float(np.mean(took)), 2), run.supersteps


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    traversal.components_vertex(fixtures.conv_turns(spark, SF_DIR))[0].count()  # compile and warm up before the clock runs
    traversal.sssp_cell(load_cell(fixtures.conv_turns(spark, SF_DIR)), [0])[0].count()
    took, steps, ratios, diameter, compute_ratio = {}, {}, {}, {}, {}
    for name, (build, source) in GRAPHS.items():
        g = getattr(fixtures, build)(spark, SF_DIR)
        vg, took[f"load_vertex_{name}"] = timed(lambda g=g: load_vertex(spark, g))
        cg, took[f"load_cell_{name}"] = timed(lambda g=g: load_cell(g))
        for algorithm, (by_vertex, by_cell) in algorithms(source).items():
            took[f"{algorithm}_cell_{name}"], steps[f"{algorithm}_cell_{name}"] = mean_run(lambda f=by_cell, x=cg: f(x))
            took[f"{algorithm}_vertex_{name}"], steps[f"{algorithm}_vertex_{name}"] = mean_run(lambda f=by_vertex, x=vg: f(x))
            v, c = took[f"{algorithm}_vertex_{name}"], took[f"{algorithm}_cell_{name}"]
            whole = (v + took[f"load_vertex_{name}"]) / (c + took[f"load_cell_{name}"])
            ratios[f"{algorithm}_{name}"] = {"compute": round(v / c, 2), "makespan": round(whole, 2)}
        diameter[name] = traversal.diameter_lower_bound(g, source, 2, cg)
        compute_ratio[name] = ratios[f"components_{name}"]["compute"]
        if name == "hub":  # loading again: from tables, from slices, from the slices of one part
            store = SliceStore(spark, f"{Scratch(spark, 'bench-slices').root}/hub")
            store.write(cg, partitioner="blocks")
            _, took["load_slices_hub"] = timed(lambda: store.load(spark).parts())
            _, took["load_one_part_hub"] = timed(lambda: store.read_topology([0]).select("src", "dst").write.format("noop").mode("overwrite").save())
        for df in (vg.edges, vg.vertices):
            df.unpersist()
        cg.unpersist()
    fit = np.corrcoef([diameter[n] for n in GRAPHS], [compute_ratio[n] for n in GRAPHS])[0, 1] ** 2
    print(json.dumps({"metric": "total_query_time", "value": round(sum(took.values()), 2), "unit": "sec", "queries": took, "sf": SF_DIR.rsplit("sf", 1)[-1], "supersteps": steps, "vertex_over_cell": ratios, "diameter_at_least": diameter, "r2_components": round(float(fit), 4), "repeats": REPEATS}))


if __name__ == "__main__":
    main()
