"""Maximum value, connected components, breadth-first levels and shortest paths, on either engine."""

from __future__ import annotations

import heapq
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellgraph.cells import CellGraph
from cellgraph.engine.cellprog import CellProgram, Context, Part, run_cell_program
from cellgraph.engine.loop import Run
from cellgraph.engine.vertex import larger, run_vertex_program, shorter
from cellgraph.graph import Graph
from cellgraph.scratch import Scratch


WHOLE = ("tinyint", "smallint", "int", "bigint")


def max_value_vertex(g: Graph, values: DataFrame) -> tuple[DataFrame, Run]:
    """``values(vid, value)``; every vertex gets the greatest value of its weak component."""
    scratch = Scratch(values.sparkSession, "max-vertex")
    arcs = scratch.save(g.weak().arcs().where("src <> dst"))
    return run_vertex_program(larger(), arcs, values.withColumn("active", F.lit(True)), scratch)


def max_value_cell(cg: CellGraph, values: DataFrame) -> tuple[DataFrame, Run]:
    """The same; only one value per cell and the edges between cells take part in the supersteps."""
    inner = cg.cell_of.join(values, "vid").groupBy(F.col("cell_id").alias("vid")).agg(F.max("value").alias("value")).withColumn("active", F.lit(True))
    between = cg.cell_edges()
    if cg.graph.directed:
        between = between.unionByName(between.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "n", "min_weight"))
    arcs = cg.scratch.save(between.select("src", "dst", F.col("min_weight").alias("weight")).dropDuplicates(["src", "dst"]))
    settled, run = run_vertex_program(larger(), arcs, inner, cg.scratch)
    return cg.cell_of.join(settled.withColumnRenamed("vid", "cell_id"), "cell_id").select("vid", "value"), run


def components_vertex(g: Graph) -> tuple[DataFrame, Run]:
    """``(vid, component)``: the greatest vid of the weak component."""
    found, run = max_value_vertex(g, g.vertices.select("vid", F.col("vid").alias("value")))
    return found.withColumnRenamed("value", "component"), run


def components_cell(cg: CellGraph) -> tuple[DataFrame, Run]:
    found, run = max_value_cell(cg, cg.graph.vertices.select("vid", F.col("vid").alias("value")))
    return found.withColumnRenamed("value", "component"), run


def components_uncached(read: Callable[[], Graph]) -> DataFrame:
    """`components_vertex` as a chain of jobs that keep nothing but the labels: each round reads the graph anew and rewrites all labels."""
    g = read()
    scratch = Scratch(g.vertices.sparkSession, "uncached")
    labels = scratch.save(g.vertices.select("vid", F.col("vid").alias("component")))
    while True:
        sent = read().weak().arcs().join(labels.withColumnRenamed("vid", "src"), "src").groupBy(F.col("dst").alias("vid")).agg(F.max("component").alias("new"))
        grown = F.coalesce(F.col("new") > F.col("component"), F.lit(False))
        nxt, got = scratch.counted(labels.join(sent, "vid", "left").select("vid", F.greatest("component", "new").alias("component"), grown.alias("grown")), n=F.count(F.when(F.col("grown"), 1)))
        scratch.drop(labels)
        labels = nxt.select("vid", "component")
        labels._scratch_path = nxt._scratch_path
        if not got["n"]:
            return labels


def component_stats(labels: DataFrame) -> DataFrame:
    return labels.groupBy("component").agg(F.count(F.lit(1)).alias("n"))


def _cost(g: Graph, weight: bool):
    """The arcs' costs in their own type: whole weights as long, others as double; arcs of null weight cannot be walked."""
    if not weight:
        return g.arcs().where("src <> dst").select("src", "dst", F.lit(1).cast("long").alias("weight"))
    kind = "long" if dict(g.edges.dtypes)["weight"] in WHOLE else "double"
    arcs = g.arcs().where("src <> dst and weight is not null").select("src", "dst", F.col("weight").cast(kind).alias("weight"))
    return arcs.where(~F.isnan("weight")) if kind == "double" else arcs


def _least_costs(g: Graph, weight: bool) -> DataFrame:
    return _cost(g, weight).groupBy("src", "dst").agg(F.min("weight").alias("weight"))


def _refuse_negative(arcs: DataFrame) -> None:
    if arcs.where("weight < 0").limit(1).count():
        raise ValueError("weights must not be negative")


def sssp_vertex(g: Graph, sources: list[int], weight: bool = False, arcs: DataFrame | None = None) -> tuple[DataFrame, Run]:
    """``(vid, dist)`` of the reached vertices, in the type of the weights; unit weights unless ``weight``; ``arcs``: the distinct ones, if made before."""
    scratch = Scratch(g.vertices.sparkSession, "sssp-vertex")
    arcs = scratch.save(_least_costs(g, weight)) if arcs is None else arcs
    if weight:
        _refuse_negative(arcs)
    here = F.col("vid").isin(sources)
    initial = g.vertices.select("vid", F.when(here, F.lit(0).cast(dict(arcs.dtypes)["weight"])).alias("value"), here.alias("active"))
    found, run = run_vertex_program(shorter(), arcs, initial, scratch)
    return found.where("value is not null").withColumnRenamed("value", "dist"), run


class ShortestPaths(CellProgram):
    """Every call searches its part from all improved vertices at once and tells each remote vertex its best value.

    ``local`` is the search inside a part: 'relax' lowers all far ends of the changed vertices at once
    until none changes, 'heap' settles vertices in order of distance.
    """

    merge = "min"

    def __init__(self, weighted: bool, whole: bool, local: str = "relax"):
        if local not in ("relax", "heap"):
            raise ValueError(local)
        self.weighted, self.local = weighted, local
        self.dtype = "bigint" if whole or not weighted else "double"
        self.far = np.iinfo(np.int64).max if self.dtype == "bigint" else np.inf

    def start(self, part: Part) -> np.ndarray:
        return np.full(len(part.ids), self.far)

    def has_value(self, value: np.ndarray) -> np.ndarray:
        return value < self.far

    def compute(self, part: Part, ctx: Context) -> None:
        value = part.value
        better = part.told_value < value[part.told]
        frontier = part.told[better]
        value[frontier] = part.told_value[better]
        cost = part.weight if self.weighted else np.ones(len(part.dst), dtype=value.dtype)
        walkable = cost >= 0  # neither the mark of a null weight
        changed = np.zeros(len(value), dtype=bool)
        changed[frontier] = True
        (self._relax if self.local == "relax" else self._settle)(part, ctx, frontier, cost, walkable, changed)
        places = np.flatnonzero(changed)
        arcs, owner = part.arcs_of(places)
        cut = (part.to[arcs] < 0) & walkable[arcs]
        arcs, owner = arcs[cut], owner[cut]
        ctx.send_arcs(part, arcs, value[places[owner]] + cost[arcs])

    def _relax(self, part: Part, ctx: Context, frontier: np.ndarray, cost: np.ndarray, walkable: np.ndarray, changed: np.ndarray) -> None:
        value = part.value
        while len(frontier):
            ctx.work += len(frontier)
            arcs, owner = part.arcs_of(frontier)
            inner = (part.to[arcs] >= 0) & walkable[arcs]
            arcs, owner = arcs[inner], owner[inner]
            to, new = part.to[arcs], value[frontier[owner]] + cost[arcs]
            less = new < value[to]
            np.minimum.at(value, to[less], new[less])
            frontier = np.unique(to[less])
            changed[frontier] = True

    def _settle(self, part: Part, ctx: Context, frontier: np.ndarray, cost: np.ndarray, walkable: np.ndarray, changed: np.ndarray) -> None:
        value, indptr, to = part.value, part.indptr, part.to
        heap = [(value[v], v) for v in frontier]
        heapq.heapify(heap)
        while heap:
            d, v = heapq.heappop(heap)
            if d > value[v]:
                continue
            ctx.work += 1
            for e in range(indptr[v], indptr[v + 1]):
                u = to[e]
                if u >= 0 and walkable[e] and d + cost[e] < value[u]:
                    value[u] = d + cost[e]
                    changed[u] = True
                    heapq.heappush(heap, (value[u], u))


def sssp_cell(cg: CellGraph, sources: list[int], weight: bool = False, local: str = "relax") -> tuple[DataFrame, Run]:
    """Shortest paths by cells: each superstep settles whole parts, messages cross part borders only."""
    whole = dict(cg.links.dtypes)["weight"] in WHOLE
    if weight:
        _refuse_negative(cg.links)
    cg = cg.fitted()
    seeds = cg.cell_of.where(F.col("vid").isin(sources)).select("pid", "cell_id", "vid", F.lit(0).alias("value"))
    found, run = run_cell_program(ShortestPaths(weight, whole, local), cg, seeds)
    return found.select("vid", F.col("value").alias("dist")), run


def with_parents(g: Graph, distances: DataFrame, weight: bool = False) -> DataFrame:
    """``(vid, dist, parent)``: the least neighbour through which the distance is reached; null at sources.

    Fractional distances are sums along a path, and a parent's distance plus the arc's weight is that very sum.
    Over arcs of weight 0 a parent's distance is the same as its child's.
    """
    arcs = _cost(g, weight).withColumnRenamed("weight", "w")
    tight = arcs.join(distances.select(F.col("vid").alias("src"), F.col("dist").alias("d0")), "src").join(distances.select(F.col("vid").alias("dst"), F.col("dist").alias("d1")), "dst").where("d0 + w = d1 and d1 > 0")
    return distances.join(tight.groupBy(F.col("dst").alias("vid")).agg(F.min("src").alias("parent")), "vid", "left").select("vid", "dist", "parent")


class Greatest(CellProgram):
    """The greatest value of the component, cell by cell: every cell holds one value and tells the cells it touches when that rises.

    The first superstep calls all cells; afterwards a cell sleeps until a neighbour writes to it.
    """

    merge, dtype = "max", "bigint"
    least = np.iinfo(np.int64).min

    def start(self, part: Part) -> np.ndarray:
        return np.full(len(part.ids), self.least)

    def has_value(self, value: np.ndarray) -> np.ndarray:
        return value > self.least

    def compute(self, part: Part, ctx: Context) -> None:
        names, own = np.unique(part.cell, return_inverse=True)
        before = np.full(len(names), self.least)
        np.maximum.at(before, own, part.value)
        best = before.copy()
        np.maximum.at(best, own[part.told], part.told_value)  # the vertices' own values, in the first superstep
        for cell, value in part.cell_messages:
            at = np.searchsorted(names, cell)
            best[at] = max(best[at], value)
        ctx.work += len(names)
        part.value[:] = best[own]
        ctx.send_cells(part, own, best, best > before)


def max_value_program(cg: CellGraph, values: DataFrame) -> tuple[DataFrame, Run]:
    """`max_value_cell` as a cell program with messages from cell to cell; for undirected graphs and whole values."""
    cg = cg.fitted()
    first = cg.cell_of.join(values, "vid").select("pid", "cell_id", "vid", "value")
    found, run = run_cell_program(Greatest(), cg, first)
    return found.select("vid", "value"), run


def _diameter_sweep(dist: DataFrame) -> tuple[int, int]:
    row = dist.agg(F.max(F.struct("dist", "vid")).alias("m")).first()["m"]
    return (row["dist"], row["vid"]) if row else (0, 0)


def cell_diameter(cg: CellGraph, sweeps: int = 2) -> int:
    """Lower bound of the diameter of the cell graph: the most cells that a message passes on its way; 0 without cut edges."""
    between = cg.scratch.save(cg.cell_edges().select("src", "dst", F.lit(1).cast("long").alias("weight")))
    if not between.limit(1).count():
        return 0
    g = Graph.from_edges(between, directed=True)
    # the cell graph of an undirected graph has every arc in both directions already
    g = (g.weak() if cg.graph.directed else g).stored()
    # from the cell with most cut edges, then from the farthest one
    start = between.groupBy("src").count().orderBy(F.desc("count"), "src").first()["src"]
    return diameter_lower_bound(g, start, sweeps)


def eccentricity(g: Graph, source: int, arcs: DataFrame | None = None) -> tuple[int, int]:
    """(greatest distance from the source, a vertex at that distance); ``arcs`` as of `sssp_vertex`."""
    return _diameter_sweep(sssp_vertex(g, [source], arcs=arcs)[0])


def diameter_lower_bound(g: Graph, start: int, sweeps: int = 2, cg: CellGraph | None = None) -> int:
    """Repeated sweeps, each from where the last ended; by the cell engine if ``cg``, the same graph undirected, is given."""
    best, at = 0, start
    by_cells = cg is not None and not cg.graph.directed
    arcs = None if by_cells else Scratch(g.vertices.sparkSession, "diameter").save(_least_costs(g, False))
    for _ in range(sweeps):
        far, at = _diameter_sweep(sssp_cell(cg, [at])[0]) if by_cells else eccentricity(g, at, arcs)
        best = max(best, far)
    return best
