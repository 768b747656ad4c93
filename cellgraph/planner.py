"""Which engine suits a graph and an algorithm."""

from __future__ import annotations

from cellgraph import metrics
from cellgraph.algorithms.traversal import cell_diameter, diameter_lower_bound
from cellgraph.cells import CellGraph


def choose_engine(algorithm: str, cut_ratio: float, rounds_ratio: float, mean_degree: float) -> str:
    """'cell' or 'vertex'.

    ``rounds_ratio`` is the graph's diameter over that of its cell graph: what a traversal saves in
    supersteps.  On dense graphs a superstep of a cell scans many arcs for each vertex that it improves, so
    more rounds must be saved.  Rank has the same rounds on both engines; there only few cut arcs pay.
    """
    if algorithm == "rank":
        return "cell" if cut_ratio < 0.3 else "vertex"
    return "cell" if rounds_ratio >= (1.5 if mean_degree <= 4 else 3.0) else "vertex"


def plan(cg: CellGraph, algorithm: str) -> str:
    """`choose_engine` by the measures of a placed graph: cut ratio, mean degree, and lower bounds of both diameters from two sweeps."""
    arcs = metrics.cut(cg).first()
    n = cg.cell_of.count()
    if not n or not arcs["edges"]:
        return "vertex"
    if algorithm == "rank":
        return choose_engine(algorithm, arcs["cut_ratio"], 1.0, arcs["edges"] / n)
    start = cg.graph.degrees().orderBy("degree", ascending=False).first()["vid"]
    graph = diameter_lower_bound(cg.graph.weak(), start, 2, cg)
    return choose_engine(algorithm, arcs["cut_ratio"], graph / max(1, cell_diameter(cg)), arcs["edges"] / n)
