"""Betweenness centrality from all sources (exact) or chosen ones (the sum over those)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellgraph.algorithms.contraction import components
from cellgraph.graph import Graph
from cellgraph.scratch import Scratch


def betweenness(g: Graph, sources: list[int] | None = None, batch_pairs: int = 200_000_000) -> DataFrame:
    """``(vid, score)``: shortest-path dependencies summed over the sources, all vertices if none are given; ordered pairs, ends not counted.

    Rows are keyed by source, so that all sources of a batch go together: path counts level by level
    outwards, dependencies back inwards.  A batch has about ``batch_pairs`` pairs of source and vertex that
    can reach each other by weak component.  Unit weights, parallel arcs count once.
    """
    scratch = Scratch(g.vertices.sparkSession, "betweenness")
    arcs = scratch.save(g.arcs().where("src <> dst").select("src", "dst").distinct())
    vertices = scratch.save(g.vertices.select("vid").distinct())
    starts = vertices if sources is None else vertices.where(F.col("vid").isin(sources))
    weak = components(g.vertices.sparkSession, arcs, "src", "dst", scratch).select(F.col("v").alias("vid"), "component")
    sizes = weak.groupBy("component").agg(F.count(F.lit(1)).alias("n"))
    pairs = starts.join(weak, "vid").join(sizes, "component").agg(F.sum("n")).first()[0] or 0
    batches = max(1, -(-pairs // batch_pairs))
    parts = []
    for k in range(batches):
        mine = starts.where(F.pmod(F.xxhash64("vid"), F.lit(batches)) == k)
        layers = [scratch.save(mine.select(F.col("vid").alias("source"), "vid", F.lit(1.0).alias("paths")))]
        while True:
            reached = layers[-1].join(arcs, F.col("vid") == F.col("src")).groupBy("source", F.col("dst").alias("vid")).agg(F.sum("paths").alias("paths"))
            # without directions a neighbour of a level lies in it or next to it
            seen = reduce(DataFrame.union, [x.select("source", "vid") for x in (layers if g.directed else layers[-2:])])
            layer = scratch.save(reached.join(seen, ["source", "vid"], "left_anti"))
            if not layer.limit(1).count():
                break
            layers.append(layer)
        lean, found = layers[-1].select("source", "vid", F.lit(0.0).alias("lean")), []
        for level in range(len(layers) - 1, 1, -1):
            share = layers[level].join(lean, ["source", "vid"]).select("source", F.col("vid").alias("dst"), ((1 + F.col("lean")) / F.col("paths")).alias("share"))
            back = share.join(arcs, "dst").groupBy("source", F.col("src").alias("vid")).agg(F.sum("share").alias("share"))
            lean = scratch.save(layers[level - 1].join(back, ["source", "vid"], "left").select("source", "vid", (F.col("paths") * F.coalesce("share", F.lit(0.0))).alias("lean")))
            found.append(lean)
        if found:
            parts.append(scratch.save(reduce(DataFrame.union, found).groupBy("vid").agg(F.sum("lean").alias("lean"))))
        scratch.drop(*layers, *found)
    if not parts:
        return vertices.select("vid", F.lit(0.0).alias("score"))
    total = reduce(DataFrame.union, parts).groupBy("vid").agg(F.sum("lean").alias("lean"))
    return scratch.save(vertices.join(total, "vid", "left").select("vid", F.coalesce("lean", F.lit(0.0)).alias("score")))
