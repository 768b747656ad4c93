"""Connected components by repeated contraction, for graphs given as an edge table.

Every round hangs each vertex below its least neighbour, follows those pointers to the roots and
keeps only edges between different roots.  A round at least halves the vertices that still have
edges, so the number of rounds grows with the logarithm of the vertex count and not with the
diameter.  Hubs are harmless: minima are pre-aggregated before the shuffle, and the joins read
stored tables, whose skewed partitions adaptive execution can split.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellgraph.scratch import Scratch
from cellgraph.workers import lean


def local_components(src: np.ndarray, dst: np.ndarray, n: int) -> np.ndarray:
    """Least member of each vertex's component, for vertices 0..n-1: roots hang below lesser neighbouring roots, then pointers are doubled."""
    root = np.arange(n)
    while len(src):
        a, b = root[src], root[dst]
        apart = a != b
        src, dst = src[apart], dst[apart]
        if not len(src):
            break
        np.minimum.at(root, np.maximum(a, b)[apart], np.minimum(a, b)[apart])
        while (up := root[root], (up != root).any())[1]:
            root = up
    return root


def _roots(pointers: DataFrame, scratch: Scratch) -> DataFrame:
    """Follows ``p`` (never above ``v``) until every vertex points at a root; doubling, so log(depth) joins."""
    while True:
        up = pointers.select(F.col("v").alias("p"), F.col("p").alias("pp"))
        moved = scratch.save(pointers.join(up, "p", "left").select("v", F.coalesce("pp", "p").alias("q"), "p"))
        changed = moved.where("q < p").limit(1).count()
        scratch.drop(pointers)
        pointers = moved.select("v", F.col("q").alias("p"))
        pointers._scratch_path = moved._scratch_path
        if not changed:
            return pointers


def components(spark: SparkSession, edges: DataFrame, src: str = "a", dst: str = "b", scratch: Scratch | None = None) -> DataFrame:
    """``(v, component)`` for every vertex with an edge to another one; component is the least vertex reached.

    Null endpoints and self-loops are ignored, repeated edges count once.  Vertices without such an
    edge do not appear: their component is themselves.
    """
    scratch = scratch or Scratch(spark, "components")
    live = scratch.save(
        edges.where(F.col(src).isNotNull() & F.col(dst).isNotNull())
        .select(F.least(src, dst).alias("a"), F.greatest(src, dst).alias("b"))
        .where("a < b")
        .distinct()
    )
    labels = None
    while live.limit(1).count():
        both = live.select(F.col("b").alias("v"), F.col("a").alias("p")).union(live.select(F.col("a").alias("v"), F.col("a").alias("p")))
        pointers = _roots(scratch.save(both.groupBy("v").agg(F.min("p").alias("p"))), scratch)
        of = lambda end: pointers.select(F.col("v").alias(end), F.col("p").alias(f"{end}_root"))
        nxt = scratch.save(
            live.join(of("a"), "a")
            .join(of("b"), "b")
            .select(F.least("a_root", "b_root").alias("a"), F.greatest("a_root", "b_root").alias("b"))
            .where("a < b")
            .distinct()
        )
        scratch.drop(live)
        live = nxt
        if labels is None:
            labels = pointers
        else:
            up = pointers.select(F.col("v").alias("p"), F.col("p").alias("pp"))
            merged = scratch.save(labels.join(up, "p", "left").select("v", F.coalesce("pp", "p").alias("p")))
            scratch.drop(labels, pointers)
            labels = merged
    if labels is None:
        vertex = edges.schema[src].dataType
        return spark.createDataFrame([], f"v {vertex.simpleString()}, component {vertex.simpleString()}")
    return labels.select("v", F.col("p").alias("component"))


def _stars(most: int | None):
    """A function of Arrow batches of edges: the vertices of every ``most`` edges or so (None: of all), each with the least one that these edges join it to."""
    schema = pa.schema([("v", pa.int64()), ("component", pa.int64())])

    def found(a: list[np.ndarray], b: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        src, dst = np.concatenate(a), np.concatenate(b)
        a.clear()
        b.clear()
        ids = np.unique(np.concatenate([src, dst]))
        src, dst = np.searchsorted(ids, src).astype(np.int32), np.searchsorted(ids, dst).astype(np.int32)
        root = local_components(src, dst, len(ids))
        below = np.flatnonzero(root != np.arange(len(ids))) if most else np.arange(len(ids))
        for i in range(0, len(below), 100_000):
            some = below[i : i + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(ids[root[some]])], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b, n = [], [], 0
        for batch in batches:
            a.append(batch.column(0).to_numpy())
            b.append(batch.column(1).to_numpy())
            n += batch.num_rows
            if most and n >= most:
                yield from found(a, b)
                n = 0
        if n:
            yield from found(a, b)

    return lean(run)


def weak_components(edges: DataFrame, src: str, dst: str, scratch: Scratch, task_edges: int = 10_000_000, at_once: int = 1_000_000) -> DataFrame:
    """`components`, for edges of which many in one partition touch: each task first joins what its own edges join.

    Of what is left, one task finds the components if there are at most ``task_edges``; more go by contraction.
    """
    given = edges.select(F.col(src).cast("long").alias("a"), F.col(dst).cast("long").alias("b")).where("a <> b")
    stars = scratch.save(given.mapInArrow(_stars(at_once), "v long, component long"))
    if stars.count() > task_edges:
        return components(edges.sparkSession, stars, "v", "component", scratch)
    found = scratch.save(stars.repartition(1).mapInArrow(_stars(None), "v long, component long"))
    scratch.drop(stars)
    return found
