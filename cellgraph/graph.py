"""Graphs as two DataFrames, and builders from tables."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cellgraph.scratch import Scratch


def _ends(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()


@dataclass
class Graph:
    """``vertices(vid BIGINT, ..)`` and ``edges(src BIGINT, dst BIGINT, weight, ..)``.

    An undirected graph holds each edge once, in either direction.  Self-loops, parallel edges and
    isolated vertices are legal; null endpoints are dropped by `from_edges`.
    """

    vertices: DataFrame
    edges: DataFrame
    directed: bool = False
    of_edges: bool = False  # the vertices are the ends of the edges
    kept: bool = False  # both tables are written

    @classmethod
    def from_edges(cls, edges: DataFrame, vertices: DataFrame | None = None, directed: bool = False) -> Graph:
        if "weight" not in edges.columns:
            edges = edges.withColumn("weight", F.lit(1).cast("long"))
        edges = edges.where("src is not null and dst is not null").withColumns({"src": F.col("src").cast("long"), "dst": F.col("dst").cast("long")})
        if vertices is None:
            return cls(_ends(edges), edges, directed, True)
        return cls(vertices.where("vid is not null"), edges, directed)

    def stored(self) -> Graph:
        """The same graph, its tables written once: what made them is not repeated by each who reads them."""
        if self.kept:
            return self
        scratch = Scratch(self.edges.sparkSession, "graph")
        edges = scratch.save(self.edges)
        return Graph(scratch.save(_ends(edges) if self.of_edges else self.vertices), edges, self.directed, self.of_edges, True)

    def arcs(self) -> DataFrame:
        """Edges in the directions in which messages travel: as given, or both."""
        if self.directed:
            return self.edges
        others = [c for c in self.edges.columns if c not in ("src", "dst")]
        # what makes an edge runs once, the edge is turned round afterwards
        way = lambda a, b: F.struct(F.col(a).alias("src"), F.col(b).alias("dst"), *others)
        return self.edges.select(F.inline(F.array(way("src", "dst"), way("dst", "src"))))

    def weak(self) -> Graph:
        return Graph(self.vertices, self.edges, False)

    def filter_vertices(self, condition) -> Graph:
        """The sub-graph induced by the vertices for which the condition holds."""
        kept = self.vertices.where(condition)
        ends = kept.select("vid")
        edges = self.edges.join(ends.withColumnRenamed("vid", "src"), "src", "left_semi").join(ends.withColumnRenamed("vid", "dst"), "dst", "left_semi")
        return Graph(kept, edges, self.directed)

    def filter_edges(self, condition) -> Graph:
        return Graph(self.vertices, self.edges.where(condition), self.directed)

    def degrees(self) -> DataFrame:
        """``(vid, degree)`` by arcs that leave a vertex, isolated ones included."""
        out = self.arcs().groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("degree"))
        return self.vertices.select("vid").join(out, "vid", "left").select("vid", F.coalesce("degree", F.lit(0)).alias("degree"))


def from_foreign_key(df: DataFrame, child, parent, weight=None) -> DataFrame:
    """One edge from each row's own id to the id that it refers to."""
    return df.select(child.alias("src"), parent.alias("dst"), (F.lit(1).cast("long") if weight is None else weight).alias("weight"))


def from_succession(df: DataFrame, group: list[str], order: list[str], vid: str, weight=None) -> DataFrame:
    """An edge from each row to the next one of its group."""
    w = Window.partitionBy(*group).orderBy(*order)
    nxt = df.withColumn("_next", F.lead(F.struct(*df.columns)).over(w)).where("_next is not null")
    return nxt.select(F.col(vid).alias("src"), F.col(f"_next.{vid}").alias("dst"), (F.lit(1).cast("long") if weight is None else weight(F.col("_next"))).alias("weight"))


def from_equal(df: DataFrame, vid: str, value: str) -> DataFrame:
    """Rows of equal value hang below the least of them: a star per value, never all pairs."""
    least = df.where(F.col(value).isNotNull()).groupBy(value).agg(F.min(vid).alias("dst"), F.count(F.lit(1)).alias("n")).where("n > 1")
    return df.join(least, value).where(F.col(vid) != F.col("dst")).select(F.col(vid).alias("src"), "dst", F.lit(1).cast("long").alias("weight"))


def from_bipartite(df: DataFrame, left, right, weight=None) -> DataFrame:
    """Distinct pairs as edges; ``weight`` aggregates the rows of a pair."""
    pairs = df.select(left.alias("src"), right.alias("dst"), *([] if weight is None else [weight.alias("w")]))
    return pairs.groupBy("src", "dst").agg((F.lit(1).cast("long") if weight is None else F.sum("w")).alias("weight"))


def from_similarity(df: DataFrame, vid: str, vec: str, least: float, blocks: int = 8) -> DataFrame:
    """``(src, dst, weight)`` with src below dst for every pair of vectors whose inner product is at least ``least``.

    Exact: rows are dealt to ``blocks`` blocks by hash and every two blocks meet once as matrices, so that
    work is quadratic in the rows and each row travels ``blocks`` times; choose blocks by rows over what
    a task holds.  Null vectors take no part.
    """
    home = F.pmod(F.xxhash64(vid), F.lit(blocks)).cast("int")
    meets = F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda j: F.least("b", j) * blocks + F.greatest("b", j))
    rows = df.where(F.col(vec).isNotNull()).select(F.col(vid).cast("long").alias("vid"), F.col(vec).cast("array<double>").alias("vec"), home.alias("b"))

    def meet(table: pa.Table) -> pa.Table:
        ids, block = table.column("vid").to_numpy(), table.column("b").to_numpy()
        x = np.array(table.column("vec").to_pylist())
        lo, hi = block == block.min(), block == block.max()
        # a block meets itself in one group, in which lo and hi are all rows
        products = x[lo] @ x[hi].T
        i, j = np.nonzero(products >= least)
        a, b = ids[lo][i], ids[hi][j]
        own = (block[lo][i] != block[hi][j]) | (a < b)
        if block.min() == block.max() and table.column("pair")[0].as_py() // blocks != table.column("pair")[0].as_py() % blocks:
            own[:] = False  # only one of the two blocks has rows
        return pa.table({"src": np.minimum(a, b)[own], "dst": np.maximum(a, b)[own], "weight": np.ones(int(own.sum()), dtype=np.int64)})

    return rows.withColumn("pair", F.explode(meets)).groupBy("pair").applyInArrow(meet, "src long, dst long, weight long")
