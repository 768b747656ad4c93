"""Cells: the weakly connected pieces of each part, with their cut edges and the graph between them."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellgraph.algorithms.contraction import components, local_components
from cellgraph.graph import Graph
from cellgraph.scratch import Scratch


#: Packed columns of a part's topology row and their types.
TOPOLOGY = {"ids": np.int64, "cell": np.int64, "indptr": np.int64, "to": np.int32, "dst": np.int64, "dst_pid": np.int32, "dst_cell": np.int64}


def pack_array(a: np.ndarray) -> bytes:
    """The array's bytes, compressed, after their number: a part is one row, which Spark copies several times on its way."""
    raw = a.tobytes()
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def unpack_array(packed: bytes, kind: type) -> np.ndarray:
    size = int.from_bytes(packed[:8], "little")
    return np.frombuffer(pa.decompress(memoryview(packed)[8:], decompressed_size=size, codec="zstd"), dtype=kind)


def topology_arrays(row: dict) -> dict[str, np.ndarray]:
    """The arrays of one topology row."""
    out = {name: unpack_array(row[name], kind) for name, kind in TOPOLOGY.items()}
    return out | {"weight": unpack_array(row["weight"], np.int64 if row["whole"] else np.float64)}


def _in_pieces(cuts: dict[int, np.ndarray], pieces: int) -> Callable:
    """Functions of Arrow batches that put the pieces of parts, cut at these ids, in the place of the parts; parts without cuts have one piece."""

    def replacing(ids: list[str], pids: list[str]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for vid, pid in zip(ids, pids, strict=True):
                    at, part = b.schema.get_field_index(pid), b.column(pid).to_numpy()
                    to = part * pieces
                    for p in np.unique(part):
                        if p in cuts:
                            here = np.flatnonzero(part == p)
                            to[here] += np.searchsorted(cuts[p], b.column(vid).to_numpy()[here])
                    b = b.set_column(at, pid, pa.array(to, pa.int32()))
                yield b

        return run

    return replacing


@dataclass
class CellGraph:
    """A graph cut into parts and cells; every table is stored."""

    graph: Graph
    cell_of: DataFrame  # vid, pid, cell_id
    links: DataFrame  # arcs with src_pid, src_cell, dst_pid, dst_cell, weight
    scratch: Scratch
    _topology: DataFrame | None = None
    _parts: int | None = None
    _fitted: dict[int, CellGraph] = field(default_factory=dict)

    def topology(self) -> DataFrame:
        """One row per part: its vertices and arcs as packed arrays, cached where the part's calls run.

        Weights keep their type, whole or floating; a null weight becomes the least number, or NaN.
        """
        if self._topology is None:
            whole = dict(self.links.dtypes)["weight"] in ("tinyint", "smallint", "int", "bigint")

            def build(key, left: pa.Table, right: pa.Table) -> pa.Table:
                ids = left.column("vid").to_numpy()
                order = np.argsort(ids)
                ids, cell = ids[order], left.column("cell_id").to_numpy()[order]
                src = np.searchsorted(ids, right.column("src").to_numpy()) if right.num_rows else np.zeros(0, np.int64)
                by = np.argsort(src, kind="stable")
                at = lambda c: right.column(c).to_numpy()[by] if right.num_rows else np.zeros(0, np.int64)
                dst, dst_pid = at("dst"), at("dst_pid")
                to = np.where(dst_pid == key[0].as_py(), np.minimum(np.searchsorted(ids, dst), len(ids) - 1), -1)
                arrays = {"ids": ids, "cell": cell, "indptr": np.searchsorted(src[by], np.arange(len(ids) + 1)), "to": to, "dst": dst, "dst_pid": dst_pid, "dst_cell": at("dst_cell")}
                cols = {name: pa.array([pack_array(arrays[name].astype(kind))], pa.binary()) for name, kind in TOPOLOGY.items()}
                weight = pack_array(at("weight").astype(np.int64 if whole else np.float64))
                return pa.table({"pid": pa.array([key[0].as_py()], pa.int32()), **cols, "weight": pa.array([weight], pa.binary()), "whole": pa.array([whole])})

            weight = F.coalesce(F.col("weight").cast("long"), F.lit(-(1 << 63))) if whole else F.coalesce(F.col("weight").cast("double"), F.lit(float("nan")))
            arcs = self.links.select(F.col("src_pid").alias("pid"), "src", "dst", "dst_pid", "dst_cell", weight.alias("weight"))
            schema = f"pid int, {', '.join(f'{name} binary' for name in TOPOLOGY)}, weight binary, whole boolean"
            packed = self.scratch.save(self.cell_of.groupBy("pid").cogroup(arcs.groupBy("pid")).applyInArrow(build, schema))
            shards = int(packed.sparkSession.conf.get("spark.sql.shuffle.partitions"))
            self._topology = packed.repartition(shards, "pid").persist(StorageLevel.MEMORY_AND_DISK)
        return self._topology

    def parts(self) -> int:
        """How many parts have vertices."""
        if self._parts is None:
            self._parts = self.topology().count()
        return self._parts

    def unpersist(self) -> None:
        for fine in self._fitted.values():
            fine.unpersist()
        if self._topology is not None:
            self._topology.unpersist()
            self._topology = None

    def fitted(self, most_arcs: int = 500_000) -> CellGraph:
        """The same graph in parts that a task can hold: each part of more arcs is cut by ranges of ids into pieces of about that many.

        What a program computes for the vertices does not depend on it, while cells and supersteps are those of the
        pieces; without such a part it is this graph itself.  A piece holds all arcs of its vertices, however many one has.
        """
        if most_arcs not in self._fitted:
            held = self.links.groupBy("src_pid").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
            pieces = -(-held // most_arcs)
            if pieces < 2:
                return self
            points = F.percentile_approx("src", [i / pieces for i in range(1, pieces)], 10_000)
            cuts = self.links.groupBy("src_pid").agg(points.alias("cuts"), F.count(F.lit(1)).alias("n")).where(F.col("n") > most_arcs)
            piece = _in_pieces({r["src_pid"]: np.array(r["cuts"]) for r in cuts.collect()}, pieces)
            scratch = Scratch(self.links.sparkSession, "cells")
            place = scratch.save(self.cell_of.select("vid", "pid").mapInArrow(piece(["vid"], ["pid"]), "vid long, pid int"))
            once, both_ways = (self.links, F.lit(False)) if self.graph.directed else (self.links.where("src <= dst"), F.col("src") < F.col("dst"))
            placed = once.select("src", "dst", "weight", "src_pid", "dst_pid")
            placed = scratch.save(placed.mapInArrow(piece(["src", "dst"], ["src_pid", "dst_pid"]), placed.schema))
            fine = _found_cells(self.graph, place, placed, both_ways, scratch, 5_000_000)
            self._fitted[most_arcs] = fine
        return self._fitted[most_arcs]

    @property
    def local_edges(self) -> DataFrame:
        return self.links.where("src_pid = dst_pid")

    @property
    def cut_edges(self) -> DataFrame:
        return self.links.where("src_pid <> dst_pid")

    def cells(self) -> DataFrame:
        """``(cell_id, pid, n_vertices)``."""
        return self.cell_of.groupBy("cell_id", "pid").agg(F.count(F.lit(1)).alias("n_vertices"))

    def cell_edges(self) -> DataFrame:
        """``(src, dst, n, min_weight)`` between different cells, by arcs."""
        return self.cut_edges.groupBy(F.col("src_cell").alias("src"), F.col("dst_cell").alias("dst")).agg(F.count(F.lit(1)).alias("n"), F.min("weight").alias("min_weight"))


def discover_cells(g: Graph, assignment: DataFrame, part_edge_cap: int = 5_000_000, part_of: Callable[[str], Column] | None = None) -> CellGraph:
    """Finds the cells of every part and resolves each arc's far end.

    A part of at most ``part_edge_cap`` inner edges is searched in one Arrow group; if any
    part has more, all go by distributed contraction, which holds no part in memory.  A cell's id is its least vertex.
    ``part_of`` says ``assignment`` as an expression of an id, if it can be said so; a graph whose vertices are the ends of its edges then needs no join for it.
    """
    scratch = Scratch(g.vertices.sparkSession, "cells")
    place = scratch.save(assignment.select("vid", "pid"))
    edges = g.edges.select("src", "dst", "weight")
    if part_of is not None and g.of_edges:
        return _found_cells(g, place, edges.select("*", part_of("src").alias("src_pid"), part_of("dst").alias("dst_pid")), F.lit(not g.directed), scratch, part_edge_cap)
    end = lambda name: place.select(F.col("vid").alias(name), F.col("pid").alias(f"{name}_pid"))
    return _found_cells(g, place, scratch.save(edges.join(end("src"), "src").join(end("dst"), "dst")), F.lit(not g.directed), scratch, part_edge_cap)


def _found_cells(g: Graph, place: DataFrame, placed: DataFrame, both_ways: Column, scratch: Scratch, part_edge_cap: int) -> CellGraph:
    """The cells of ``place(vid, pid)`` by ``placed(src, dst, weight, src_pid, dst_pid)``, whose rows stand for the opposite arc too where ``both_ways`` holds."""
    inner = placed.where("src_pid = dst_pid and src <> dst").select(F.col("src_pid").alias("pid"), "src", "dst")
    largest = inner.groupBy("pid").count().agg(F.max("count")).first()[0] or 0
    if largest <= part_edge_cap:

        def run(table: pa.Table) -> pa.Table:
            src, dst = (table.column(c).to_numpy() for c in ("src", "dst"))
            ids, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
            root = local_components(at[: len(src)], at[len(src) :], len(ids))
            return pa.table({"vid": ids, "cell": ids[root]})

        found = inner.groupBy("pid").applyInArrow(run, "vid long, cell long")
    else:
        found = components(g.vertices.sparkSession, inner, "src", "dst", scratch).select(F.col("v").alias("vid"), F.col("component").alias("cell"))
    cell_of = scratch.save(place.join(found, "vid", "left").select("vid", "pid", F.coalesce("cell", "vid").alias("cell_id")))
    cell_end = lambda name: cell_of.select(F.col("vid").alias(name), F.col("cell_id").alias(f"{name}_cell"))
    once = placed.join(cell_end("src"), "src").join(cell_end("dst"), "dst")
    # an edge is joined once and turned round afterwards
    way = lambda a, b: F.struct(F.col(a).alias("src"), F.col(b).alias("dst"), "weight", *[F.col(f"{of}_{c}").alias(f"{name}_{c}") for name, of in (("src", a), ("dst", b)) for c in ("pid", "cell")])
    there, back = way("src", "dst"), way("dst", "src")
    links = scratch.save(once.select(F.inline(F.when(both_ways, F.array(there, back)).otherwise(F.array(there)))))
    scratch.drop(placed, place)
    return CellGraph(g, cell_of, links, scratch)
