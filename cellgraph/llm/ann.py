"""Approximate nearest neighbours by multiprobe p-stable hashing.

Vectors are scaled to unit length (their Euclidean order is then that of the cosine) and hashed in
each of ``tables`` tables by ``hashes`` functions floor((a.v + b) / w) with Gaussian a; the values
name a bucket.  For a query, the chance that a neighbour of cosine ``near`` falls into a cell of a
hash, against the chance of any vector, follows from the query's own projection; the sum of the
logarithms over the hashes orders all buckets, its own and the perturbed ones, by estimated success.
A table's buckets are visited in that order until such a neighbour is among them with the chance
``reach``.  Buckets that share their first hash values are stored as blocks of vectors, and a query
is sent once to each group of blocks that can hold a bucket it visits.  There, exact cosines are taken of what
lies in visited buckets, and the best k of each query go on.  The tables' candidates are merged by
id and ranked.  A query that found fewer than k is compared with all rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property, lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellgraph.llm.vectors import usable
from cellgraph.scratch import Scratch

_GRID = np.linspace(-8, 8, 3201)


@lru_cache(1)
def _normal_table() -> np.ndarray:
    return np.array([0.5 * (1 + math.erf(z / math.sqrt(2))) for z in _GRID])


def normal_share(z: np.ndarray) -> np.ndarray:
    """Cumulative share of the standard normal distribution."""
    return np.interp(z, _GRID, _normal_table(), 0.0, 1.0)


@dataclass(frozen=True)
class HashTables:
    """The random projections of all tables; the same seed gives the same tables everywhere.

    ``near`` and ``reach`` set what is visited: more for a smaller cosine or a greater chance.  A hash
    has 2 * ``levels`` cells, the outer ones open.
    """

    tables: int = 2
    hashes: int = 20
    width: float = 1.4
    levels: int = 4
    near: float = 0.35
    reach: float = 0.75
    leading: int = 2
    seed: int = 11

    @cached_property
    def _known(self) -> dict:
        return {}

    def projections(self, dim: int) -> list[tuple[np.ndarray, np.ndarray]]:
        """Directions of Gaussian length, orthogonal within a table: less redundant, same marginals in high dimension."""
        if dim not in self._known:
            rng = np.random.default_rng([self.seed, dim])
            n = min(self.hashes, dim)
            self._known[dim] = [(np.linalg.qr(rng.standard_normal((dim, n)))[0] * math.sqrt(dim), rng.random(n) * self.width) for _ in range(self.tables)]
        return self._known[dim]

    def cells(self, unit: np.ndarray, table: int) -> np.ndarray:
        """Hash values from 0 on, (n, hashes)."""
        gauss, shift = self.projections(unit.shape[1])[table]
        return np.clip(np.floor((unit @ gauss + shift) / self.width), -self.levels, self.levels - 1).astype(np.int64) + self.levels

    def group(self, cells: np.ndarray) -> np.ndarray:
        """The leading hash values as one number."""
        code = np.zeros(len(cells), dtype=np.int64)
        for j in range(min(self.leading, cells.shape[1])):
            code = code * 2 * self.levels + cells[:, j]
        return code

    def success(self, unit: np.ndarray, table: int) -> tuple[np.ndarray, np.ndarray]:
        """(log chance ratio of each cell of each hash, (n, hashes, cells); least sum that is visited, (n,))."""
        gauss, shift = self.projections(unit.shape[1])[table]
        spot = (unit @ gauss)[:, :, None]
        walls = np.arange(-self.levels, self.levels + 1) * self.width - shift[:, None]
        walls[:, 0], walls[:, -1] = -50.0, 50.0
        spread = math.sqrt(1 - self.near**2)
        there = np.maximum(np.diff(normal_share((walls[None] - self.near * spot) / spread), axis=2), 1e-9)
        ratio = np.log(there / np.maximum(np.diff(normal_share(walls), axis=1), 1e-9)[None])
        mean = (there * ratio).sum(axis=2)
        spare = ((there * ratio * ratio).sum(axis=2) - mean * mean).sum(axis=1)
        z = float(np.interp(self.reach, _normal_table(), _GRID))
        return ratio, mean.sum(axis=1) - z * np.sqrt(np.maximum(spare, 0.0))

    def groups_of(self, ratio: np.ndarray, least: np.ndarray) -> list[np.ndarray]:
        """For each query the groups that can hold a bucket it visits."""
        best = ratio[:, self.leading :, :].max(axis=2).sum(axis=1)
        bound = np.zeros((len(ratio), 1))
        for j in range(min(self.leading, ratio.shape[1])):
            bound = (bound[:, :, None] + ratio[:, j, None, :]).reshape(len(ratio), -1)
        return [np.flatnonzero(row) for row in bound + best[:, None] >= least[:, None]]

    def visited(self, ratio: np.ndarray, least: np.ndarray, cells: np.ndarray) -> np.ndarray:
        """(queries, candidates): whether the candidate's bucket is visited."""
        n, hashes, width = ratio.shape
        marks = np.zeros((len(cells), hashes * width), dtype=np.float32)
        np.put_along_axis(marks, cells + np.arange(hashes) * width, 1.0, axis=1)
        return ratio.reshape(n, -1).astype(np.float32) @ marks.T >= least[:, None]


def scaled(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x * x).sum(axis=1))[:, None]


def exact_cosine(q: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Row-by-row cosine in double precision; equal rows give equal values wherever they stand."""
    return (q * c).sum(axis=1) / (np.sqrt((q * q).sum(axis=1)) * np.sqrt((c * c).sum(axis=1)))


def best_of_block(q_ids: np.ndarray, q: np.ndarray, c_ids: np.ndarray, c: np.ndarray, k: int, visited: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query position, candidate position, cosine): each query's best k of what it visits, ties to the smaller id."""
    rough = scaled(q) @ scaled(c).T
    rough[q_ids[:, None] == c_ids[None, :]] = -np.inf
    if visited is not None:
        rough[~visited] = -np.inf
    floor = np.partition(rough, -k, axis=1)[:, -k] if c.shape[0] > k else np.full(len(q), -2.0)
    row, col = np.nonzero((rough >= np.maximum(floor, -2.0)[:, None] - 1e-9) & np.isfinite(rough))
    score = exact_cosine(q[row], c[col])
    order = np.lexsort((c_ids[col], -score, row))
    row, col, score = row[order], col[order], score[order]
    keep = np.arange(len(row)) - np.searchsorted(row, row) < k
    return row[keep], col[keep], score[keep]


class Best:
    """The best k candidates of every query met so far in a task; holds at most ``rows`` of them and some unsorted ones."""

    def __init__(self, k: int, rows: int = 500_000, loose: int = 100_000):
        self.k, self.rows, self.loose = k, rows, loose
        self.parts: list[tuple[np.ndarray, ...]] = []
        self.size = self.kept = 0

    def add(self, query: np.ndarray, found: np.ndarray, score: np.ndarray) -> None:
        self.parts.append((query, found, score))
        self.size += len(query)
        if self.size - self.kept > self.loose:
            self._reduce()

    def _reduce(self) -> None:
        query, found, score = (np.concatenate(x) for x in zip(*self.parts, strict=True))
        order = np.lexsort((found, -score, query))
        query, found, score = query[order], found[order], score[order]
        again = np.concatenate([[False], (query[1:] == query[:-1]) & (found[1:] == found[:-1]) & (score[1:] == score[:-1])]) if len(query) else np.zeros(0, bool)
        query, found, score = query[~again], found[~again], score[~again]
        keep = np.arange(len(query)) - np.searchsorted(query, query) < self.k
        self.parts = [(query[keep], found[keep], score[keep])]
        self.size = self.kept = int(keep.sum())

    def full(self) -> bool:
        return self.kept > self.rows

    def take(self) -> pa.RecordBatch:
        if self.parts:
            self._reduce()
        query, found, score = self.parts[0] if self.parts else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        self.parts, self.size, self.kept = [], 0, 0
        return pa.RecordBatch.from_arrays([pa.array(query), pa.array(found), pa.array(score)], names=["query_id", "id", "score"])


def _vectors(b: pa.RecordBatch, kind: type, rows: int = 2048) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, vectors) of equal dimension from columns id and vec, some rows at a time."""
    ids, lists = b.column(0).to_numpy(zero_copy_only=False), b.column(1)
    offsets, flat = np.asarray(lists.offsets), lists.values.to_numpy(zero_copy_only=False).astype(kind)
    dims = np.diff(offsets)
    for dim in np.unique(dims):
        own = np.flatnonzero(dims == dim)
        for at in range(0, len(own), rows):
            part = own[at : at + rows]
            yield ids[part], flat[offsets[part][:, None] + np.arange(dim)]


KEYS = "tab long, grp long, dim long, id long, vec binary"


def _placed(rows: DataFrame, tables: HashTables, kind: type, probing: bool) -> DataFrame:
    """Each vector once for every table, in the group of its bucket; a query once for every group that it visits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for ids, vecs in _vectors(b, kind):
                unit = scaled(vecs.astype(np.float64))
                raw = pa.array([v.tobytes() for v in vecs], pa.binary())
                for t in range(tables.tables):
                    if probing:
                        found = tables.groups_of(*tables.success(unit, t))
                        own, group = np.repeat(np.arange(len(ids)), [len(g) for g in found]), np.concatenate(found)
                    else:
                        own, group = np.arange(len(ids)), tables.group(tables.cells(unit, t))
                    n = len(own)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(n, t)), pa.array(group), pa.array(np.full(n, vecs.shape[1])), pa.array(ids[own]), raw.take(pa.array(own))], names=["tab", "grp", "dim", "id", "vec"])

    return rows.select("id", "vec").mapInArrow(run, KEYS)


def _blocks(placed: DataFrame, name: str, n: int, salts: int) -> DataFrame:
    """Rows of one table, group and dimension as blocks of at most ``n``; a large group is spread over ``salts`` tasks."""
    schema = f"tab long, grp long, dim long, {name}_ids binary, {name}_vecs binary"
    dealt = placed.repartition("tab", "grp", "dim", F.pmod(F.xxhash64("id"), F.lit(salts))).sortWithinPartitions("tab", "grp", "dim")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, ids, vecs = None, [], []

        def emit() -> pa.RecordBatch:
            cols = [pa.array([x], pa.int64()) for x in key]
            return pa.RecordBatch.from_arrays([*cols, pa.array([np.array(ids, dtype=np.int64).tobytes()]), pa.array([b"".join(vecs)])], names=["tab", "grp", "dim", f"{name}_ids", f"{name}_vecs"])

        for b in batches:
            keys = zip(*(b.column(i).to_pylist() for i in range(3)), strict=True)
            for own, i, v in zip(keys, b.column(3).to_pylist(), b.column(4).to_pylist(), strict=True):
                if ids and (own != key or len(ids) >= n):
                    yield emit()
                    ids, vecs = [], []
                key = own
                ids.append(i)
                vecs.append(v)
        if ids:
            yield emit()

    return dealt.mapInArrow(run, schema)


def nearest(vectors: DataFrame, is_query, id_col: str = "id", vec_col: str = "vec", k: int = 5, tables: HashTables = HashTables(), block: int = 1024, query_block: int = 256, salts: int = 16) -> DataFrame:
    """``(query_id, rank, id, score)``: the k nearest rows found for every query, by largest cosine.

    Queries are the rows for which ``is_query`` holds; candidates are all rows but those of the query's
    id.  Vectors that are null, empty, zero or hold a null or non-finite component take no part, nor do
    null ids; vectors of different dimension do not meet.  Scores are exact cosines of the original
    vectors in double precision; ties go to the smaller id, repeated rows of an id count once.  Every
    row is indexed, whatever its bucket's size: large buckets are many blocks.  An empty table gives an
    empty result.
    """
    scratch = Scratch(vectors.sparkSession, "nearest")
    kind = np.float32 if "float" in dict(vectors.dtypes)[vec_col] else np.float64
    element = "float" if kind is np.float32 else "double"
    norm = F.aggregate(vec_col, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    rows = vectors.where(F.col(id_col).isNotNull() & usable(F.col(vec_col))).where(norm > 0).select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast(f"array<{element}>").alias("vec"), F.coalesce(is_query, F.lit(False)).alias("is_query"))
    queries = rows.where("is_query")
    stored = scratch.save(_blocks(_placed(rows, tables, kind, False), "c", block, salts))
    probes = _blocks(_placed(queries, tables, kind, True), "q", query_block, 1)

    def meet(batches: Iterator[pa.RecordBatch], all_buckets: bool) -> Iterator[pa.RecordBatch]:
        best = Best(k)
        for b in batches:
            for r in b.to_pylist():
                q_ids, c_ids = (np.frombuffer(r[f"{s}_ids"], dtype=np.int64) for s in "qc")
                q, c = (np.frombuffer(r[f"{s}_vecs"], dtype=kind).reshape(-1, r["dim"]).astype(np.float64) for s in "qc")
                seen = None if all_buckets else tables.visited(*tables.success(scaled(q), r["tab"]), tables.cells(scaled(c), r["tab"]))
                row, col, score = best_of_block(q_ids, q, c_ids, c, k, seen)
                best.add(q_ids[row], c_ids[col], score)
                if best.full():
                    yield best.take()
        yield best.take()

    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    found = "query_id long, id long, score double"

    def ranked(pairs: DataFrame, all_buckets: bool) -> DataFrame:
        met = pairs.mapInArrow(lambda batches: meet(batches, all_buckets), found)
        once = met.groupBy("query_id", "id").agg(F.max("score").alias("score"))
        return once.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "id", "score")

    best = scratch.save(ranked(stored.join(probes.hint("shuffle_merge"), ["tab", "grp", "dim"]), False))
    served = best.where(F.col("rank") == k).select(F.col("query_id").alias("id"))
    short = scratch.save(queries.join(served, "id", "left_anti"))
    if not short.limit(1).count():
        return best
    # every block of one table is all rows; blocks and copies of the short queries meet under a slot
    slot = F.pmod(F.xxhash64("c_ids"), F.lit(salts))
    slots = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long")))
    raw = _placed(short, tables, kind, False).where("tab = 0").distinct().select("tab", slots.alias("grp"), "dim", "id", "vec")
    asked = _blocks(raw, "q", query_block, 1)
    again = ranked(stored.where("tab = 0").withColumn("grp", slot.cast("long")).join(asked, ["tab", "grp", "dim"]), True)
    return best.join(short.select(F.col("id").alias("query_id")).distinct(), "query_id", "left_anti").unionByName(again)


def ann_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    return nearest(rows, F.col("vec_id") % 50 == 0, "vec_id", "embedding").withColumnRenamed("id", "vec_id")
