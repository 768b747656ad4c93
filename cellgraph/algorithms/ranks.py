"""Classic rank on either engine, and block rank."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellgraph.cells import CellGraph
from cellgraph.engine.cellprog import CellProgram, Context, Part, run_cell_program
from cellgraph.engine.loop import Run
from cellgraph.graph import Graph
from cellgraph.scratch import Scratch


#: A graph of at most so many vertices and arcs goes through all rounds in one task.
TASK_ARCS = 4_000_000


def rounds_in_arrays(rank: np.ndarray, start: np.ndarray, kept: np.ndarray, loose: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray, damping: float, rounds: int | None, tol: float | None) -> tuple[np.ndarray, list[float]]:
    """The ranks after all rounds of a graph in memory, and the L1 change of every round.

    An arc carries its source's rank times ``w``, a vertex keeps ``kept`` of its own, and the rank of ``loose`` vertices is spread over all.
    """
    deltas: list[float] = []
    while rounds is None or len(deltas) < rounds:
        got = np.bincount(dst, weights=rank[src] * w, minlength=len(rank)) + kept * rank + rank[loose].sum() / len(rank)
        new = (1 - damping) * start + damping * got
        deltas.append(float(np.abs(new - rank).sum()))
        rank = new
        if tol is not None and deltas[-1] < tol:
            break
    return rank, deltas


def _in_one_task(vertices: DataFrame, arcs: DataFrame, scratch: Scratch, damping: float, redistribute: bool, rounds: int | None, tol: float | None) -> tuple[DataFrame, list[float]] | None:
    """``(vid, rank)`` and the changes of `rounds_in_arrays` for ``vertices(vid, rank, start, kept)`` and ``arcs(src, dst, w)``; None if an id repeats or is null.

    A null ``w`` is one over the number of arcs of the source.
    """
    null = lambda kind: F.lit(None).cast(kind)
    heads = vertices.select(F.lit(0).alias("kind"), F.col("vid").alias("a"), null("long").alias("b"), F.col("rank").alias("x"), F.col("start").alias("y"), F.col("kept").alias("z"))
    lines = arcs.select(F.lit(1).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("w").alias("x"), null("double").alias("y"), null("double").alias("z"))
    schema = pa.schema([("kind", pa.int32()), ("vid", pa.int64()), ("rank", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = lambda kind, vid, rank: pa.RecordBatch.from_arrays([pa.array(np.full(len(vid), kind, np.int32)), pa.array(vid, pa.int64()), pa.array(rank, pa.float64())], schema=schema)
        numbers = lambda c: c.to_numpy(zero_copy_only=False)
        held: list[list[np.ndarray]] = [[] for _ in range(4)]
        ends: list[list[np.ndarray]] = [[] for _ in range(3)]
        for b in batches:
            n = int(np.count_nonzero(b.column(0).to_numpy() == 0))  # vertices come first
            v, e = b.slice(0, n), b.slice(n)
            if v.column(1).null_count:
                yield rows(2, [0], [0.0])
                return
            for out, c in zip(held, (1, 3, 4, 5), strict=True):
                out.append(numbers(v.column(c)))
            for out, c in zip(ends, (1, 2, 3), strict=True):
                out.append(numbers(e.column(c).fill_null(np.nan) if c == 3 else e.column(c)))
        ids, rank, start, kept = (np.concatenate(c) for c in held)
        if (ids[1:] == ids[:-1]).any():
            yield rows(2, [0], [0.0])
            return
        src, dst, w = (np.concatenate(c) for c in ends)
        at = np.minimum(np.searchsorted(ids, src), len(ids) - 1)
        known = ids[at] == src
        degree = np.bincount(at[known], minlength=len(ids))
        to = np.minimum(np.searchsorted(ids, dst), len(ids) - 1)
        known &= ids[to] == dst
        at, to, w = at[known], to[known], w[known]
        w = np.where(np.isnan(w), 1.0 / degree[at], w)
        loose = (degree == 0) & redistribute
        rank, deltas = rounds_in_arrays(rank, start, kept, loose, at, to, w, damping, rounds, tol)
        for i in range(0, len(ids), 100_000):
            yield rows(0, ids[i : i + 100_000], rank[i : i + 100_000])
        yield rows(1, np.arange(len(deltas)), deltas)

    both = heads.unionByName(lines).repartition(1).sortWithinPartitions("kind", "a", "b")
    made = scratch.save(both.mapInArrow(run, "kind int, vid long, rank double"))
    told = made.where("kind > 0").collect()
    if any(r["kind"] == 2 for r in told):
        scratch.drop(made)
        return None
    return made.where("kind = 0").select("vid", "rank"), [r["rank"] for r in sorted(told, key=lambda r: r["vid"])]


def pagerank_vertex(g: Graph, iterations: int | None = 30, damping: float = 0.85, dangling: str = "redistribute", tol: float | None = None, seed: DataFrame | None = None, parts: int = 8, task_arcs: int = TASK_ARCS) -> tuple[DataFrame, Run, list[float]]:
    """``(vid, rank)``, the run and the L1 change of every round.  ``dangling``: 'leak' loses the rank of vertices without out-arcs, 'redistribute' spreads it.

    Runs ``iterations`` rounds, or until the L1 change of a round is below ``tol``.  Parallel arcs count.
    A round is one job: ranks meet the arcs, which are cached by source, shares are summed by target, and
    the change and the rank of vertices without out-arcs are observed while the new ranks are written.
    Of a graph of at most ``task_arcs`` vertices and arcs, one task does all rounds.
    """
    scratch = Scratch(g.vertices.sparkSession, "rank-vertex")
    run, deltas = Run(), []
    shards = int(g.vertices.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    arcs = g.arcs().select("src", "dst").repartition(shards, "src").persist(StorageLevel.MEMORY_AND_DISK)
    home = lambda v: F.pmod(F.xxhash64(v), F.lit(parts))
    counted = arcs.agg(F.count(F.lit(1)).alias("n"), F.count(F.when(home("src") != home("dst"), 1)).alias("x"), F.countDistinct("dst").alias("c")).first()
    degree = arcs.groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("degree"))
    n = g.vertices.count()
    first = F.lit(1.0 / max(1, n)) if seed is None else F.coalesce("seed", F.lit(0.0))
    base = g.vertices.select("vid") if seed is None else g.vertices.select("vid").join(seed.select("vid", F.col("rank").alias("seed")), "vid", "left")
    if 0 < n <= task_arcs and counted["n"] <= task_arcs:
        heads = base.select("vid", first.alias("rank"), F.lit(1.0 / n).alias("start"), F.lit(0.0).alias("kept"))
        lines = arcs.select("src", "dst", F.lit(None).cast("double").alias("w"))
        if done := _in_one_task(heads, lines, scratch, damping, dangling == "redistribute", iterations, tol):
            for moved in done[1]:
                run.step(counted["n"], counted["c"], counted["x"], counted["n"], moved)
            arcs.unpersist()
            return done[0], run, done[1]
    loose_now = F.sum(F.when(F.col("degree") == 0, F.col("rank")))
    ranks, told = scratch.counted(base.join(degree, "vid", "left").select("vid", first.alias("rank"), F.coalesce("degree", F.lit(0)).alias("degree")), loose=loose_now)
    while n and (iterations is None or run.supersteps < iterations):
        share = ranks.where("degree > 0").select(F.col("vid").alias("src"), (F.col("rank") / F.col("degree")).alias("share"))
        got = arcs.join(share, "src").groupBy(F.col("dst").alias("vid")).agg(F.sum("share").alias("got"))
        spread = (told["loose"] or 0.0) / n if dangling == "redistribute" else 0.0
        value = F.lit((1 - damping) / n) + F.lit(damping) * (F.coalesce("got", F.lit(0.0)) + F.lit(spread))
        nxt, told = scratch.counted(ranks.join(got, "vid", "left").select("vid", value.alias("rank"), "degree", F.abs(value - F.col("rank")).alias("moved")), loose=loose_now, moved=F.sum("moved"))
        deltas.append(told["moved"] or 0.0)
        run.step(counted["n"], counted["c"], counted["x"], counted["n"], deltas[-1])
        scratch.drop(ranks)
        ranks = nxt
        if tol is not None and deltas[-1] < tol:
            break
    arcs.unpersist()
    return ranks.select("vid", "rank"), run, deltas


class Rank(CellProgram):
    """One rank update of all cells of a part per superstep; a remote vertex gets one pre-summed share from each part."""

    merge, dtype = "sum", "double"

    def __init__(self, n: int, iterations: int | None, damping: float, dangling: str, tol: float | None, seeded: bool):
        self.n, self.iterations, self.damping, self.dangling, self.tol, self.seeded = n, iterations, damping, dangling, tol, seeded

    def start(self, part: Part) -> np.ndarray:
        return np.full(len(part.ids), 0.0 if self.seeded else 1.0 / self.n)

    def compute(self, part: Part, ctx: Context) -> None:
        degree = np.diff(part.indptr)
        src, inner = part.src, part.to >= 0
        out = lambda rank: np.divide(rank, degree, out=np.zeros_like(rank), where=degree > 0)
        ctx.work += len(part.dst)
        if ctx.superstep == 1:
            part.value[part.told] = part.told_value  # the seed, if there is one
        else:
            got = np.bincount(part.to[inner], weights=out(part.value)[src[inner]], minlength=len(part.ids)).astype(float)
            got[part.told] += part.told_value
            spread = ctx.reported[0] / self.n if self.dangling == "redistribute" else 0.0
            new = (1 - self.damping) / self.n + self.damping * (got + spread)
            ctx.report(float(np.abs(new - part.value).sum()), 1)
            part.value[:] = new
        ctx.report(float(part.value[degree == 0].sum()))
        last = self.iterations is not None and ctx.superstep > self.iterations
        if last or (self.tol is not None and ctx.superstep > 2 and ctx.reported[1] < self.tol):
            return
        ctx.keep_awake()
        cut = np.flatnonzero(~inner)
        ctx.send_arcs(part, cut, out(part.value)[src[cut]])


def pagerank_cell(cg: CellGraph, iterations: int | None = 30, damping: float = 0.85, dangling: str = "redistribute", tol: float | None = None, seed: DataFrame | None = None) -> tuple[DataFrame, Run, list[float]]:
    """The same ranks by a cell program: arcs inside a part need no message, those over a cut are summed per sending part and target.

    The first superstep only sends, so there is one more than there are rounds; with ``tol`` one more again, in which all parts learn that the last round moved less.
    """
    cg = cg.fitted()
    n = sum(r["n"] for r in cg.cell_of.groupBy("pid").agg(F.count(F.lit(1)).alias("n")).collect())
    if not n:
        return cg.cell_of.select("vid", F.lit(0.0).alias("rank")), Run(), []
    first = None
    if seed is not None:  # every part must be called, seeded or not
        first = cg.cell_of.join(seed.select("vid", "rank"), "vid", "left").select("pid", "cell_id", "vid", F.coalesce("rank", F.lit(0.0)).alias("value"))
    found, run = run_cell_program(Rank(n, iterations, damping, dangling, tol, seed is not None), cg, first)
    return found.select("vid", F.col("value").alias("rank")), run, run.reports[1:]


def local_rank(cg: CellGraph, rounds: int = 30, damping: float = 0.85, tol: float | None = None) -> DataFrame:
    """``(vid, cell_id, rank)``: ranks inside each cell on its own arcs, summing to 1; one call per part, no message.

    Dangling rank is spread inside the cell.  With ``tol`` a part stops when no cell moves more than that.
    """
    inner = cg.local_edges.select(F.col("src_pid").alias("pid"), "src", "dst")
    members = cg.cell_of.select("pid", "vid", "cell_id")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        ids = left.column("vid").to_numpy()
        order = np.argsort(ids)
        cells, cell = np.unique(left.column("cell_id").to_numpy(), return_inverse=True)
        size = np.bincount(cell).astype(float)[cell]
        src, dst = (order[np.searchsorted(ids[order], right.column(c).to_numpy())] if right.num_rows else np.zeros(0, int) for c in ("src", "dst"))
        degree = np.bincount(src, minlength=len(ids)).astype(float)
        rank = 1 / size
        for _ in range(rounds):
            share = np.divide(rank, degree, out=np.zeros_like(rank), where=degree > 0)
            got = np.bincount(dst, weights=share[src], minlength=len(ids))
            loose = np.bincount(cell, weights=np.where(degree == 0, rank, 0.0), minlength=len(cells))
            new = (1 - damping) / size + damping * (got + loose[cell] / size)
            moved = np.bincount(cell, weights=np.abs(new - rank), minlength=len(cells)).max(initial=0)
            rank = new
            if tol is not None and moved < tol:
                break
        return pa.table({"vid": ids, "cell_id": left.column("cell_id").to_numpy(), "rank": rank})

    return members.groupBy("pid").cogroup(inner.groupBy("pid")).applyInArrow(run, "vid long, cell_id long, rank double")


def cell_rank(cg: CellGraph, local: DataFrame, rounds: int = 30, damping: float = 0.85, block_teleport: str = "size", task_arcs: int = TASK_ARCS) -> DataFrame:
    """``(cell_id, rank)``: rank of the cells; an arc between two cells weighs its source's local rank over its out-degree.

    What a cell's vertices do not send out stays with the cell.  The walk restarts at cells by their
    share of vertices ('size') or alike ('uniform').  Of at most ``task_arcs`` cells and flows, one task does all rounds.
    """
    scratch = cg.scratch
    degrees = cg.graph.degrees().select(F.col("vid").alias("src"), "degree")
    flows = cg.links.join(local.select(F.col("vid").alias("src"), "rank"), "src").join(degrees, "src")
    flows = scratch.save(flows.groupBy("src_cell", "dst_cell").agg(F.sum(F.col("rank") / F.col("degree")).alias("w")))
    cells = cg.cells().select("cell_id", "n_vertices")
    totals = cells.agg(F.count(F.lit(1)).alias("c"), F.sum("n_vertices").alias("v")).first()
    n_cells, n_vertices = totals["c"], totals["v"] or 1
    start = F.col("n_vertices") / F.lit(float(n_vertices)) if block_teleport == "size" else F.lit(1.0 / max(1, n_cells))
    kept = flows.groupBy(F.col("src_cell").alias("cell_id")).agg((F.lit(1.0) - F.sum("w")).alias("kept"))
    ranks = scratch.save(cells.join(kept, "cell_id", "left").select("cell_id", start.alias("start"), F.coalesce("kept", F.lit(1.0)).alias("kept"), start.alias("rank")))
    if 0 < n_cells <= task_arcs and flows.count() <= task_arcs:
        heads = ranks.select(F.col("cell_id").alias("vid"), "rank", "start", "kept")
        lines = flows.select(F.col("src_cell").alias("src"), F.col("dst_cell").alias("dst"), "w")
        if done := _in_one_task(heads, lines, scratch, damping, False, rounds, None):
            scratch.drop(ranks)
            return done[0].select(F.col("vid").alias("cell_id"), "rank")
    for _ in range(rounds):
        sent = flows.join(ranks.select(F.col("cell_id").alias("src_cell"), "rank"), "src_cell").groupBy(F.col("dst_cell").alias("cell_id")).agg(F.sum(F.col("w") * F.col("rank")).alias("got"))
        nxt = scratch.save(ranks.join(sent, "cell_id", "left").select("cell_id", "start", "kept", (F.lit(1 - damping) * F.col("start") + F.lit(damping) * (F.coalesce("got", F.lit(0.0)) + F.col("kept") * F.col("rank"))).alias("rank")))
        scratch.drop(ranks)
        ranks = nxt
    return ranks.select("cell_id", "rank")


def seed_rank(local: DataFrame, cells: DataFrame, scratch: Scratch) -> DataFrame:
    """Local rank times the cell's rank, normalised to sum 1."""
    seed = scratch.save(local.join(cells.withColumnRenamed("rank", "b"), "cell_id").select("vid", (F.col("rank") * F.col("b")).alias("rank")))
    total = seed.agg(F.sum("rank")).first()[0] or 1.0
    return seed.select("vid", (F.col("rank") / total).alias("rank"))


def block_rank(cg: CellGraph, tol: float = 1e-6, damping: float = 0.85, block_teleport: str = "size", local_tol: float = 1e-6, engine: str = "vertex") -> tuple[DataFrame, Run, list[float]]:
    """Classic rank from a seed of local ranks and cell ranks; same limit, in fewer rounds where cells are nearly closed.  ``engine`` runs the last stage."""
    local = cg.scratch.save(local_rank(cg, 200, damping, local_tol))
    cells = cell_rank(cg, local, 30, damping, block_teleport)
    seed = seed_rank(local, cells, cg.scratch)
    if engine == "cell":
        return pagerank_cell(cg, None, damping, "redistribute", tol, seed)
    return pagerank_vertex(cg.graph, None, damping, "redistribute", tol, seed)


def rank_error(ranks: DataFrame, reference: DataFrame) -> DataFrame:
    """``(l1, max_error)`` against a reference of the same vertices."""
    gap = F.abs(F.col("rank") - F.col("ref"))
    return ranks.join(reference.select("vid", F.col("rank").alias("ref")), "vid").agg(F.sum(gap).alias("l1"), F.max(gap).alias("max_error"))


def topk_overlap(ranks: DataFrame, reference: DataFrame, k: int) -> DataFrame:
    """``(k, overlap)``: how many of the k best (ties by vid) are the same."""
    top = lambda df: df.orderBy(F.desc(F.round("rank", 12)), "vid").limit(k).select("vid")
    return top(ranks).join(top(reference), "vid").agg(F.lit(k).cast("long").alias("k"), F.count(F.lit(1)).alias("overlap"))
