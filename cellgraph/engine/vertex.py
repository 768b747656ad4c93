"""Vertex-centric programs, as column expressions.

A superstep joins the vertices that changed with their arcs and merges the messages by target with
map-side combining; what improves on a vertex's value is the next frontier.  Only the frontier is
kept per superstep.  The whole state is rewritten when the changes since then have grown to a share of
it, or after ``merge_every`` supersteps.

A graph of few enough arcs for one task goes through the same supersteps inside that task, on arrays:
there a superstep costs its messages and not a job, which decides on graphs of large diameter.  Components
of a larger graph do not hear of each other, so that several tasks can do the same.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellgraph.algorithms.contraction import weak_components
from cellgraph.engine.loop import Run
from cellgraph.partition import balance_cells
from cellgraph.scratch import Scratch
from cellgraph.workers import lean


@dataclass(frozen=True)
class VertexProgram:
    """``message`` maps a sender's value and an arc's weight to what is sent; ``merge`` is min or max, and a vertex takes what ``better`` prefers to its value (null: none yet).

    ``arrays`` says the same for arrays, if that can be said: 'max' for values sent as they are, 'min' for values plus weights.
    """

    message: Callable[[Column, Column], Column]
    merge: Callable[[Column], Column]
    better: Callable[[Column, Column], Column]
    arrays: str | None = None


def larger() -> VertexProgram:
    return VertexProgram(lambda value, weight: value, F.max, lambda new, old: old.isNull() | (new > old), "max")


def shorter() -> VertexProgram:
    return VertexProgram(lambda value, weight: value + weight, F.min, lambda new, old: old.isNull() | (new < old), "min")


def supersteps_in_arrays(kind: str, ids: np.ndarray, value: np.ndarray, known: np.ndarray, active: np.ndarray, indptr: np.ndarray, to: np.ndarray, weight: np.ndarray | None, crosses: np.ndarray, max_supersteps: int, block: int = 1 << 20) -> list[tuple[int, int, int, int]]:
    """The supersteps of one graph in memory; changes ``value`` and ``known`` and returns (messages, vertices reached, crossing, found) of each.

    Vertices are places; the arcs of place i are those from ``indptr[i]`` to ``indptr[i + 1]``, and ``known``
    marks who has a value.  About ``block`` arcs are looked at together, or those of one vertex.
    """
    pick, none = (np.maximum, -np.inf) if kind == "max" else (np.minimum, np.inf)
    if value.dtype.kind == "i":
        none = np.iinfo(value.dtype).min if kind == "max" else np.iinfo(value.dtype).max
    got, told, touched = np.full(len(ids), none, value.dtype), np.zeros(len(ids), bool), np.zeros(len(ids), bool)
    degree, passed = np.diff(indptr), np.concatenate([[0], np.cumsum(crosses)])
    leaving = passed[indptr[1:]] - passed[indptr[:-1]]
    del passed
    frontier, steps = np.flatnonzero(active), []
    while len(steps) < max_supersteps:
        ends = np.cumsum(degree[frontier])
        whole = bool(known[frontier].all())  # who was active at the start may have nothing to send
        for some in np.split(frontier, np.flatnonzero(np.diff(ends // block)) + 1) if len(ends) and ends[-1] > block else [frontier]:
            n = degree[some]
            arcs = np.repeat(indptr[some] - np.cumsum(n) + n, n)
            arcs += np.arange(len(arcs))
            targets = to[arcs]
            touched[targets] = True
            sent = np.repeat(value[some], n)
            if kind == "min":
                before = sent
                sent = sent + weight[arcs]
                if value.dtype.kind == "i" and (sent < before).any():
                    raise OverflowError("a sum of weights exceeds 64 bits")
            if not whole:
                says = np.repeat(known[some], n)
                targets, sent = targets[says], sent[says]
                told[targets] = True
            pick.at(got, targets, sent)
        reached = np.flatnonzero(touched)
        new = got[reached]
        better = ~known[reached] | ((new > value[reached]) if kind == "max" else (new < value[reached]))
        if not whole:
            better &= told[reached]
            told[reached] = False
        messages, crossing = int(ends[-1]) if len(ends) else 0, int(leaving[frontier].sum())
        frontier = reached[better]
        value[frontier], known[frontier] = new[better], True
        got[reached], touched[reached] = none, False
        steps.append((messages, len(reached), crossing, len(frontier)))
        if not len(frontier):
            break
    return steps


class _Held:
    """What a task holds of a graph that it goes through: the vertices in order of id, then the arcs in order of source."""

    def __init__(self, kind: str, np_type: type):
        self.kind, self.np_type = kind, np_type
        self.columns: list[list] = [[], [], [], []]
        self.to: list[np.ndarray] = []
        self.weight: list[np.ndarray] = []
        self.crosses: list[np.ndarray] = []
        self.ids = None

    def closed(self) -> bool:
        """All vertices are there; False if an id repeats, which arrays by id cannot hold."""
        if self.ids is None:
            kinds = (np.int64, self.np_type, bool, bool)
            self.ids, self.value, self.known, self.active = (np.concatenate([*c, np.zeros(0, t)]) for c, t in zip(self.columns, kinds, strict=True))
            self.columns.clear()
            self.degree = np.zeros(len(self.ids), np.int64)
        return not (self.ids[1:] == self.ids[:-1]).any()

    def add(self, b: pa.RecordBatch) -> None:
        n = int(np.count_nonzero(b.column("kind").to_numpy() == 0))  # vertices come first
        if n:
            v = b.slice(0, n)
            x = v.column("x")
            self.columns[0].append(v.column("vid").to_numpy())
            self.columns[1].append(x.fill_null(0).to_numpy(zero_copy_only=False).astype(self.np_type))
            self.columns[2].append(x.is_valid().to_numpy(zero_copy_only=False))
            self.columns[3].append(v.column("mark").fill_null(False).to_numpy(zero_copy_only=False))
        if n == b.num_rows or not self.closed():
            return
        e, ids = b.slice(n), self.ids
        src, dst = e.column("vid").to_numpy(), e.column("dst").to_numpy()
        at, end = (np.minimum(np.searchsorted(ids, k), max(0, len(ids) - 1)) for k in (src, dst))
        both = (ids[at] == src) & (ids[end] == dst) if len(ids) else np.zeros(len(src), bool)
        if len(kept := at[both]):
            self.degree[kept[0] : kept[-1] + 1] += np.bincount(kept - kept[0])
        self.to.append(end[both].astype(np.int32))
        self.crosses.append(e.column("mark").to_numpy(zero_copy_only=False).astype(bool)[both])
        if self.kind == "min":
            self.weight.append(e.column("x").to_numpy(zero_copy_only=False).astype(self.np_type)[both])

    def supersteps(self, most: int) -> list[tuple[int, int, int, int]]:
        indptr = np.concatenate([[0], np.cumsum(self.degree)])
        to, crosses = np.concatenate([*self.to, np.zeros(0, np.int32)]), np.concatenate([*self.crosses, np.zeros(0, bool)])
        weight = np.concatenate([*self.weight, np.zeros(0, self.np_type)]) if self.kind == "min" else None
        del self.to, self.weight, self.crosses, self.degree
        return supersteps_in_arrays(self.kind, self.ids, self.value, self.known, self.active, indptr, to, weight, crosses, most)


def _in_tasks(program: VertexProgram, arcs: DataFrame, initial: DataFrame, scratch: Scratch, max_supersteps: int, home, tasks: int = 1) -> tuple[DataFrame, list[tuple]] | None:
    """``(vid, value)`` and what `supersteps_in_arrays` tells of each superstep; None if an id repeats.

    ``arcs`` and ``initial`` say in ``bin`` which vertices and arcs go together, and no arc leads from one bin to another: what
    a superstep does is the sum of what it does in the bins.  A task reads the vertices of a bin, then the arcs in order of their source, batch by batch.
    """
    kind, of = program.arrays, dict(initial.dtypes)["value"]
    np_type, pa_type = (np.int64, pa.int64()) if of == "bigint" else (np.float64, pa.float64())
    null = F.lit(None)
    vertices = initial.select("bin", F.lit(0).alias("kind"), "vid", null.cast("long").alias("dst"), F.col("value").alias("x"), F.col("active").alias("mark"))
    weights = F.col("weight").cast(of) if kind == "min" else null.cast(of)
    lines = arcs.select("bin", F.lit(1).alias("kind"), F.col("src").alias("vid"), "dst", weights.alias("x"), (home("src") != home("dst")).alias("mark"))
    schema = pa.schema([("kind", pa.int32()), ("vid", pa.int64()), ("value", pa_type), ("n", pa.int64()), ("c", pa.int64()), ("x", pa.int64())])

    def rows(size: int, **columns) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) if f.name in columns else pa.nulls(size, f.type) for f in schema], schema=schema)

    def done(held: _Held) -> Iterator[pa.RecordBatch]:
        if not held.closed():
            yield rows(1, kind=[2])
            return
        steps = held.supersteps(max_supersteps)
        for at in range(0, len(held.ids), 100_000):
            part = slice(at, at + 100_000)
            n = len(held.ids[part])
            yield rows(n, kind=np.zeros(n, np.int32), vid=held.ids[part], value=pa.array(held.value[part], pa_type, mask=~held.known[part]))
        for at in range(0, len(steps), 100_000):
            part = steps[at : at + 100_000]
            yield rows(len(part), kind=np.ones(len(part), np.int32), vid=np.arange(at, at + len(part)), **{name: [s[i] for s in part] for i, name in enumerate("ncx")})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held = None, _Held(kind, np_type) if tasks == 1 else None
        for b in batches:
            bins = b.column("bin").to_numpy()
            starts = [0, *(np.flatnonzero(np.diff(bins)) + 1).tolist(), len(bins)]
            for first, past in zip(starts[:-1], starts[1:], strict=True):
                if past == first:
                    continue
                if bins[first] != at:
                    if held is not None and at is not None:
                        yield from done(held)
                    at, held = bins[first], _Held(kind, np_type)
                held.add(b.slice(first, past - first))
        if held is not None:
            yield from done(held)

    both = vertices.unionByName(lines)
    both = (both.repartition(1) if tasks == 1 else both.repartition(tasks, "bin")).sortWithinPartitions("bin", "kind", "vid")
    made = scratch.save(both.mapInArrow(lean(run), f"kind int, vid long, value {of}, n long, c long, x long"))
    told = made.where("kind > 0").groupBy("kind", "vid").agg(*[F.sum(c).alias(c) for c in "ncx"]).collect()
    if any(r["kind"] == 2 for r in told):
        scratch.drop(made)
        return None
    return made.where("kind = 0").select("vid", "value"), [(r["n"], r["c"], r["x"]) for r in sorted(told, key=lambda r: r["vid"])]


def _by_components(program: VertexProgram, arcs: DataFrame, initial: DataFrame, scratch: Scratch, max_supersteps: int, home, task_arcs: int) -> tuple[DataFrame, list[tuple]] | None:
    """`_in_tasks` for a graph too large for one task, its weak components dealt to many; None if a bin of them is too large for a task as well."""
    spark = initial.sparkSession
    labels = weak_components(arcs, "src", "dst", scratch)
    size = arcs.count() + initial.count()
    bins = max(4 * spark.sparkContext.defaultParallelism, -(-4 * size // task_arcs))
    member = scratch.save(initial.join(labels.withColumnRenamed("v", "vid"), "vid", "left").select("vid", "value", "active", F.coalesce("component", "vid").alias("cell_id")))
    if (member.groupBy("cell_id").count().agg(F.max("count")).first()[0] or 0) > task_arcs:
        scratch.drop(member)
        return None
    place = scratch.save(balance_cells(member, bins).withColumnRenamed("pid", "bin"))
    placed = scratch.save(arcs.join(place.withColumnRenamed("vid", "src"), "src"))
    done = None
    if (placed.groupBy("bin").count().agg(F.max("count")).first()[0] or 0) <= task_arcs:
        done = _in_tasks(program, placed, member.join(place, "vid"), scratch, max_supersteps, home, bins)
    scratch.drop(member, place, placed)
    return done


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for more in frames[1:]:
        out = out.unionByName(more)
    return out


def _is_long(arcs: DataFrame, vertices: int, mean: int = 4, most: int = 1000) -> bool:
    """Whether supersteps may be many: few arcs a vertex and no hub."""
    seen = arcs.groupBy("src").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n").alias("arcs"), F.max("n").alias("top")).first()
    return (seen["arcs"] or 0) <= mean * vertices and (seen["top"] or 0) <= most


def run_vertex_program(program: VertexProgram, arcs: DataFrame, initial: DataFrame, scratch: Scratch, max_supersteps: int = 10_000, merge_every: int = 8, parts: int = 8, task_arcs: int = 4_000_000) -> tuple[DataFrame, Run]:
    """``initial(vid, value, active)`` to ``(vid, value)`` at rest; one job per superstep, which writes the vertices reached.

    Of a graph of at most ``task_arcs`` vertices and arcs, one task does all supersteps; of a larger one with few arcs a vertex and no hub,
    whose supersteps may be many, a task does those of some weak components, if none is too large for that.  A vertex halts in a superstep
    that brings it nothing new, so that the last superstep finds nothing; it counts even if no message was left for it.
    ``crossing`` counts the messages that leave their part when ``parts`` parts are dealt by hash, as
    vertex-centric engines do.
    """
    run = Run()
    home = lambda v: F.pmod(F.xxhash64(v), F.lit(parts))
    initial = initial.select("vid", "value", "active")
    of = dict(initial.dtypes)["value"]
    no_number = lambda c: F.isnan(c) if of == "double" else F.lit(False)
    initial, seen = scratch.counted(initial, total=F.count(F.lit(1)), active=F.count(F.when(F.col("active"), 1)), odd=F.count(F.when(F.col("vid").isNull() | no_number("value"), 1)))
    total, changed = seen["total"], 0
    arcs = arcs.select("src", "dst", "weight")
    if program.arrays and of in ("bigint", "double") and task_arcs and not seen["odd"]:
        if program.arrays == "max" or dict(arcs.dtypes)["weight"] == of and not arcs.where(F.col("weight").isNull() | no_number("weight")).limit(1).count():
            done, alone = None, F.lit(0).alias("bin")
            if total <= task_arcs and arcs.count() <= task_arcs:
                done = _in_tasks(program, arcs.select("*", alone), initial.select("*", alone), scratch, max_supersteps, home)
            elif _is_long(arcs, total):
                done = _by_components(program, arcs, initial, scratch, max_supersteps, home, task_arcs)
            if done:
                state, steps = done
                for n, c, x in steps:
                    run.step(n, c, x, n)
                if seen["active"] and run.supersteps < max_supersteps:
                    run.step(0, 0)
                return state, run
    state, frontier = initial.select("vid", "value"), initial.where("active").select("vid", "value")
    sending = seen["active"]
    changes: list[DataFrame] = []  # since the state was written: all vertices reached, the improved ones marked
    latest = lambda: _union([c.where("better") for c in changes]).groupBy("vid").agg(program.merge("new").alias("latest"))
    while run.supersteps < max_supersteps:
        senders = frontier.select(F.col("vid").alias("src"), "value")
        if sending <= 200_000:  # so that the arcs need not travel
            senders = F.broadcast(senders)
        crosses = F.count(F.when(home("src") != home("dst"), 1))
        sent = senders.join(arcs, "src").groupBy(F.col("dst").alias("vid")).agg(program.merge(program.message(F.col("value"), F.col("weight"))).alias("new"), F.count(F.lit(1)).alias("n"), crosses.alias("x"))
        reached = sent.join(state, "vid")
        if changes:
            reached = reached.join(latest(), "vid", "left").withColumn("value", F.coalesce("latest", "value"))
        reached = reached.select("vid", "new", "n", "x", F.coalesce(F.col("new").isNotNull() & program.better(F.col("new"), F.col("value")), F.lit(False)).alias("better"))
        reached, got = scratch.counted(reached, n=F.sum("n"), c=F.count(F.lit(1)), x=F.sum("x"), found=F.count(F.when(F.col("better"), 1)))
        run.step(got["n"] or 0, got["c"], got["x"] or 0, got["n"] or 0)
        changes.append(reached)
        changed += got["found"]
        sending = got["found"]
        frontier = reached.where("better").select("vid", F.col("new").alias("value"))
        if not got["found"] or len(changes) >= merge_every or changed * 2 > total:
            merged = scratch.save(state.join(latest(), "vid", "left").select("vid", F.coalesce("latest", "value").alias("value")))
            scratch.drop(state, *changes[:-1])
            state, changes, changed = merged, [], 0
        if not got["found"]:
            if seen["active"] and run.supersteps < max_supersteps:  # one more superstep, in which the last called vertices halt
                run.step(0, 0)
            break
    if changes:
        state = scratch.save(state.join(latest(), "vid", "left").select("vid", F.coalesce("latest", "value").alias("value")))
    return state, run
