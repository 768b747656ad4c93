"""Cell programs: user code that sees all cells of one part, their state and their messages at once.

A part's constant topology is one row: its vertices, its arcs by source and the far end of each, as
packed arrays made once and cached by part.  Its state is one array.  A superstep ships both to the
parts that have messages or asked to be called again, as blocks of bytes, and returns the new state
and the messages; nothing is indexed or turned into Python objects on the way.  Messages to one
vertex are merged by their sender first, then by the receiver.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellgraph.cells import CellGraph, topology_arrays, unpack_array
from cellgraph.engine.loop import Run
from cellgraph.workers import release_memory

STATE, TO_VERTEX, TO_CELL, CALL = 0, 1, 2, 3
MERGE = {"min": np.minimum, "max": np.maximum, "sum": np.add}


def merged(keys: np.ndarray, values: np.ndarray, how: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys, ascending, and the merged value of each."""
    if not len(keys):
        return keys, values
    order = np.argsort(keys, kind="stable")
    keys, values = keys[order], values[order]
    starts = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return keys[starts], MERGE[how].reduceat(values, starts)


@dataclass
class Part:
    """One part: its vertices in order of id, its arcs in order of source, what its cells hold and receive.

    ``value`` may be changed in place.  ``to`` is the far end's place in ``ids``, -1 over a cut.
    """

    pid: int
    ids: np.ndarray
    cell: np.ndarray
    indptr: np.ndarray
    to: np.ndarray
    dst: np.ndarray
    dst_pid: np.ndarray
    dst_cell: np.ndarray
    weight: np.ndarray
    value: np.ndarray
    told: np.ndarray  # places of vertices with messages
    told_value: np.ndarray  # merged
    cell_messages: list[tuple[int, float]]
    called: set[int] | None  # cells that are not halted; None: all

    @property
    def src(self) -> np.ndarray:
        """Place of each arc's source."""
        return np.repeat(np.arange(len(self.ids)), np.diff(self.indptr))

    def cells(self) -> list[int]:
        """The cells to compute: not halted, or with messages."""
        every = np.unique(self.cell)
        if self.called is None:
            return every.tolist()
        return sorted(self.called | {c for c, _ in self.cell_messages} | set(self.cell[self.told].tolist()))

    def arcs_of(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of the arcs that leave these vertices, and for each its source's position in ``places``."""
        n = self.indptr[places + 1] - self.indptr[places]
        owner = np.repeat(np.arange(len(places)), n)
        first = np.cumsum(n) - n
        return np.arange(n.sum()) - first[owner] + self.indptr[places][owner], owner


@dataclass
class Context:
    """What a program may do in a superstep; ``told_all`` and ``reported`` are of the one before."""

    superstep: int
    told_all: float | None = None
    reported: tuple[float, float] = (0.0, 0.0)
    merge: str = "min"
    vertex: list[tuple] = field(default_factory=list)
    rows: list[tuple] = field(default_factory=list)
    cells: list[tuple] = field(default_factory=list)
    awake: set[int] = field(default_factory=set)
    generated: int = 0
    work: int = 0
    sums: list[float] = field(default_factory=lambda: [0.0, 0.0])
    broadcast: float | None = None

    def send_arcs(self, part: Part, arcs: np.ndarray, values: np.ndarray) -> None:
        """To the far ends of these arcs, all over a cut; one value each."""
        self.generated += len(arcs)
        if not len(arcs):
            return
        to = part.dst[arcs]
        order = np.argsort(to, kind="stable")
        to = to[order]
        first = np.flatnonzero(np.concatenate([[True], to[1:] != to[:-1]]))
        at = arcs[order[first]]
        self.vertex.append((part.dst_pid[at], part.dst_cell[at], to[first], MERGE[self.merge].reduceat(values[order], first)))

    def send_vertex(self, pid: int, cell: int, vid: int, value: float) -> None:
        self.generated += 1
        self.vertex.append((np.array([pid]), np.array([cell]), np.array([vid]), np.array([value])))

    def send_cell(self, pid: int, cell: int, value: float) -> None:
        self.generated += 1
        self.rows.append((pid, TO_CELL, cell, value))

    def send_neighbors(self, part: Part, cell: int, value: float) -> None:
        """One message to each cell that an arc of this cell leads to."""
        places = np.flatnonzero(part.cell == cell)
        arcs, _ = part.arcs_of(places)
        arcs = arcs[part.to[arcs] < 0]
        for pid, other in {*zip(part.dst_pid[arcs].tolist(), part.dst_cell[arcs].tolist(), strict=True)}:
            self.send_cell(pid, other, value)

    def send_cells(self, part: Part, own: np.ndarray, values: np.ndarray, send: np.ndarray) -> None:
        """`send_neighbors` of many cells at once: ``own`` is each vertex's cell as a place in ``values``, ``send`` marks the cells; what goes to one cell is merged."""
        arcs, owner = part.arcs_of(places := np.flatnonzero(send[own]))
        cut = part.to[arcs] < 0
        arcs, cell = arcs[cut], own[places[owner[cut]]]
        if not len(arcs):
            return
        order = np.lexsort((cell, part.dst_cell[arcs]))
        arcs, cell = arcs[order], cell[order]
        target = part.dst_cell[arcs]
        once = np.concatenate([[True], (target[1:] != target[:-1]) | (cell[1:] != cell[:-1])])
        self.generated += int(np.count_nonzero(once))
        first = np.flatnonzero(np.concatenate([[True], target[1:] != target[:-1]]))
        self.cells.append((part.dst_pid[arcs[first]], target[first], MERGE[self.merge].reduceat(values[cell], first)))

    def send_all(self, value: float) -> None:
        """To every cell of the graph: ``told_all`` of the next superstep is the greatest of those sent, and every cell is called."""
        self.broadcast = value if self.broadcast is None else max(value, self.broadcast)

    def report(self, value: float, slot: int = 0) -> None:
        """Added up over the graph in one of two slots; the sums are ``reported`` in the next superstep.  Wakes no one."""
        self.sums[slot] += value

    def keep_awake(self, cell: int | None = None) -> None:
        """Cells halt after every superstep unless they ask to be called again (None: all of the part)."""
        self.awake.add(cell)


class CellProgram:
    """Subclass and override `start` and `compute`."""

    merge = "min"  # how messages to one vertex are merged
    dtype = "double"  # of values and messages: 'double' or 'bigint'

    def start(self, part: Part) -> np.ndarray:
        """The values before the first superstep."""
        raise NotImplementedError

    def compute(self, part: Part, ctx: Context) -> None:
        """Changes ``part.value`` and sends through ``ctx``."""
        raise NotImplementedError

    def has_value(self, value: np.ndarray) -> np.ndarray:
        """Which vertices appear in the result."""
        return np.ones(len(value), dtype=bool)


def _schemas(dtype: str) -> tuple[str, pa.Schema]:
    spark_schema = f"pid int, kind int, cell_id long, vid long, value {dtype}, blob binary, generated long, work long, report double, second double, told double"
    t = pa.float64() if dtype == "double" else pa.int64()
    return spark_schema, pa.schema([("pid", pa.int32()), ("kind", pa.int32()), ("cell_id", pa.int64()), ("vid", pa.int64()), ("value", t), ("blob", pa.binary()), ("generated", pa.int64()), ("work", pa.int64()), ("report", pa.float64()), ("second", pa.float64()), ("told", pa.float64())])


def _rows(schema: pa.Schema, n: int, most: int = 50_000, **columns) -> pa.Table:
    """Rows in chunks of at most ``most``, which are the batches that Spark gets: one vertex may send millions of messages. Chunks share their nulls."""
    nulls = {f.name: pa.nulls(min(n, most), f.type) for f in schema if f.name not in columns}
    chunk = lambda f, at: pa.array(columns[f.name][at : at + most], f.type) if f.name in columns else nulls[f.name].slice(0, min(most, n - at))
    return pa.Table.from_batches([pa.RecordBatch.from_arrays([chunk(f, at) for f in schema], schema=schema) for at in range(0, n, most)], schema=schema)


def _caller(program: CellProgram, step: int, told_all: float | None, reported: tuple[float, float]):
    """The function that calls one part with its topology, its state and its messages."""
    np_type = np.float64 if program.dtype == "double" else np.int64
    _, schema = _schemas(program.dtype)

    def call(key, left: pa.Table, right: pa.Table) -> pa.Table:
        if left.num_rows == 0:
            return schema.empty_table()
        arrays = topology_arrays({c: left.column(c)[0].as_py() for c in left.column_names if c != "pid"})
        pid = key[0].as_py()
        kind = right.column("kind").to_numpy()
        blob = next((right.column("blob")[int(i)].as_py() for i in np.flatnonzero(kind == STATE)), None)
        tv = np.flatnonzero(kind == TO_VERTEX)
        none = np.zeros(0, np_type)
        vids, values = merged(right.column("vid").take(pa.array(tv)).to_numpy(), right.column("value").take(pa.array(tv)).to_numpy(), program.merge) if len(tv) else (np.zeros(0, np.int64), none)
        cm = np.flatnonzero(kind == TO_CELL)
        cell_messages = [(right.column("cell_id")[int(i)].as_py(), right.column("value")[int(i)].as_py()) for i in cm]
        calls = {right.column("cell_id")[int(i)].as_py() for i in np.flatnonzero(kind == CALL)}
        part = Part(pid, **arrays, value=none, told=np.searchsorted(arrays["ids"], vids), told_value=values, cell_messages=cell_messages, called=None if None in calls else calls)
        part.value = program.start(part).astype(np_type) if blob is None else np.frombuffer(blob, dtype=np_type).copy()
        ctx = Context(step, told_all, reported, program.merge)
        program.compute(part, ctx)
        out = [_rows(schema, 1, pid=[pid], kind=[STATE], blob=[part.value.tobytes()], generated=[ctx.generated], work=[ctx.work], report=[ctx.sums[0]], second=[ctx.sums[1]], told=[ctx.broadcast])]
        if ctx.vertex:
            to_pid, to_cell, to_vid, value = (np.concatenate([v[i] for v in ctx.vertex]) for i in range(4)) if len(ctx.vertex) > 1 else ctx.vertex[0]
            ctx.vertex.clear()
            out.append(_rows(schema, len(to_vid), pid=to_pid, kind=np.full(len(to_vid), TO_VERTEX, np.int32), cell_id=to_cell, vid=to_vid, value=value.astype(np_type)))
        if ctx.rows:
            cols = list(zip(*ctx.rows, strict=True))
            out.append(_rows(schema, len(ctx.rows), pid=cols[0], kind=cols[1], cell_id=cols[2], value=np.array(cols[3], dtype=np_type)))
        for to_pid, to_cell, value in ctx.cells:
            out.append(_rows(schema, len(to_cell), pid=to_pid, kind=np.full(len(to_cell), TO_CELL), cell_id=to_cell, value=value.astype(np_type)))
        if ctx.awake:
            cells = [None] if None in ctx.awake else sorted(ctx.awake)
            out.append(_rows(schema, len(cells), pid=[pid] * len(cells), kind=[CALL] * len(cells), cell_id=cells))
        if len(part.dst) > 1_000_000:  # as a vertex of very many arcs may bring
            release_memory()
        return pa.concat_tables(out)

    return call


def run_cell_program(program: CellProgram, cg: CellGraph, initial: DataFrame | None = None, max_supersteps: int = 10_000) -> tuple[DataFrame, Run]:
    """Runs to rest; returns ``(pid, cell_id, vid, value)`` and the run.

    ``initial(pid, cell_id, vid, value)`` are the first messages and only their parts are called first;
    without it every cell is called.  A superstep is one job, which writes states and messages.  The driver holds one number per part: where its latest state is.
    """
    scratch, spark = cg.scratch, cg.cell_of.sparkSession
    row_schema, _ = _schemas(program.dtype)
    names = [c.split()[0] for c in row_schema.split(", ")]
    topology = cg.topology()
    null = lambda c: F.lit(None).cast({"blob": "binary", "value": program.dtype, "told": "double", "report": "double", "second": "double"}.get(c, "long")).alias(c)
    if initial is None:
        inbox = topology.select("pid", F.lit(CALL).alias("kind"), *[null(c) for c in names[2:]])
    else:
        cells = {"pid": F.col("pid").cast("int").alias("pid"), "kind": F.lit(TO_VERTEX).alias("kind"), "cell_id": F.col("cell_id"), "vid": F.col("vid"), "value": F.col("value").cast(program.dtype).alias("value")}
        inbox = initial.select(*[cells.get(c, null(c)) for c in names])
    inbox = scratch.save(inbox)
    called = sorted(r["pid"] for r in inbox.select("pid").distinct().collect())
    run, told_all, reported = Run(), None, (0.0, 0.0)
    tables: dict[int, DataFrame] = {}
    at: dict[int, int] = {}  # part -> superstep of its latest state
    step = 0
    while called and step < max_supersteps:
        step += 1
        right = inbox
        for s in sorted({at[p] for p in called if p in at}):
            right = right.unionByName(tables[s].where((F.col("kind") == STATE) & F.col("pid").isin([p for p in called if at.get(p) == s])))
        live = topology.where(F.col("pid").isin(called)) if len(called) < cg.parts() else topology
        made = live.groupBy("pid").cogroup(right.groupBy("pid")).applyInArrow(_caller(program, step, told_all, reported), row_schema)
        is_message = F.col("kind").isin(TO_VERTEX, TO_CELL)
        made, got = scratch.counted(
            made,
            generated=F.sum("generated"),
            combined=F.count(F.when(is_message, 1)),
            work=F.sum("work"),
            report=F.sum("report"),
            second=F.sum("second"),
            told=F.max("told"),
            next=F.collect_set(F.when(F.col("kind") != STATE, F.col("pid"))),
        )
        run.step(got["generated"] or 0, got["combined"], got["combined"], got["work"] or 0, got["second"] or 0.0)
        for p in called:
            at[p] = step
        tables[step] = made
        stale = [s for s in tables if s not in at.values()]
        if len(tables) - len(stale) > 8:  # keep the latest states together
            old = [s for s in tables if s in at.values() and s != step]
            together = tables[old[0]].where(F.col("pid").isin([p for p in at if at[p] == old[0]]))
            for s in old[1:]:
                together = together.unionByName(tables[s].where(F.col("pid").isin([p for p in at if at[p] == s])))
            together = scratch.save(together.where(F.col("kind") == STATE))
            stale += old
            at = {p: s if s == step else -step for p, s in at.items()}
            tables[-step] = together
        for s in stale:
            scratch.drop(tables.pop(s))
        told_all, reported = got["told"], (got["report"] or 0.0, got["second"] or 0.0)
        inbox = made.where(F.col("kind") != STATE)
        called = sorted(got["next"])
        if told_all is not None:  # a broadcast calls every cell
            inbox = inbox.unionByName(topology.select("pid", F.lit(CALL).alias("kind"), *[null(c) for c in names[2:]]))
            called = sorted(r["pid"] for r in topology.select("pid").collect())
    found = _result(program, cg, tables, at)
    scratch.drop(inbox, *tables.values())
    return found, run


def _result(program: CellProgram, cg: CellGraph, tables: dict[int, DataFrame], at: dict[int, int]) -> DataFrame:
    """The values of all vertices that have one; parts that were never called have none."""
    np_type = np.float64 if program.dtype == "double" else np.int64
    value_type = pa.float64() if program.dtype == "double" else pa.int64()
    out = f"pid int, cell_id long, vid long, value {program.dtype}"
    states = None
    for s in sorted(set(at.values())):
        one = tables[s].where((F.col("kind") == STATE) & F.col("pid").isin([p for p in at if at[p] == s])).select("pid", F.col("blob").alias("state"))
        states = one if states is None else states.unionByName(one)
    if states is None:
        return cg.cell_of.sparkSession.createDataFrame([], out)

    def spread(batches):
        for b in batches:
            for i in range(b.num_rows):
                ids, cell = (unpack_array(b.column(c)[i].as_py(), np.int64) for c in (1, 2))
                value = np.frombuffer(b.column(3)[i].as_py(), dtype=np_type)
                keep = program.has_value(value)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(int(keep.sum()), b.column(0)[i].as_py(), dtype=np.int32)), pa.array(cell[keep]), pa.array(ids[keep]), pa.array(value[keep], value_type)], names=["pid", "cell_id", "vid", "value"])

    return cg.scratch.save(cg.topology().select("pid", "ids", "cell").join(states, "pid").mapInArrow(spread, out))
