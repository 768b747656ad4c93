"""Placement of vertices into parts: ``(vid, pid INT)``."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellgraph.graph import Graph
from cellgraph.scratch import Scratch
from cellgraph.workers import lean


#: An odd number near 2^32 divided by the square of the golden ratio: neighbouring ids land far apart.
MIX = 1640531527


def partition_hash(g: Graph, k: int) -> DataFrame:
    """The default of vertex-centric engines: an integer mix of the id, no locality; the same in any SQL with 64-bit integers."""
    fold = F.pmod("vid", F.lit(1 << 31)) + F.pmod(F.floor(F.col("vid") / (1 << 31)), F.lit(1 << 31))
    mixed = F.pmod(fold * F.lit(MIX), F.lit(1 << 32))
    return g.vertices.select("vid", F.pmod(F.floor(mixed / (1 << 12)), F.lit(k)).cast("int").alias("pid"))


def partition_modulo(g: Graph, k: int) -> DataFrame:
    """vid modulo k: a hash that plain SQL can repeat."""
    return g.vertices.select("vid", F.pmod("vid", F.lit(k)).cast("int").alias("pid"))


def partition_blocks(g: Graph, k: int, id_space: int) -> DataFrame:
    """Equal id ranges of a known id space, by arithmetic alone."""
    return g.vertices.select("vid", block_of("vid", k, id_space).alias("pid"))


def block_of(vid: str, k: int, id_space: int) -> Column:
    return F.least(F.floor(F.col(vid) * k / id_space), F.lit(k - 1)).cast("int")


def partition_range(g: Graph, k: int, order_by: str = "vid", accuracy: int = 10_000) -> DataFrame:
    """Contiguous ranges of ``order_by`` with about as many vertices each; k - 1 boundaries from a quantile sketch, no global sort."""
    cuts = g.vertices.agg(F.percentile_approx(order_by, [i / k for i in range(1, k)], accuracy)).first()[0] if k > 1 else []
    inside = F.lit(0)
    for cut in cuts or []:
        inside = inside + (F.col(order_by) > F.lit(cut)).cast("int")
    return g.vertices.select("vid", inside.cast("int").alias("pid"))


def _by_end(arcs: DataFrame) -> DataFrame:
    """The arcs, kept in order of ``dst`` where joins on it want them, so that they travel once for all rounds."""
    shards = int(arcs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return arcs.repartition(shards, "dst").sortWithinPartitions("dst").persist(StorageLevel.MEMORY_AND_DISK)


def hash_of(x: np.ndarray, seed: int) -> np.ndarray:
    """What ``xxhash64`` of a long is, signed, where the columns before it have hashed to ``seed``."""
    one, two, three, four, five = (np.uint64(p) for p in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    turn = lambda v, n: (v << np.uint64(n)) | (v >> np.uint64(64 - n))
    start = np.uint64((seed + int(five) + 8) % (1 << 64))
    h = turn(start ^ turn(x.astype(np.int64).view(np.uint64) * two, 31) * one, 27) * one + four
    h = (h ^ (h >> np.uint64(33))) * two
    h = (h ^ (h >> np.uint64(29))) * three
    return (h ^ (h >> np.uint64(32))).view(np.int64)


def grow_in_arrays(ids: np.ndarray, size: np.ndarray, src: np.ndarray, dst: np.ndarray, n: np.ndarray, cap: int, marks: list[int]) -> np.ndarray:
    """`_grow` of a graph in memory, with a round for each of ``marks``, the hashes of their numbers; vertices and labels are places in ``ids``, which ascend."""
    label = np.arange(len(ids))
    for mark in marks:
        held = np.zeros(len(ids), np.int64)
        np.add.at(held, label, size)
        lot = hash_of(ids, mark)
        theirs = label[dst]
        free = held[theirs] < cap
        key, votes = src[free] * np.int64(len(ids)) + theirs[free], n[free]
        if not len(key):
            break
        order = np.argsort(key, kind="stable")
        key, votes = key[order], votes[order]
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        vertex, to = np.divmod(key[first], len(ids))
        order = np.lexsort((to, lot[to] & ((1 << 30) - 1), held[to], np.add.reduceat(votes, first), vertex))
        vertex, to = vertex[order], to[order]
        best = np.concatenate([vertex[1:] != vertex[:-1], [True]])
        vertex, to = vertex[best], to[best]
        go = to != label[vertex]
        vertex, to = vertex[go], to[go]
        order = np.lexsort((lot[vertex], to))
        vertex, to = vertex[order], to[order]
        taken = np.cumsum(size[vertex])
        first = np.searchsorted(to, to)
        taken -= taken[first] - size[vertex[first]]
        moves = taken + held[to] <= cap
        label[vertex[moves]] = to[moves]
    return label


def _grow_in_task(arcs: DataFrame, sizes: DataFrame, cap: int, rounds: int, seed: int, scratch: Scratch) -> DataFrame | None:
    """`_grow` by one task; None if an id repeats or is null."""
    marks = list(arcs.sparkSession.range(1).select(*[F.xxhash64(F.lit(seed + r)).alias(f"h{r}") for r in range(rounds)]).first()) if rounds else []
    rows = sizes.select(F.lit(0).alias("kind"), F.col("vid").alias("a"), F.lit(None).cast("long").alias("b"), F.col("size").alias("n")).unionByName(arcs.select(F.lit(1).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), "n"))
    schema = pa.schema([("vid", pa.int64()), ("label", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        heads, lines = [], []
        for b in batches:
            is_line = b.column("kind").to_numpy() == 1
            some = b.filter(pa.array(~is_line))
            if some.column("a").null_count:
                yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64())] * 2, schema=schema)
                return
            heads.append([some.column(c).to_numpy() for c in ("a", "n")])
            some = b.filter(pa.array(is_line))
            lines.append([some.column(c).to_numpy() for c in ("a", "b", "n")])
        if not heads:
            return
        ids, size = (np.concatenate(c) for c in zip(*heads, strict=True))
        src, dst, n = (np.concatenate(c) for c in zip(*lines, strict=True))
        del heads, lines
        order = np.argsort(ids)
        ids, size = ids[order], size[order]
        if not len(ids):
            return
        if (ids[1:] == ids[:-1]).any():
            yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64())] * 2, schema=schema)
            return
        a, b = (np.minimum(np.searchsorted(ids, end), len(ids) - 1) for end in (src, dst))
        known = (ids[a] == src) & (ids[b] == dst)
        label = ids[grow_in_arrays(ids, size, a[known], b[known], n[known], cap, marks)]
        for at in range(0, len(ids), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(ids[at : at + 100_000]), pa.array(label[at : at + 100_000])], schema=schema)

    found = scratch.save(rows.repartition(1).mapInArrow(lean(run), "vid long, label long"))
    if found.where("vid is null").limit(1).count():
        scratch.drop(found)
        return None
    return found


def _grow(arcs: DataFrame, sizes: DataFrame, cap: int, rounds: int, seed: int, scratch: Scratch, task_arcs: int = 4_000_000) -> DataFrame:
    """``(vid, label)``: label propagation over weighted ``arcs(src, dst, n)`` between vertices of ``sizes(vid, size)``; no label grows beyond ``cap``.

    ``arcs`` are best kept by `_by_end`.  A round brings each label to the arcs' ends with what it holds, and all votes of a vertex together once.
    Of at most ``task_arcs`` vertices and arcs, one task does all rounds, with the same labels.
    """
    if sizes.count() <= task_arcs and arcs.count() <= task_arcs and (found := _grow_in_task(arcs, sizes, cap, rounds, seed, scratch)):
        return found
    labels = scratch.save(sizes.select("vid", F.col("vid").alias("label"), "size"))
    for r in range(rounds):
        room = labels.select(F.col("vid").alias("dst"), "label", F.sum("size").over(Window.partitionBy("label")).alias("held")).where(F.col("held") < cap)
        votes = arcs.join(room, "dst").select("src", "label", "held", "n").repartition("src").groupBy("src", "label", "held").agg(F.sum("n").alias("n"))
        best = votes.groupBy(F.col("src").alias("vid")).agg(F.max(F.struct("n", "held", F.pmod(F.xxhash64(F.lit(seed + r), "label"), F.lit(1 << 30)).alias("h"), "label")).alias("b"))
        wish = labels.join(best, "vid", "left").select("vid", "label", "size", F.when(F.col("b.label") != F.col("label"), F.col("b.label")).alias("to"), F.col("b.held").alias("held"))
        # a label takes no more newcomers than it has room for; who stays is dealt out, as no one waits for another
        wish = wish.withColumn("stays", F.when(F.col("to").isNull(), F.pmod(F.xxhash64("vid"), F.lit(4096))).otherwise(-1))
        taken = F.sum("size").over(Window.partitionBy("to", "stays").orderBy(F.xxhash64(F.lit(seed + r), "vid")).rowsBetween(Window.unboundedPreceding, 0))
        moves = F.col("to").isNotNull() & (taken + F.col("held") <= cap)
        nxt = scratch.save(wish.select("vid", F.when(moves, F.col("to")).otherwise(F.col("label")).alias("label"), "size"))
        scratch.drop(labels)
        labels = nxt
    return labels.select("vid", "label")


def _between(arcs: DataFrame, labels: DataFrame) -> DataFrame:
    """``(src, dst, n)`` between the labels of ``(vid, label)``, the sums of ``arcs(src, dst, n)`` between their vertices."""
    ends = labels.select(F.col("vid").alias("src"), F.col("label").alias("a")), labels.select(F.col("vid").alias("dst"), F.col("label").alias("b"))
    return arcs.join(ends[1], "dst").join(ends[0], "src").where("a <> b").groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.sum("n").alias("n"))


def partition_mincut(g: Graph, k: int, balance: float = 1.05, rounds: int = 6, refine: int = 4, seed: int = 1, driver_clusters: int = 200_000) -> DataFrame:
    """Parts with few cut edges, of at most ``balance`` times the mean number of vertices (and one more).

    Label propagation with a size cap grows clusters; while there are more than ``driver_clusters``, the
    clusters become the vertices of a smaller graph and grow again, and where that no longer helps, small
    clusters are put together by hash.  That bounds what the driver looks at, at every size: it packs
    the clusters into k parts, heaviest first, each joining those it has most edges with.  Then boundary
    vertices move to the part that holds most of their neighbours, as far as the room there goes; at last
    what a part holds over its limit goes to parts with room.
    """
    scratch = Scratch(g.vertices.sparkSession, "mincut")
    one = F.lit(1).cast("long")
    arcs = _by_end(scratch.save(g.weak().arcs().where("src <> dst").select("src", "dst")).withColumn("n", one))
    n = g.vertices.count()
    if not n:
        arcs.unpersist()
        return g.vertices.select("vid", F.lit(0).alias("pid"))
    cap = max(1, n // (k * 8))
    labels = scratch.save(_grow(arcs, g.vertices.select("vid", one.alias("size")), cap, rounds, seed, scratch))
    links = scratch.save(_between(arcs, labels))
    clusters = labels.select("label").distinct().count()
    while clusters > driver_clusters:
        sizes = scratch.save(labels.groupBy(F.col("label").alias("vid")).agg(F.count(F.lit(1)).alias("size")))
        kept = _by_end(links)
        up = scratch.save(_grow(kept, sizes, cap, rounds, seed + 100, scratch))
        kept.unpersist()
        fewer = up.select("label").distinct().count()
        if fewer > clusters * 0.8:  # what is left hardly touches: clusters of like hash become one, which leaves at most half the limit
            bins = max(1, driver_clusters // 2)
            up = scratch.save(up.select("vid", F.pmod(F.xxhash64("label"), F.lit(bins)).alias("label")))
            fewer = up.select("label").distinct().count()
        labels = scratch.save(labels.join(up.select(F.col("vid").alias("label"), F.col("label").alias("next")), "label").select("vid", F.col("next").alias("label")))
        links = scratch.save(_between(links, up))
        clusters = fewer
    weight = {r["label"]: r["n"] for r in labels.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    placed = scratch.save(labels.join(F.broadcast(_pack_clusters(links, weight, k, balance)), "label").select("vid", "pid"))
    limit = int(balance * n / k) + 1
    for _ in range(refine):
        load = placed.groupBy("pid").agg(F.count(F.lit(1)).alias("load"))
        votes = arcs.join(placed.select(F.col("vid").alias("dst"), F.col("pid").alias("to")), "dst").select("src", "to", "n").repartition("src").groupBy("src", "to").agg(F.sum("n").alias("n"))
        own = placed.select(F.col("vid").alias("src"), "pid")
        want = votes.join(own, "src").groupBy(F.col("src").alias("vid"), "pid").agg(F.max(F.struct("n", "to")).alias("t"), F.max(F.when(F.col("to") == F.col("pid"), F.col("n"))).alias("held"))
        want = want.select("vid", "pid", F.col("t.to").alias("to"), (F.col("t.n") - F.coalesce("held", F.lit(0))).alias("gain"))
        gains = want.where("to <> pid and gain > 0").withColumn("bucket", F.pmod(F.xxhash64("vid"), F.lit(64)))
        # each of 64 buckets of movers gets its share of half the room, so that no task holds all movers to a part
        room = load.select(F.col("pid").alias("to"), F.floor((F.lit(limit) - F.col("load")) / 128.0).alias("room"))
        turn = F.row_number().over(Window.partitionBy("to", "bucket").orderBy(F.desc("gain"), "vid"))
        moves = gains.join(F.broadcast(room), "to").withColumn("turn", turn).where("turn <= greatest(room, 0)").select("vid", "to")
        nxt = scratch.save(placed.join(moves, "vid", "left").select("vid", F.coalesce("to", "pid").alias("pid")))
        scratch.drop(placed)
        placed = nxt
    arcs.unpersist()
    return _within_limit(placed, limit, k, scratch)


def _within_limit(placed: DataFrame, limit: int, k: int, scratch: Scratch) -> DataFrame:
    """Moves what is over a part's limit, by hash of the id, to parts with room; exact, by numbers per part and hash bucket."""
    loads = {r["pid"]: r["n"] for r in placed.groupBy("pid").agg(F.count(F.lit(1)).alias("n")).collect()}
    over = {p: c - limit for p, c in loads.items() if c > limit}
    if not over:
        return placed
    spark = placed.sparkSession
    free = [(p, limit - loads.get(p, 0)) for p in range(k) if loads.get(p, 0) < limit]
    bucket = F.pmod(F.xxhash64(F.lit(7), "vid"), F.lit(1024))
    counts = placed.where(F.col("pid").isin(list(over))).withColumn("bucket", bucket).groupBy("pid", "bucket").agg(F.count(F.lit(1)).alias("n")).collect()
    quota, taken = [], dict.fromkeys(over, 0)
    for r in sorted(counts, key=lambda r: (r["pid"], r["bucket"])):  # the first buckets leave, the last of them in part
        leave = min(r["n"], over[r["pid"]] - taken[r["pid"]])
        if leave <= 0:
            continue
        taken[r["pid"]] += leave
        start = 0
        while start < leave:
            to, room = free[-1]
            n = min(room, leave - start)
            quota.append((r["pid"], r["bucket"], start, start + n, to))
            start += n
            free[-1] = (to, room - n)
            if room == n:
                free.pop()
    table = F.broadcast(spark.createDataFrame(quota, "pid int, bucket long, first long, past long, to int"))
    turn = F.row_number().over(Window.partitionBy("pid", "bucket").orderBy("vid")) - 1
    leaving = placed.withColumn("bucket", bucket).join(F.broadcast(table.select("pid", "bucket").distinct()), ["pid", "bucket"]).withColumn("turn", turn)
    moves = leaving.join(table, ["pid", "bucket"]).where("turn >= first and turn < past").select("vid", "to")
    return scratch.save(placed.join(moves, "vid", "left").select("vid", F.coalesce("to", "pid").alias("pid")))


def _pack_clusters(links: DataFrame, weight: dict[int, int], k: int, balance: float) -> DataFrame:
    """Greedy growth on the cluster graph ``links(src, dst, n)``: the next part starts at the heaviest free cluster and takes its best-connected neighbours."""
    import heapq

    spark, pairs = links.sparkSession, links.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"), "n")
    near: dict[int, dict[int, int]] = {}
    for r in pairs.toLocalIterator():
        near.setdefault(r["a"], {})[r["b"]] = r["n"]
        near.setdefault(r["b"], {})[r["a"]] = r["n"]
    total, where = sum(weight.values()), {}
    order = sorted(weight, key=lambda c: (-weight[c], c))
    start = 0
    for pid in range(k):
        goal, load = (total - sum(weight[c] for c in where)) / (k - pid), 0
        pull: dict[int, int] = {}
        heap: list[tuple[int, int]] = []
        while load < goal:
            c = None
            while heap:
                links, c = heapq.heappop(heap)
                if c not in where and pull.get(c) == -links:
                    break
                c = None
            if c is None:
                while start < len(order) and order[start] in where:
                    start += 1
                if start == len(order):
                    break
                c = order[start]
            if load and load + weight[c] > goal * balance:
                if not heap:
                    break
                continue
            where[c], load = pid, load + weight[c]
            for d, n in near.get(c, {}).items():
                if d not in where:
                    pull[d] = pull.get(d, 0) + n
                    heapq.heappush(heap, (-pull[d], d))
    for c in order:
        where.setdefault(c, k - 1)
    return spark.createDataFrame(list(where.items()), "label long, pid int")


def balance_cells(cell_of: DataFrame, k: int, cores: int = 1) -> DataFrame:
    """``(vid, pid)``: whole cells dealt anew, so that parts are alike in vertices and none has many more units than others.

    A unit is a large cell, or the small cells of one hash bin taken together: at every size the driver
    sees at most 64 large cells a part (those of over a 64th of a part) and 16 bins a core.  Units are
    dealt largest first to the emptiest part that may still take one: the mean number of units, rounded up to a
    multiple of ``cores``, and four more for each core.
    """
    import heapq

    spark = cell_of.sparkSession
    sizes = cell_of.groupBy("cell_id").agg(F.count(F.lit(1)).alias("n"))
    total = cell_of.count()
    large = F.col("n") * (64 * k) > total
    bins = k * cores * 16
    unit = F.when(large, F.struct(F.lit(1).alias("large"), F.col("cell_id").alias("u"))).otherwise(F.struct(F.lit(0).alias("large"), F.pmod(F.xxhash64("cell_id"), F.lit(bins)).alias("u")))
    units = sizes.withColumn("unit", unit)
    rows = [((r["unit"]["large"], r["unit"]["u"]), r["n"]) for r in units.groupBy("unit").agg(F.sum("n").alias("n")).collect()]
    per_part = (-(-len(rows) // (k * cores)) + 4) * cores
    heap = [(0, p, 0) for p in range(k)]
    table = []
    for (is_large, u), n in sorted(rows, key=lambda r: (-r[1], r[0])):
        load, p, held = heapq.heappop(heap)
        table.append((is_large, u, p))
        if held + 1 < per_part:
            heapq.heappush(heap, (load + n, p, held + 1))
    dealt = spark.createDataFrame(table, "large int, u long, pid int")
    where = units.select("cell_id", "unit.large", "unit.u").join(F.broadcast(dealt), ["large", "u"]).select("cell_id", "pid")
    return cell_of.select("vid", "cell_id").join(where, "cell_id").select("vid", "pid")
