"""Exact top-k search by distributed histogram selection.

All pairs of a query and a candidate are scored, block against block.  A first pass histograms the
scores of every query over the whole possible range; the global histogram tells in which bin the
k-th score lies; further passes histogram only that bin, finer, until a bin is one score wide.
The last pass keeps what reaches the k-th score, and ties go to smaller ids.

Each block reports only its bins from the top down to its own k-th score: lower bins cannot hold the
global one.  Scores are integers, so the result is exact.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellgraph.llm.vectors import pack, unpack, usable
from cellgraph.scratch import Scratch


def block_scores(q_ids: np.ndarray, q: np.ndarray, c_ids: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Integer inner products, and which pairs count (a query is no candidate of its own)."""
    limit = float(np.abs(q).max(initial=0)) * float(np.abs(c).max(initial=0)) * q.shape[1]
    scores = np.rint(q @ c.T).astype(np.int64) if limit < 2**52 else q.astype(np.int64) @ c.astype(np.int64).T
    return scores, q_ids[:, None] != c_ids[None, :]


def _histogram(scores: np.ndarray, counted: np.ndarray, low: np.ndarray, high: np.ndarray, need: np.ndarray, width: int, bins: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, bin, count) of the scores in [low, high) of each row, from the top down to the row's ``need``-th."""
    cell = (scores - low[:, None]) // width
    inside = counted & (scores >= low[:, None]) & (scores < high[:, None])
    flat = (np.arange(len(scores))[:, None] * bins + cell)[inside]
    hist = np.bincount(flat, minlength=len(scores) * bins).reshape(len(scores), bins)
    above = np.cumsum(hist[:, ::-1], axis=1)[:, ::-1] - hist
    row, at = np.nonzero((hist > 0) & (above < need[:, None]))
    return row, at, hist[row, at]


def top_k(vectors: DataFrame, is_query, id_col: str = "id", vec_col: str = "vec", k: int = 20, bins: int = 512, block: int = 2048, query_block: int = 1024) -> DataFrame:
    """``(query_id, rank, id, score)``: the k best candidates of every query by integer inner product.

    ``vec_col`` holds whole numbers as doubles.  Queries are the rows for which ``is_query`` holds,
    candidates all rows but those of the query's id.  Unusable vectors (null, empty, null or non-finite
    component) and null ids take no part; vectors of different dimension do not meet.  With fewer
    candidates than k all are returned.  Equal scores, repeated vectors included, go to the smaller id;
    a repeated id counts once per row.  An empty table gives an empty result.
    """
    spark = vectors.sparkSession
    scratch = Scratch(spark, "topk")
    rows = vectors.where(usable(F.col(vec_col)) & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("vec"), F.coalesce(is_query, F.lit(False)).alias("is_query"))
    cand = scratch.save(pack(rows, [], block, "c", False).withColumn("c_block", F.xxhash64("c_ids")))
    query = scratch.save(pack(rows.where("is_query"), [], query_block, "q", False).withColumn("q_block", F.xxhash64("q_ids")))
    n_cand, n_query = cand.count(), query.count()
    out_schema = "query_id long, rank int, id long, score long"
    if not n_query:
        return spark.createDataFrame([], out_schema)
    # Blocks meet on a grid line: candidate blocks are dealt to the lines, query blocks visit every line.
    lines = max(1, min(n_cand, 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))))
    grid = cand.withColumn("line", F.pmod("c_block", F.lit(lines)))

    def meet(state: DataFrame | None) -> DataFrame:
        q = query.join(state, "q_block") if state is not None else query.withColumn("state", F.lit(None).cast("binary"))
        visits = q.withColumn("line", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(lines - 1).cast("long"))))
        return grid.join(visits.hint("shuffle_merge"), ["line"]).where("c_dim = q_dim").select("c_ids", "c_vecs", "c_dim", "q_block", "q_ids", "q_vecs", "state")

    peak = max((float(np.sqrt(r[0] or 0)) for r in _largest_norm(rows).collect()), default=0.0)
    bound = int(peak * peak) + 2
    low, span = -bound, 2 * bound + 1
    width = max(1, -(-span // bins))
    state, counts_below = None, None
    while True:
        hist = _histogram_pass(meet(state), low, span, width, bins, k)
        summed = hist.groupBy("q_block", "query", "bin").agg(F.sum("n").alias("n"))
        by_query = Window.partitionBy("q_block", "query").orderBy(F.desc("bin"))
        running = summed.withColumn("upto", F.sum("n").over(by_query)).withColumn("last", F.min("bin").over(Window.partitionBy("q_block", "query")))
        prior = counts_below.select("q_block", F.col("query").alias("pq"), F.col("low").alias("plow"), F.col("need").alias("pneed")) if counts_below is not None else None
        if prior is None:
            running = running.withColumn("plow", F.lit(low).cast("long")).withColumn("pneed", F.lit(k).cast("long"))
        else:
            running = running.join(prior.withColumnRenamed("q_block", "pb"), (F.col("q_block") == F.col("pb")) & (F.col("query") == F.col("pq")))
        # the bin of the k-th score: the first whose count from the top reaches the need, else the lowest of all
        hit = running.where((F.col("upto") - F.col("n") < F.col("pneed")) & ((F.col("upto") >= F.col("pneed")) | (F.col("bin") == F.col("last"))))
        counts_below = scratch.save(hit.select("q_block", "query", (F.col("plow") + F.col("bin") * width).alias("low"), (F.col("pneed") - (F.col("upto") - F.col("n"))).alias("need")))
        state = _state(counts_below)
        if width == 1:
            break
        span, width = width, max(1, -(-width // bins))
    best = _final_pass(meet(state), k)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "id", "score")


def _largest_norm(rows: DataFrame) -> DataFrame:
    return rows.agg(F.max(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x * x)))


def _state(found: DataFrame) -> DataFrame:
    """Per query block the (position, low, need) of its queries, packed."""
    packed = found.groupBy("q_block").agg(F.collect_list(F.struct("query", "low", "need")).alias("s"))
    return packed.select("q_block", F.to_json("s").cast("binary").alias("state"))


def _read_state(state: bytes | None, n: int, low: int, need: int, span: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    import json

    if state is None:
        return np.full(n, low), np.full(n, low + span), np.full(n, need)
    lows, needs = np.zeros(n, dtype=np.int64), np.zeros(n, dtype=np.int64)
    for s in json.loads(state):
        lows[s["query"]], needs[s["query"]] = s["low"], s["need"]
    return lows, lows + span, needs


def _histogram_pass(pairs: DataFrame, low: int, span: int, width: int, bins: int, k: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                q_ids, q = unpack(r["q_ids"], r["q_vecs"], r["c_dim"])
                c_ids, c = unpack(r["c_ids"], r["c_vecs"], r["c_dim"])
                lows, highs, needs = _read_state(r["state"], len(q_ids), low, k, span)
                scores, counted = block_scores(q_ids, q, c_ids, c)
                row, at, n = _histogram(scores, counted, lows, highs, needs, width, bins)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(row), r["q_block"])), pa.array(row), pa.array(at), pa.array(n)], names=["q_block", "query", "bin", "n"])

    return pairs.mapInArrow(run, "q_block long, query long, bin long, n long")


def _final_pass(pairs: DataFrame, k: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                q_ids, q = unpack(r["q_ids"], r["q_vecs"], r["c_dim"])
                c_ids, c = unpack(r["c_ids"], r["c_vecs"], r["c_dim"])
                floor, _, needs = _read_state(r["state"], len(q_ids), 0, k, 1)
                scores, counted = block_scores(q_ids, q, c_ids, c)
                row, col = np.nonzero(counted & (scores >= floor[:, None]) & (needs[:, None] > 0))
                s = scores[row, col]
                order = np.lexsort((c_ids[col], -s, row))  # within a block no more than k of a query can win
                row, col, s = row[order], col[order], s[order]
                first = np.searchsorted(row, row)
                win = np.arange(len(row)) - first < k
                row, col, s = row[win], col[win], s[win]
                yield pa.RecordBatch.from_arrays([pa.array(q_ids[row]), pa.array(c_ids[col]), pa.array(s)], names=["query_id", "id", "score"])

    return pairs.mapInArrow(run, "query_id long, id long, score long")


def top_k_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components become floor(64 * x); queries are the ids divisible by 20."""
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    whole = rows.where(usable(F.col("embedding"))).select("vec_id", F.transform("embedding", lambda x: F.floor(x.cast("double") * 64).cast("double")).alias("whole"))
    return top_k(whole, F.col("vec_id") % 20 == 0, "vec_id", "whole").withColumnRenamed("id", "vec_id")
