"""SimHash near-dedup with pigeonring filtering.

A fingerprint is cut into a ring of segments.  If two fingerprints differ in at most t bits, some
segment starts a chain along the ring in which the first l segments together differ in at most
floor(l * t / m) bits, for every l.  With t < m the first segment of that chain must be equal, and
with t < 2m the second differs in at most one bit, so one of its two halves is equal too: segment
plus half make the join key, the chain condition prunes what meets under it, and only the rest
gets the full Hamming check.

Equal fingerprints are merged before the join.  A key under which more than ``hot`` distinct
fingerprints meet is not joined in pairs: its fingerprints go by the exact midpoint route, where
each emits itself and its one-bit neighbours and any two that share one are within two bits.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellgraph.algorithms.contraction import components
from cellgraph.scratch import Scratch
from cellgraph.workers import lean

BITS = 64
_BLOCK = 1 << 15


def shingles(text: str | None, words: int) -> list[bytes]:
    """Word shingles in order, repeats included, after A-Z is lower-cased; fewer words make one shingle, none make none."""
    tokens = text.encode().lower().split() if text else []
    if len(tokens) <= words:
        return [b" ".join(tokens)] if tokens else []
    return [b" ".join(t) for t in zip(*(tokens[i:] for i in range(words)), strict=False)]


def majority_bits(hashes: np.ndarray) -> int:
    """The 64-bit word whose bit is 1 where over half of the hashes have it; 0 for no hash."""
    counts = np.zeros(BITS, dtype=np.int64)
    for at in range(0, len(hashes), _BLOCK):
        part = hashes[at : at + _BLOCK]
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(counts * 2 > len(hashes), bitorder="little").view(np.uint64)[0]) if len(hashes) else 0


def fingerprint(text: str | None, words: int = 3, seed: int = 42) -> int:
    import xxhash

    digest = xxhash.xxh64_intdigest
    parts = shingles(text, words)
    return majority_bits(np.fromiter((digest(s, seed) for s in parts), dtype=np.uint64, count=len(parts)))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, seed: int = 42) -> DataFrame:
    """``(id, fp)``; whole texts, one pass, no shuffle.  Null, empty and blank texts have fingerprint 0."""

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.fromiter((fingerprint(t.as_py(), words, seed) for t in b.column(1)), dtype=np.uint64, count=b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64))], names=["id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("id"), text_col).mapInArrow(run, "id long, fp long")


def ring(bits: int, segments: int) -> list[tuple[int, int]]:
    """(offset, width) of nearly equal segments."""
    ends = [round(i * bits / segments) for i in range(segments + 1)]
    return [(a, b - a) for a, b in zip(ends, ends[1:], strict=False)]


def _cut(fp, offset: int, width: int) -> F.Column:
    return F.shiftrightunsigned(fp, offset).bitwiseAND(F.lit((1 << width) - 1))


def ring_keys(fp, segments: int, bits: int = BITS) -> F.Column:
    """Array of join keys, two for each chain start: (2 * start + half, first segment, that half of the second)."""
    parts, keys = ring(bits, segments), []
    for i, (offset, width) in enumerate(parts):
        after, after_width = parts[(i + 1) % segments]
        low = after_width // 2
        for half, (o, w) in enumerate(((after, low), (after + low, after_width - low))):
            keys.append(F.lit((2 * i + half) << 56).bitwiseOR(F.shiftleft(_cut(fp, offset, width), 24)).bitwiseOR(_cut(fp, o, w)))
    return F.array(*keys)


def chain_holds(diff, start: F.Column, max_bits: int, segments: int, bits: int = BITS) -> F.Column:
    """Whether the chain from ``start`` keeps within its proportional budgets, for every length."""
    parts = ring(bits, segments)
    cases = F.lit(False)
    for i in range(segments):
        ok, spent = F.lit(True), F.lit(0)
        for length in range(1, segments + 1):
            offset, width = parts[(i + length - 1) % segments]
            spent = spent + F.bit_count(_cut(diff, offset, width))
            ok = ok & (spent <= math.floor(length * max_bits / segments))
        cases = F.when(start == i, ok).otherwise(cases)
    return cases


def busy_keys(keyed: DataFrame, hot: int, scratch: Scratch) -> tuple[DataFrame, int, Callable[[DataFrame], DataFrame]]:
    """Keys under which more than ``hot`` rows meet, their number, and how to mark them in a join: broadcast only if few."""
    busy = scratch.save(keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("rep").alias("leader")).where(F.col("n") > hot).select("key", "leader"))
    n = busy.count()
    return busy, n, F.broadcast if n <= 500_000 else (lambda df: df)


def linked_fingerprints(groups: DataFrame, max_bits: int, segments: int, hot: int, scratch: Scratch) -> DataFrame:
    """Edges ``(a, b)`` between rows of ``groups(fp, rep)``, fps distinct, that connect all fps within ``max_bits``."""
    if segments <= max_bits:
        raise ValueError("a ring needs more segments than bits may differ")
    keyed = scratch.save(groups.select("fp", "rep", F.explode(ring_keys(F.col("fp"), segments)).alias("key")))
    n_busy = 0
    if max_bits == 2:  # for other limits every key is joined in pairs, which is exact as well
        busy, n_busy, mark = busy_keys(keyed, hot, scratch)
    cold = keyed.join(mark(busy), "key", "left_anti") if n_busy else keyed
    left = cold.select("key", F.col("fp").alias("fa"), F.col("rep").alias("a"))
    right = cold.select(F.col("key").alias("key_b"), F.col("fp").alias("fb"), F.col("rep").alias("b"))
    diff = F.col("fa").bitwiseXOR(F.col("fb"))
    start = F.shiftright("key", 57)
    pairs = left.join(right, (F.col("key") == F.col("key_b")) & (F.col("fa") < F.col("fb")) & chain_holds(diff, start, max_bits, segments) & (F.bit_count(diff) <= max_bits))
    edges = pairs.select("a", "b")
    if n_busy:
        crowd = keyed.join(mark(busy), "key", "left_semi").select("fp", "rep").distinct()
        flips = [F.col("fp"), *(F.col("fp").bitwiseXOR(F.lit(1 << b if b < 63 else -(1 << 63))) for b in range(BITS))]
        near = scratch.save(crowd.select("rep", F.explode(F.array(*flips)).alias("mid")))
        stars = scratch.save(near.groupBy("mid").agg(F.min("rep").alias("hub"), F.count(F.lit(1)).alias("n")).where("n > 1").select("mid", "hub"))
        edges = edges.union(near.join(stars, "mid").where("rep != hub").select(F.col("hub").alias("a"), F.col("rep").alias("b")))
    return scratch.save(edges.distinct())


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, max_bits: int = 2, segments: int = 3, hot: int = 64, seed: int = 42) -> DataFrame:
    """``(id, fp, component_id)`` for every row of ``docs``.

    Documents link when their fingerprints differ in at most ``max_bits`` bits; component_id is the
    least id reachable, the document itself included.  Blank texts share fingerprint 0 and link like any
    other.  Rows of null id keep a fingerprint and get the least id of their component, if any.  Repeated
    rows get equal answers.  Nothing is capped: hot keys take an exact route of linear size.
    """
    scratch = Scratch(docs.sparkSession, "simhash")
    fps = scratch.save(fingerprints(docs, id_col, text_col, words, seed))
    groups = scratch.save(fps.groupBy("fp").agg(F.min("id").alias("rep")).where("rep is not null"))
    edges = linked_fingerprints(groups, max_bits, segments, hot, scratch)
    found = components(docs.sparkSession, edges, scratch=scratch)
    merged = scratch.save(groups.join(found, groups.rep == found.v, "left").select("fp", F.coalesce("component", "rep").alias("component_id")))
    return fps.join(merged, "fp", "left").select("id", "fp", "component_id")


def simhash_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = near_duplicates(docs)
    return out.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
