"""Mixing sources to target weights.

Every document gets a hash-random key.  Within each source the keys are cut into equal ranges
(the keys are uniform, so the ranges are balanced without sampling); the ranges' sizes give
distributed prefix sums, which say in which range a source's budget runs out.  That range is cut
into finer ones until it holds few documents, at any number of rows.  Only those few are sorted
document by document, and the budget is cut inside them to the exact word.  Whole epochs are taken before the partial one when the budget exceeds the source.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellgraph.scratch import Scratch

WORD = r"[^\x20\x09-\x0D]+"


def word_count(text) -> F.Column:
    """Number of maximal runs of characters other than the six ASCII white-space ones; null counts 0."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def plan_targets(sizes: list[tuple[str | None, int]], weights: tuple[float, ...], max_epochs: float) -> dict[str | None, float]:
    """Target per source: weight shares of the total, no target above max_epochs times its source's size.

    Sources are taken in code-point order, null last, and given the weights in turn.  What a cap cuts
    off goes to the uncapped sources in proportion to their weights, until no target is above its cap.
    """
    order = sorted(sizes, key=lambda x: (x[0] is None, x[0] or ""))
    size = dict(order)
    weight = {name: weights[i % len(weights)] for i, (name, _) in enumerate(order)}
    capped: dict[str | None, float] = {}
    total = float(sum(size.values()))
    while True:
        free = [name for name in weight if name not in capped]
        left, shares = total - sum(capped.values()), sum(weight[name] for name in free)
        targets = {name: left * weight[name] / shares for name in free}
        over = [name for name in free if targets[name] > max_epochs * size[name]]
        if not over:
            return capped | targets
        capped |= {name: float(max_epochs * size[name]) for name in over}


STEP = 10  # bits of the key that a pass looks at


def _prefix(bits) -> F.Column:
    return F.call_function("shiftright", F.col("_mix_key"), F.lit(64) - bits)


class MixPlan:
    """Where each source's budget runs out: a few numbers per source, found from range sums alone."""

    def __init__(self, rows: DataFrame, weights: tuple[float, ...], max_epochs: float, cut_rows: int = 4096):
        """rows: ``_mix_source``, ``_mix_size`` and ``_mix_key``, stored.  One row per source is collected, no document.

        The range in which a budget runs out is cut again while it holds more than ``cut_rows`` rows.
        """
        spark = rows.sparkSession
        scratch = Scratch(spark, "mix-ranges")
        sums = [F.sum("_mix_size").alias("n"), F.count(F.lit(1)).alias("c")]
        per_range = scratch.save(rows.groupBy("_mix_source", _prefix(F.lit(STEP)).alias("rng")).agg(*sums))
        sizes = [tuple(r) for r in per_range.groupBy("_mix_source").agg(F.sum("n")).collect()]
        targets = plan_targets(sizes, weights, max_epochs)
        plan = []
        for name, size in sizes:
            epochs, rest = divmod(int(targets[name] + 0.5), size) if size else (0, 0)
            plan.append((name, size, targets[name], epochs, rest))
        self.n_sources = len(plan)
        small = (lambda df: F.broadcast(df)) if self.n_sources <= 100_000 else (lambda df: df)
        cuts = {name: (None, None, 0) for name, *_ in plan}  # bits, prefix, words before
        todo, bits = {row[0]: row[4] for row in plan}, STEP
        while todo:
            open_ = spark.createDataFrame([(s, rest, cuts[s][2]) for s, rest in todo.items()], "s string, rest long, base long")
            ends = F.sum("n").over(Window.partitionBy("_mix_source").orderBy("rng").rowsBetween(Window.unboundedPreceding, 0))
            before = per_range.join(small(open_), F.col("_mix_source").eqNullSafe(F.col("s"))).withColumn("before", F.col("base") + ends - F.col("n"))
            reached = before.where("before < rest").groupBy("s").agg(F.max(F.struct("rng", "before", "c")).alias("at")).collect()
            todo_rows = {r["s"]: r["at"]["c"] for r in reached}
            for r in reached:
                cuts[r["s"]] = (bits, r["at"]["rng"], r["at"]["before"])
            todo = {s: rest for s, rest in todo.items() if todo_rows.get(s, 0) > cut_rows and bits < 60}
            if todo:
                chosen = spark.createDataFrame([(s, cuts[s][1]) for s in todo], "s string, prefix long")
                inside = rows.join(small(chosen), F.col("_mix_source").eqNullSafe(F.col("s")) & (_prefix(F.lit(bits)) == F.col("prefix")))
                bits += STEP
                per_range = scratch.save(inside.groupBy("_mix_source", _prefix(F.lit(bits)).alias("rng")).agg(*sums))
        self.table = spark.createDataFrame([(*row, *cuts[row[0]]) for row in plan], "_mix_s string, source_size long, target double, _mix_epochs long, _mix_rest long, _mix_bits int, _mix_cut long, _mix_before long")

    def place(self, rows: DataFrame) -> DataFrame:
        """Adds ``taken``; only rows of the range where a source's budget ends are shuffled and sorted."""
        table = F.broadcast(self.table) if self.n_sources <= 100_000 else self.table
        placed = rows.join(table, F.col("_mix_source").eqNullSafe(F.col("_mix_s"))).withColumn("_mix_rng", _prefix(F.coalesce("_mix_bits", F.lit(STEP))))
        inside = F.col("_mix_cut").isNotNull() & (F.col("_mix_rng") == F.col("_mix_cut"))
        outer = placed.where(~inside).withColumn("_mix_part", F.when(F.col("_mix_rng") < F.col("_mix_cut"), F.col("_mix_size")).otherwise(F.lit(0)))
        order = Window.partitionBy("_mix_source").orderBy("_mix_key", "_mix_id", "_mix_size").rowsBetween(Window.unboundedPreceding, 0)
        start = F.col("_mix_before") + F.sum("_mix_size").over(order) - F.col("_mix_size")
        edge = placed.where(inside).withColumn("_mix_part", F.greatest(F.lit(0), F.least(F.col("_mix_size"), F.col("_mix_rest") - start)))
        return outer.unionByName(edge).withColumn("taken", (F.col("_mix_epochs") * F.col("_mix_size") + F.coalesce("_mix_part", F.lit(0))).cast("long"))


def _keyed(docs: DataFrame, size, id_col: str, source_col: str, seed: int, tie) -> DataFrame:
    """Adds the mixing columns; rows without an id get their key from ``tie``."""
    key = F.xxhash64(F.lit(seed), F.col(id_col), F.when(F.col(id_col).isNull(), tie))
    return docs.select("*", F.col(id_col).alias("_mix_id"), F.col(source_col).alias("_mix_source"), size.alias("_mix_size"), key.alias("_mix_key"))


def mix(
    docs: DataFrame,
    id_col: str = "doc_id",
    size_col: str = "size",
    source_col: str = "source",
    weights: tuple[float, ...] = (5, 2, 1),
    max_epochs: float = 3,
    seed: int = 17,
    tie_col: str | None = None,
    cut_rows: int = 4096,
) -> DataFrame:
    """``(id, source, size, source_size, target, taken, mix_key)`` for every row.

    ``taken`` is how much of the row the mix takes, repeats counted: whole epochs of the source plus a
    last, partial epoch in key order that is cut at the budget, the boundary row in part.  Each
    source's taken sum is its target rounded to a whole number.  Rows of size 0 or null (null or empty
    texts) take 0; a null source is a source; rows of equal id are told apart by size and are otherwise
    interchangeable; rows of null id get their keys from ``tie_col`` (by default their size); an empty table
    gives an empty result; other columns are ignored.
    """
    tie = F.col(size_col if tie_col is None else tie_col).alias("tie")
    slim = docs.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), F.coalesce(F.col(size_col).cast("long"), F.lit(0)).alias("size"), tie)
    rows = Scratch(docs.sparkSession, "mix").save(_keyed(slim, F.col("size"), "id", "source", seed, F.col("tie")).drop("tie"))
    placed = MixPlan(rows, weights, max_epochs, cut_rows).place(rows)
    return placed.select(F.col("id").alias(id_col), "source", "size", "source_size", "target", "taken", F.col("_mix_key").alias("mix_key"))


def mix_documents(docs: DataFrame, **options) -> DataFrame:
    """`mix` over a table of documents, sized by their words."""
    return mix(docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), F.xxhash64("text").alias("tie")), tie_col="tie", **options)


def apply_mix(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), max_epochs: float = 3, seed: int = 17, cut_rows: int = 4096) -> DataFrame:
    """The mixed corpus itself, with the columns of ``docs``; texts are not shuffled, except those of the few rows where a budget ends.

    A document comes as often as the mix takes it, whole; the share of the boundary document is
    rounded to whole copies (from one half up).  Null and empty texts, and others without words, cost no budget and
    come once.  Repeated rows and rows of null id are mixed like others; a null source is a source; an empty
    table gives an empty result; columns of any name but ``_mix_...`` are kept as they are.
    """
    size, tie = word_count(F.col("text")), F.xxhash64("text")
    slim = _keyed(docs.select("doc_id", "source", size.alias("size"), tie.alias("tie")), F.col("size"), "doc_id", "source", seed, F.col("tie"))
    plan = MixPlan(Scratch(docs.sparkSession, "mix").save(slim.select("_mix_source", "_mix_size", "_mix_key")), weights, max_epochs, cut_rows)
    whole = docs.select(F.struct("*").alias("_mix_doc"))
    keyed = _keyed(whole, word_count(F.col("_mix_doc.text")), "_mix_doc.doc_id", "_mix_doc.source", seed, F.xxhash64("_mix_doc.text"))
    copies = F.when(F.col("_mix_size") == 0, F.lit(1)).otherwise(F.floor(F.col("taken") / F.col("_mix_size") + 0.5)).cast("int")
    return plan.place(keyed).select("_mix_doc", F.explode(F.array_repeat(F.lit(1), copies)).alias("_mix_copy")).select("_mix_doc.*")


def mix_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mix_documents(docs).select("doc_id", "size", "source_size", "target", "taken", "source", "mix_key")
