"""Line dedup with levelled sorted runs, in DataFrame functions only.

A run is a table of line hashes with the number of documents that hold the line and the first of
them (by batch, then id), sorted by hash.  Documents come in batches.  Each batch is counted alone,
merge-anti-joined with the keys that the runs already show to be frequent (their fate is settled),
and what is left becomes a run of level 0.  As soon as a level holds ``fanout`` runs they are merged
into one run of the next level, counts added.  The store is a folder: it outlives the call, and a
later batch is added to what is there.  Only hashes (128 bits) travel; texts are shuffled once, as
whole rows, to meet the positions of their dropped lines.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellgraph.scratch import Scratch

#: The white space that is stripped from a line's ends, and the letters that are folded.
SPACE = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def line_key(line) -> F.Column:
    """The line without white space at its ends, A-Z lower-cased (other letters stay as they are)."""
    bare = F.btrim(line, F.lit(SPACE))
    return F.when(F.length(bare) == F.octet_length(bare), F.lower(bare)).otherwise(F.translate(bare, UPPER, LOWER))


def _hashes(key) -> list:
    return [F.xxhash64(key).alias("h1"), F.xxhash64(F.lit(1), key).alias("h2")]


def _lines(text) -> F.Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


class LineRuns:
    """The levelled store below ``root``, or in a scratch folder.

    A run is a folder ``<level>-<first>-<last>`` that holds the batches with those numbers; it appears
    by a rename when it is complete.  Opening a folder takes up its runs; those whose batches a higher
    level holds as well (the merge was done, the removal was not) are removed.
    """

    def __init__(self, spark: SparkSession, min_docs: int, fanout: int = 4, root: str | None = None):
        self.spark, self.min_docs, self.fanout = spark, min_docs, fanout
        self.scratch = Scratch(spark, "line-runs")
        self.root = (root or f"{self.scratch.root}/runs").rstrip("/")
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
        self._path = lambda name: path(f"{self.root}/{name}")
        self._fs = path(self.root).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        self._fs.mkdirs(path(self.root))
        names = [f.getPath().getName() for f in self._fs.listStatus(path(self.root))]
        found = [tuple(map(int, n.split("-"))) for n in names if n[0].isdigit()]
        held = [r for r in found if not any(o[0] > r[0] and o[1] <= r[1] and r[2] <= o[2] for o in found)]
        for r in found:
            if r not in held:
                self._remove(r)
        self.runs: list[tuple[int, int, int]] = sorted(held)

    @property
    def next_batch(self) -> int:
        return max((r[2] for r in self.runs), default=-1) + 1

    def _remove(self, run: tuple[int, int, int]) -> None:
        self._fs.delete(self._path("-".join(map(str, run))), True)

    def _read(self, run: tuple[int, int, int]) -> DataFrame:
        return self.spark.read.parquet(f"{self.root}/{'-'.join(map(str, run))}")

    def _write(self, df: DataFrame, run: tuple[int, int, int]) -> None:
        name = "-".join(map(str, run))
        df.sortWithinPartitions("h1", "h2").write.mode("overwrite").parquet(f"{self.root}/_{name}")
        if not self._fs.rename(self._path(f"_{name}"), self._path(name)):
            raise OSError(f"run {name} could not be put in place")
        self.runs.append(run)

    def _all(self, runs: list[tuple[int, int, int]]) -> DataFrame:
        out = self._read(runs[0])
        for run in runs[1:]:
            out = out.unionByName(self._read(run))
        return out

    def add(self, lines: DataFrame) -> None:
        """Adds a batch: ``lines(id, h1, h2)``, a row for each distinct line of a document; an empty batch makes an empty run."""
        number = self.next_batch
        first = F.struct(F.lit(number).alias("batch"), F.min("id").alias("id"))
        batch = lines.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n"), first.alias("first"))
        if self.runs:
            batch = batch.join(self._all(self.runs).where(F.col("n") >= self.min_docs).select("h1", "h2"), ["h1", "h2"], "left_anti")
        self._write(batch, (0, number, number))
        level = 0
        while len(full := [r for r in self.runs if r[0] == level]) >= self.fanout:
            self._write(self._merged(full), (level + 1, min(r[1] for r in full), max(r[2] for r in full)))
            for run in full:
                self.runs.remove(run)
                self._remove(run)
            level += 1

    def _merged(self, runs: list[tuple[int, int, int]]) -> DataFrame:
        return self._all(runs).groupBy("h1", "h2").agg(F.sum("n").alias("n"), F.min("first").alias("first"))

    def frequent(self) -> DataFrame:
        """``(h1, h2, first)`` of the keys found in at least ``min_docs`` documents of all batches so far."""
        totals = self._read(self.runs[0]) if len(self.runs) == 1 else self._merged(self.runs)
        return totals.where(F.col("n") >= self.min_docs).select("h1", "h2", "first")


def _batch(id_col: str, batches: int) -> F.Column:
    return F.pmod(F.xxhash64(id_col), F.lit(batches)).cast("int")


def distinct_lines(docs: DataFrame, text_col: str, min_chars: int, batches: int, id_col: str) -> DataFrame:
    """``(id, h1, h2, batch)``: a row for each distinct key of a document; keys are made distinct inside the document, before anything travels."""
    keys = F.filter(F.array_distinct(F.transform(_lines(F.col(text_col)), line_key)), lambda k: F.length(k) >= min_chars)
    each = docs.select(_batch(id_col, batches).alias("batch"), F.col(id_col).alias("id"), F.explode(keys).alias("key"))
    return each.select("id", *_hashes(F.col("key")), "batch")


def frequent_lines(docs: DataFrame, text_col: str = "text", min_docs: int = 10, min_chars: int = 1, batches: int = 4, fanout: int = 4, id_col: str = "doc_id", store: str | None = None) -> tuple[DataFrame, int]:
    """``(h1, h2, first)`` of the frequent keys, and the number of the first batch.

    The documents go to the runs in ``batches`` batches by id hash, one after the other; each is counted
    alone.  Their hashed lines are written once, a folder per batch.
    """
    runs = LineRuns(docs.sparkSession, min_docs, fanout, store)
    before = runs.next_batch
    lines = distinct_lines(docs, text_col, min_chars, batches, id_col)
    path = f"{runs.scratch.root}/lines"
    lines.write.partitionBy("batch").parquet(path)
    stored = docs.sparkSession.read.schema(lines.schema).parquet(path)
    for b in range(batches):
        runs.add(stored.where(F.col("batch") == b))
    found = runs.scratch.save(runs.frequent())
    runs.scratch._delete(path)
    return found, before


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_docs: int = 10, min_chars: int = 1, batches: int = 4, fanout: int = 4, broadcast_keys: int = 500_000, keep_first: bool = False, store: str | None = None, names: tuple[str, str, str] = ("kept_text", "n_lines", "n_dropped")) -> DataFrame:
    """``docs`` with three columns added, by default ``kept_text``, ``n_lines`` and ``n_dropped``; columns of ``docs`` with one of ``names`` are replaced.

    A line found in at least ``min_docs`` documents goes from all of them or, with ``keep_first``, from
    all but the first (by batch, then id).  A null or empty text is one empty line and is kept as an empty text.  Rows are documents: repeated
    rows count as often as they come and get the same answer.  Very long lines and texts are hashed
    whole; an empty table gives an empty result; a null id is an id of its own.  With ``store``, a shared folder, the lines
    of earlier calls on it count as well, and those of this one stay there for later calls.  At most ``broadcast_keys`` frequent keys (8 MB) are broadcast; beyond that they are joined
    by shuffle, with the lines salted so that one line in a third of all documents is no hot task.
    """
    keys, before = frequent_lines(docs, text_col, min_docs, min_chars, batches, fanout, id_col, store)
    n_keys = keys.count()
    row = [F.xxhash64(id_col, text_col).alias("_r1"), F.xxhash64(F.lit(1), id_col, text_col).alias("_r2")]
    held = docs.select(*row, F.col(id_col).alias("_id"), (_batch(id_col, batches) + before).alias("_batch"), F.posexplode(_lines(F.col(text_col))).alias("_pos", "_line")).withColumn("_key", line_key(F.col("_line")))
    held = held.where(F.length("_key") >= min_chars).select("_r1", "_r2", "_pos", "_id", "_batch", *_hashes(F.col("_key")))
    later = (F.col("first.batch") < F.col("_batch")) | ~F.col("first.id").eqNullSafe(F.col("_id")) if keep_first else F.lit(True)
    if n_keys <= broadcast_keys:
        hits = held.join(F.broadcast(keys), ["h1", "h2"]).where(later)
    else:
        salts = 32
        salted = keys.select("h1", "h2", "first", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("_salt"))
        hits = held.withColumn("_salt", F.pmod("_r1", F.lit(salts)).cast("int")).join(salted, ["h1", "h2", "_salt"]).where(later)
    dropped = hits.groupBy("_r1", "_r2").agg(F.collect_set("_pos").alias("_drop"))
    joined = docs.select("*", *row).join(dropped, ["_r1", "_r2"], "left")
    lines = _lines(F.col(text_col))
    n_lines = F.size(lines)
    positions = F.array_except(F.sequence(F.lit(0), n_lines - 1), F.col("_drop"))
    kept = F.when(F.col("_drop").isNull(), F.coalesce(F.col(text_col), F.lit(""))).otherwise(F.array_join(F.transform(positions, lambda i: F.get(lines, i)), "\n"))
    return joined.select(
        *[F.col(c) for c in docs.columns if c not in names],
        kept.alias(names[0]),
        n_lines.cast("long").alias(names[1]),
        F.when(F.col("_drop").isNull(), F.lit(0)).otherwise(F.size("_drop")).cast("long").alias(names[2]),
    )


def line_dedup_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = dedup_lines(docs)
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))
