"""Graphs that arrive as streams of events."""

from __future__ import annotations

import os

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellgraph.algorithms.contraction import components
from cellgraph.scratch import Scratch, shared_dir


def event_stream(spark: SparkSession, path: str, files_per_batch: int | None = None) -> DataFrame:
    """The events table, a file or a folder, as a stream of its files in the order they were written, all at once or some to a batch."""
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(place).isDirectory():
        stream = reader.parquet(path)
    else:
        folder, name = os.path.split(path.rstrip("/"))
        stream = reader.option("pathGlobFilter", name).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))  # event time needs a zone


def drain(spark: SparkSession, stream: DataFrame, mode: str, name: str) -> DataFrame:
    """Runs a stream over all that is there now and returns the sink's rows (last epoch's, for complete mode)."""
    scratch = Scratch(spark, f"stream-{name}")
    out: list[DataFrame] = []

    def keep(batch: DataFrame, _: int) -> None:
        if mode == "complete":
            out.clear()
        out.append(scratch.save(batch))

    stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{shared_dir(spark)}/{name}-{os.urandom(6).hex()}").trigger(availableNow=True).start().awaitTermination()
    if not out:  # nothing has arrived
        return spark.createDataFrame([], stream.schema)
    result = out[0]
    for more in out[1:]:
        result = result.unionByName(more)
    return result


def windowed_degree(stream: DataFrame, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Events per user and window."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", length, slide) if slide else F.window("ts", length), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "user_id", "n")


def sessions(stream: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("session_window.start").cast("timestamp_ntz").alias("start"), "user_id", "n")


def succession(stream: DataFrame) -> DataFrame:
    """Edges ``(src, dst)`` from each event to the user's next one; the last event of a user is state.

    Events of a micro-batch are put in order; one that arrives in a later batch than its successor is
    joined to the user's last event at that time.
    """

    def follow(key, batches, state):
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        ids = ([state.get[0]] if state.exists else []) + rows["event_id"].tolist()
        state.update((ids[-1],))
        yield pd.DataFrame({"src": ids[:-1], "dst": ids[1:]}, dtype="int64")

    return stream.select("user_id", "ts", "event_id").groupBy("user_id").applyInPandasWithState(follow, "src long, dst long", "last long", "append", "NoTimeout")


def components_of_stream(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    """``(v, label)`` of edge files ``(src long, dst long)`` taken in as a stream, some files at a time."""
    held = IncrementalComponents(spark)
    stream = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    writer = stream.writeStream.foreachBatch(lambda batch, _: held.add(held.scratch.save(batch)))
    writer.option("checkpointLocation", f"{shared_dir(spark)}/stream-components-{os.urandom(6).hex()}").trigger(availableNow=True).start().awaitTermination()
    return held.labels if held.labels is not None else spark.createDataFrame([], "v long, label long")


class IncrementalComponents:
    """Labels kept up to date batch by batch: new edges are lifted to labels, and only the label graph is solved."""

    def __init__(self, spark: SparkSession):
        self.spark, self.scratch = spark, Scratch(spark, "incremental")
        self.labels: DataFrame | None = None

    def add(self, edges: DataFrame) -> None:
        ends = edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
        if self.labels is None:
            known = self.scratch.save(ends.select("v", F.col("v").alias("label")))
        else:
            new = ends.join(self.labels, "v", "left_anti").select("v", F.col("v").alias("label"))
            known = self.scratch.save(self.labels.unionByName(new))
        end = lambda name: known.select(F.col("v").alias(name), F.col("label").alias(f"{name}_label"))
        lifted = edges.join(end("src"), "src").join(end("dst"), "dst").select(F.col("src_label").alias("a"), F.col("dst_label").alias("b"))
        merged = components(self.spark, lifted, scratch=self.scratch).withColumnRenamed("v", "label")
        self.labels = self.scratch.save(known.join(merged, "label", "left").select("v", F.coalesce("component", "label").alias("label")))
        self.scratch.drop(known)
