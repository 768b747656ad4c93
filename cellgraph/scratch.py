"""Intermediate tables in the folder that all executors share.

Lineage is cut with Parquet tables below ``spark.checkpoint.dir`` (columnar, compressed and
re-readable after an executor is lost) rather than with block-manager copies.  A table read back
has no remembered partitioning, so a join on it gets ordinary exchanges, which adaptive execution
may split when a key is skewed.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder; only a local session without one gets a temporary folder."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        if sc.master.startswith("local") and not sc.master.startswith("local-cluster"):
            sc.setCheckpointDir(tempfile.mkdtemp(prefix="cellgraph-"))
        else:
            sc.setCheckpointDir(spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_checkpoints")
    return sc.getCheckpointDir()


class Scratch:
    """Writes tables for one operator call and removes those that are no longer read."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"
        self._paths: dict[int, str] = {}
        atexit.register(self._at_exit)

    def save(self, df: DataFrame) -> DataFrame:
        path = f"{self.root}/{len(self._paths)}-{uuid.uuid4().hex[:6]}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self._paths[id(out)] = path
        out._scratch_path = path
        return out

    def counted(self, df: DataFrame, **sums: Column) -> tuple[DataFrame, dict]:
        """`save`, with aggregates of the written rows taken on the way."""
        seen = Observation()
        out = self.save(df.observe(seen, *[c.alias(name) for name, c in sums.items()]))
        return out, seen.get

    def drop(self, *frames: DataFrame) -> None:
        for df in frames:
            path = getattr(df, "_scratch_path", None)
            if path:
                self._delete(path)

    def _delete(self, path: str) -> None:
        jvm = self.spark.sparkContext._jvm
        hadoop_path = jvm.org.apache.hadoop.fs.Path(path)
        hadoop_path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop_path, True)

    def _at_exit(self) -> None:
        try:
            self._delete(self.root)
        except Exception:  # the session has ended before this process did
            pass
