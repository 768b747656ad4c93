"""The slice store: a cell graph written once and read many times.

Topology and each family of attributes are Parquet tables of their own, partitioned by part, sorted by
cell: reading some parts prunes folders, reading some cells prunes row groups, and attributes that an
algorithm does not name are never opened.
"""

from __future__ import annotations

import json
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from cellgraph.cells import CellGraph
from cellgraph.graph import Graph
from cellgraph.scratch import Scratch


class SliceStore:
    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")

    def write(self, cg: CellGraph, attributes: dict[str, DataFrame] | None = None, partitioner: str = "unknown") -> None:
        """``attributes``: families of columns by name, each with a ``vid`` column."""
        parts = cg.cell_of.select("pid").distinct().count()
        topology = cg.links.withColumn("pid", F.col("src_pid"))
        topology.repartition(max(1, parts), "pid").sortWithinPartitions("pid", "src_cell").write.mode("overwrite").partitionBy("pid").parquet(f"{self.root}/topology")
        cg.cell_of.repartition(max(1, parts), "pid").sortWithinPartitions("pid", "cell_id").write.mode("overwrite").partitionBy("pid").parquet(f"{self.root}/cells")
        schemas = {}
        for name, df in (attributes or {}).items():
            schemas[name] = json.loads(df.schema.json())
            df.join(cg.cell_of, "vid").repartition(max(1, parts), "pid").sortWithinPartitions("pid", "cell_id").write.mode("overwrite").partitionBy("pid").parquet(f"{self.root}/attr_{name}")
        meta = {"parts": parts, "partitioner": partitioner, "directed": cg.graph.directed, "vertices": cg.cell_of.count(), "arcs": cg.links.count(), "attributes": schemas}
        self.spark.createDataFrame([(json.dumps(meta),)], "meta string").coalesce(1).write.mode("overwrite").text(f"{self.root}/meta")

    def meta(self) -> dict:
        return json.loads(self.spark.read.text(f"{self.root}/meta").first()[0])

    def schema(self, family: str) -> StructType:
        return StructType.fromJson(self.meta()["attributes"][family])

    def cells(self, pid: int) -> DataFrame:
        return self.spark.read.parquet(f"{self.root}/cells").where(F.col("pid") == pid).groupBy("cell_id").agg(F.count(F.lit(1)).alias("n_vertices"))

    def read_topology(self, pids: Iterable[int] | None = None, cells: Iterable[int] | None = None) -> DataFrame:
        df = self.spark.read.parquet(f"{self.root}/topology")
        if pids is not None:
            df = df.where(F.col("pid").isin(list(pids)))
        return df if cells is None else df.where(F.col("src_cell").isin(list(cells)))

    def load(self, spark: SparkSession) -> CellGraph:
        """The cell graph again, as it was written: no placement, no search for cells, no resolving of far ends."""
        links, cells = self.spark.read.parquet(f"{self.root}/topology").drop("pid"), self.spark.read.parquet(f"{self.root}/cells").select("vid", "pid", "cell_id")
        edges = links.select("src", "dst", "weight")
        directed = self.meta()["directed"]
        if not directed:  # each edge is stored in both directions, a loop twice
            loops = edges.where("src = dst").groupBy("src", "dst", "weight").agg(F.count(F.lit(1)).alias("n"))
            once = loops.select("src", "dst", "weight", F.explode(F.array_repeat(F.lit(1), (F.col("n") / 2).cast("int"))).alias("_n")).drop("_n")
            edges = edges.where("src < dst").unionByName(once)
        return CellGraph(Graph(cells.select("vid"), edges, directed), cells, links, Scratch(spark, "slices"))

    def read_attributes(self, family: str, names: list[str]) -> DataFrame:
        return self.spark.read.parquet(f"{self.root}/attr_{family}").select("vid", "pid", "cell_id", *names)


def read_edge_list(spark: SparkSession, path: str, form: str = "csv", schema: str = "src long, dst long, weight double", sep: str = ",") -> DataFrame:
    """Edges from CSV, JSON, ORC, Parquet, or text of ids parted by white space (lines of # are comments)."""
    if form == "text":
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where("value rlike '^\\\\s*[0-9]'")
        return lines.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"))
    if form == "csv":
        return spark.read.csv(path, schema=schema, sep=sep)
    return spark.read.schema(schema).format(form).load(path)
