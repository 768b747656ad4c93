"""Graphs made from the given tables (definitions in FIXTURES.md), with the same graphs as SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellgraph.cells import CellGraph, discover_cells
from cellgraph.graph import Graph, from_bipartite, from_equal, from_foreign_key, from_similarity, from_succession
from cellgraph.partition import block_of, partition_blocks


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _micros(ts: str = "ts") -> F.Column:
    """Microseconds since 1970 by the clock that the column shows, with or without a time zone."""
    c = F.col(ts)
    seconds = (F.unix_date(F.to_date(c)).cast("long") * 24 + F.hour(c)) * 3600 + F.minute(c) * 60
    return seconds * 1_000_000 + (F.extract(F.lit("SECOND"), c) * 1_000_000).cast("long")


def _road(spark: SparkSession, sf_dir: str, row, group, rung: int) -> Graph:
    """Rows of consecutive events; every ``rung``-th rank is joined to the same rank of the next row of its group."""
    events = _table(spark, sf_dir, "events").select(F.col("event_id").alias("vid"), "ts", row.alias("line"), group.alias("area"))
    ranked = events.withColumn("rank", F.row_number().over(Window.partitionBy("line").orderBy("ts", "vid")))
    ranked = ranked.withColumn("sec", F.floor(_micros() / 1_000_000))
    gap = lambda a, b: F.abs(F.col(a) - F.col(b)).cast("long").alias("weight")
    nxt = lambda part: ranked.select("vid", "sec", "area", "rank", *[F.lead(c).over(Window.partitionBy(*part).orderBy("line", "rank")).alias(f"n_{c}") for c in ("vid", "sec", "line")], "line")
    along = nxt(["line"]).where("n_vid is not null").select(F.col("vid").alias("src"), F.col("n_vid").alias("dst"), gap("sec", "n_sec"))
    across = nxt(["area", "rank"]).where((F.col("rank") % rung == 0) & F.col("n_vid").isNotNull() & (F.col("n_line") == F.col("line") + 1))
    return Graph.from_edges(along.union(across.select(F.col("vid").alias("src"), F.col("n_vid").alias("dst"), gap("sec", "n_sec"))), events.select("vid"))


def event_road(spark: SparkSession, sf_dir: str) -> Graph:
    day = F.floor(_micros() / 86_400_000_000)
    return _road(spark, sf_dir, day, F.floor((day + 3) / 7), 25)  # day 0 is a Thursday: weeks begin on Monday


def road_hour(spark: SparkSession, sf_dir: str) -> Graph:
    hour = F.floor(_micros() / 3_600_000_000)
    return _road(spark, sf_dir, hour, F.floor(hour / 24), 5)


def user_chain(spark: SparkSession, sf_dir: str, directed: bool = False) -> Graph:
    events = _table(spark, sf_dir, "events").select("event_id", "ts", "user_id")
    return Graph.from_edges(from_succession(events, ["user_id"], ["ts", "event_id"], "event_id"), events.select(F.col("event_id").alias("vid")), directed)


def hub_tree(spark: SparkSession, sf_dir: str) -> Graph:
    t = lambda name: _table(spark, sf_dir, name)
    k = lambda col, kind: F.col(col).cast("long") * 10 + kind
    root, hub = F.lit(5).cast("long"), F.lit(6).cast("long")
    edges = from_foreign_key(t("orders"), k("o_orderkey", 0), k("o_custkey", 1))
    for more in (
        from_foreign_key(t("customer"), k("c_custkey", 1), k("c_nationkey", 2)),
        from_foreign_key(t("nation"), k("n_nationkey", 2), k("n_regionkey", 3)),
        from_foreign_key(t("region"), k("r_regionkey", 3), root),
        from_foreign_key(t("supplier"), k("s_suppkey", 4), k("s_nationkey", 2)),
        from_foreign_key(t("orders").where("o_orderstatus = 'P'"), k("o_orderkey", 0), hub),
    ):
        edges = edges.union(more)
    return Graph.from_edges(edges)


def order_supplier(spark: SparkSession, sf_dir: str) -> Graph:
    return Graph.from_edges(from_bipartite(_table(spark, sf_dir, "lineitem"), F.col("l_orderkey") * 10, F.col("l_suppkey") * 10 + 1))


def part_flow(spark: SparkSession, sf_dir: str) -> Graph:
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    pairs = from_succession(lines, ["l_orderkey"], ["l_linenumber", "l_partkey", "l_suppkey"], "l_partkey").where("src <> dst")
    return Graph.from_edges(pairs.select("src", "dst").distinct(), directed=True)


#: More turns than a conversation has.
TURNS = 1 << 20


def conv_turns(spark: SparkSession, sf_dir: str) -> Graph:
    turns = _table(spark, sf_dir, "conversations").select("conv_id", "turn", (F.col("conv_id") * TURNS + F.col("turn")).alias("vid"))
    return Graph.from_edges(from_succession(turns, ["conv_id"], ["turn"], "vid"), turns.select("vid"))


def doc_copies(spark: SparkSession, sf_dir: str) -> Graph:
    docs = _table(spark, sf_dir, "documents").select("doc_id", F.xxhash64("text").alias("h1"), F.sha2("text", 256).alias("text_key"))
    return Graph.from_edges(from_equal(docs, "doc_id", "text_key"), docs.select(F.col("doc_id").alias("vid")))


def road_fraction(spark: SparkSession, sf_dir: str) -> Graph:
    """The hourly road with fractional weights, whose sums are exact in binary."""
    g = road_hour(spark, sf_dir)
    return Graph(g.vertices, g.edges.withColumn("weight", F.col("weight") * F.lit(0.125) + F.lit(0.25)))


def knn(spark: SparkSession, sf_dir: str, least: float = 0.3) -> Graph:
    vectors = _table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return Graph.from_edges(from_similarity(vectors, "vec_id", "embedding", least))


def page_host(spark: SparkSession, sf_dir: str) -> Graph:
    """Pages to the least page of their host: a star per host."""
    pages = _table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))
    return Graph.from_edges(from_equal(pages, "page_id", "host"), pages.select(F.col("page_id").alias("vid")))


def in_blocks(g: Graph, k: int = 4) -> CellGraph:
    """Cells of contiguous id ranges over the ids there are."""
    g = g.stored()
    space = (g.vertices.agg(F.max("vid")).first()[0] or 0) + 1
    return discover_cells(g, partition_blocks(g, k, space), part_of=lambda vid: block_of(vid, k, space))


# --- the same graphs for the SQL side --------------------------------------------------------------

_ROAD_SQL = """
  SELECT vid, line, area, sec, row_number() OVER (PARTITION BY line ORDER BY ts, vid) AS rank
  FROM (SELECT event_id AS vid, ts, {row} AS line, {area} AS area, epoch_us(ts) // 1000000 AS sec FROM events)
"""


def _road_sql(row: str, area: str, rung: int) -> str:
    ranked = _ROAD_SQL.format(row=row, area=area)
    return f"""
  SELECT vid AS src, nv AS dst, abs(ns - sec) AS weight FROM (
    SELECT vid, sec, lead(vid) OVER w AS nv, lead(sec) OVER w AS ns FROM ({ranked}) WINDOW w AS (PARTITION BY line ORDER BY rank)) WHERE nv IS NOT NULL
  UNION ALL
  SELECT a.vid, b.vid, abs(b.sec - a.sec) FROM ({ranked}) a JOIN ({ranked}) b ON b.line = a.line + 1 AND b.area = a.area AND b.rank = a.rank WHERE a.rank % {rung} = 0
"""


EDGES_SQL = {
    "event_road": _road_sql("epoch_us(ts) // 86400000000", "(epoch_us(ts) // 86400000000 + 3) // 7", 25),
    "road_hour": _road_sql("epoch_us(ts) // 3600000000", "epoch_us(ts) // 86400000000", 5),
    "user_chain": "SELECT * FROM (SELECT event_id AS src, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst, 1::BIGINT AS weight FROM events) WHERE dst IS NOT NULL",
    "hub_tree": """
  SELECT o_orderkey * 10 AS src, o_custkey * 10 + 1 AS dst, 1::BIGINT AS weight FROM orders
  UNION ALL SELECT c_custkey * 10 + 1, c_nationkey * 10 + 2, 1 FROM customer
  UNION ALL SELECT n_nationkey * 10 + 2, n_regionkey * 10 + 3, 1 FROM nation
  UNION ALL SELECT r_regionkey * 10 + 3, 5, 1 FROM region
  UNION ALL SELECT s_suppkey * 10 + 4, s_nationkey * 10 + 2, 1 FROM supplier
  UNION ALL SELECT o_orderkey * 10, 6, 1 FROM orders WHERE o_orderstatus = 'P'""",
    "order_supplier": "SELECT DISTINCT l_orderkey * 10 AS src, l_suppkey * 10 + 1 AS dst, 1::BIGINT AS weight FROM lineitem",
    "part_flow": """
  SELECT DISTINCT src, dst, 1::BIGINT AS weight FROM (
    SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst FROM lineitem)
  WHERE dst IS NOT NULL AND src <> dst""",
    "conv_turns": "SELECT * FROM (SELECT conv_id * 1048576 + turn AS src, lead(conv_id * 1048576 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst, 1::BIGINT AS weight FROM conversations) WHERE dst IS NOT NULL",
    "doc_copies": "SELECT * FROM (SELECT doc_id AS src, min(doc_id) OVER (PARTITION BY text) AS dst, 1::BIGINT AS weight FROM documents WHERE text IS NOT NULL) WHERE src <> dst",
    "knn": "SELECT a.vec_id AS src, b.vec_id AS dst, 1::BIGINT AS weight FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id AND list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= 0.3",
    "page_host": "SELECT * FROM (SELECT page_id AS src, min(page_id) OVER (PARTITION BY regexp_extract(url, '^[a-z]+://([^/]+)', 1)) AS dst, 1::BIGINT AS weight FROM pages WHERE url IS NOT NULL) WHERE src <> dst",
}
EDGES_SQL["road_fraction"] = f"SELECT src, dst, weight * 0.125::DOUBLE + 0.25::DOUBLE AS weight FROM ({EDGES_SQL['road_hour']})"
VERTICES_SQL = {
    "road_fraction": "SELECT event_id AS vid FROM events",
    "page_host": "SELECT page_id AS vid FROM pages",
    "event_road": "SELECT event_id AS vid FROM events",
    "road_hour": "SELECT event_id AS vid FROM events",
    "user_chain": "SELECT event_id AS vid FROM events",
    "conv_turns": "SELECT conv_id * 1048576 + turn AS vid FROM conversations",
    "doc_copies": "SELECT doc_id AS vid FROM documents",
}


def vertices_sql(name: str) -> str:
    return VERTICES_SQL.get(name, f"SELECT src AS vid FROM ({EDGES_SQL[name]}) UNION SELECT dst FROM ({EDGES_SQL[name]})")
