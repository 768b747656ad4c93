"""A few catalogue queries against their SQL at the smallest scale."""

import duckdb
import pytest

from cellgraph import catalogue

DIR = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents conversations pages embeddings".split()


@pytest.mark.parametrize("name", ["cells_summary", "cc_cell_road_range", "sssp_cell_hub", "pagerank_vertex_part_flow", "metric_idle", "asof_edges", "stream_components"])
def test_same_rows(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DIR}/{t}.parquet'")
    df = catalogue.queries()[name](spark, DIR)
    columns = ", ".join(df.columns)
    want = con.sql(f"SELECT {columns} FROM ({catalogue.oracle_sql()[name]})").fetchall()
    assert sorted(map(str, (tuple(r) for r in df.collect()))) == sorted(map(str, want))
