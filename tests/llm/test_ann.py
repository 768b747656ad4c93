"""Multiprobe hashing on the given vectors: recall against brute force, and how much of the table is visited."""

import collections

import numpy as np
import pytest
from pyspark.sql import functions as F

from cellgraph.llm import ann


def _brute(ids, x, queries, k):
    unit = x / np.linalg.norm(x, axis=1)[:, None]
    out = {}
    for q in queries:
        s = unit @ unit[q]
        out[ids[q]] = [ids[j] for j in np.lexsort((ids, -s)) if ids[j] != ids[q]][:k]
    return out


@pytest.mark.parametrize("sf", ["sf0.01", "sf0.1"])
def test_recall_and_visited_share(spark, sf):
    rows = spark.read.parquet(f"/root/testdata/{sf}/embeddings.parquet").orderBy("vec_id").collect()
    ids, x = np.array([r["vec_id"] for r in rows]), np.array([r["embedding"] for r in rows], dtype=float)
    queries = np.flatnonzero(ids % 50 == 0)
    want = _brute(ids, x, queries, 5)
    got = collections.defaultdict(list)
    for r in ann.ann_query(spark, f"/root/testdata/{sf}").orderBy("query_id", "rank").collect():
        got[r["query_id"]].append(r["vec_id"])
    assert got.keys() == want.keys() and all(len(v) == 5 for v in got.values())
    assert np.mean([len(set(got[q]) & set(want[q])) / 5 for q in want]) >= 0.9
    tables, unit = ann.HashTables(), ann.scaled(x)
    seen = np.zeros((len(queries), len(x)), dtype=bool)
    for t in range(tables.tables):
        seen |= tables.visited(*tables.success(unit[queries], t), tables.cells(unit, t))
    assert seen.mean() < 0.4


def test_groups_hold_every_visited_bucket():
    rng = np.random.default_rng(1)
    unit, tables = ann.scaled(rng.standard_normal((300, 24))), ann.HashTables()
    for t in range(tables.tables):
        ratio, least = tables.success(unit[:20], t)
        cells = tables.cells(unit, t)
        seen, groups = tables.visited(ratio, least, cells), tables.groups_of(ratio, least)
        for q in range(20):
            assert set(tables.group(cells)[seen[q]]) <= set(groups[q].tolist())


def test_few_and_opposed_vectors(spark):
    rows = [(0, [1.0, 0.0, 0.0]), (1, [-1.0, 0.0, 0.0]), (2, [-1.0, 0.01, 0.0]), (3, [0.0, 0.0]), (4, [1.0, 2.0])]
    got = [tuple(r)[:3] for r in ann.nearest(spark.createDataFrame(rows, "id long, vec array<double>"), F.lit(True)).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 2), (0, 2, 1), (1, 1, 2), (1, 2, 0), (2, 1, 1), (2, 2, 0)]
    assert ann.nearest(spark.createDataFrame([], "id long, vec array<float>"), F.lit(True)).count() == 0


def test_outliers_of_a_dense_mass(spark):
    rng = np.random.default_rng(3)
    mass = ann.scaled(rng.standard_normal((1, 32)) + 0.05 * rng.standard_normal((400, 32)))
    rows = [(i, v.tolist()) for i, v in enumerate(mass)] + [(1000, (-mass[0]).tolist()), (1001, (-mass[1]).tolist())]
    got = collections.Counter(r["query_id"] for r in ann.nearest(spark.createDataFrame(rows, "id long, vec array<double>"), F.col("id") >= 1000).collect())
    assert got == {1000: 5, 1001: 5}
