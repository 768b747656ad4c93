"""The levelled store: batches counted alone, runs that outlive the call."""

import collections
import random

import pytest
from pyspark.sql import functions as F

from cellgraph.llm import linededup


def _docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string")


def _rows(seed, ids):
    rng = random.Random(seed)
    return [(i, "\n".join(rng.choice([f"l{k}" for k in range(25)]) for _ in range(rng.randrange(1, 5)))) for i in ids]


def _counts(rows):
    return collections.Counter(k for _, t in rows for k in set(t.split("\n")))


@pytest.mark.parametrize("fanout, batches", [(2, 5), (3, 4), (4, 4), (10, 3)])
def test_runs_hold_the_counts(spark, tmp_path, fanout, batches):
    rows = _rows(1, range(80))
    root = f"{tmp_path}/runs"
    keys, before = linededup.frequent_lines(_docs(spark, rows), min_docs=10, batches=batches, fanout=fanout, store=root)
    assert before == 0
    want = {k for k, n in _counts(rows).items() if n >= 10}
    hashes = {(r["h1"], r["h2"]): r["key"] for r in spark.createDataFrame([(k,) for k in _counts(rows)], "key string").select("key", *linededup._hashes(F.col("key"))).collect()}
    assert {hashes[(r["h1"], r["h2"])] for r in keys.collect()} == want
    runs = linededup.LineRuns(spark, 10, fanout, root)
    assert all(sum(r[0] == level for r in runs.runs) < fanout for level in range(4)) and runs.next_batch == batches
    for run in runs.runs:  # sorted inside its files
        for part in runs._read(run).rdd.glom().collect():
            assert [(r["h1"], r["h2"]) for r in part] == sorted((r["h1"], r["h2"]) for r in part)


def test_store_takes_a_later_batch(spark, tmp_path):
    first, second = _rows(2, range(30)), _rows(3, range(100, 130))
    root = f"{tmp_path}/runs"
    linededup.dedup_lines(_docs(spark, first), store=root).count()
    got = {r["doc_id"]: r["kept_text"] for r in linededup.dedup_lines(_docs(spark, second), store=root).collect()}
    seen = _counts(first + second)
    assert got == {i: "\n".join(x for x in t.split("\n") if seen[x] < 10) for i, t in second}
    assert any(n >= 10 > _counts(second)[k] for k, n in seen.items())


def test_a_merge_that_was_not_cleaned_up(spark, tmp_path):
    root = f"{tmp_path}/runs"
    rows = _rows(4, range(40))
    linededup.frequent_lines(_docs(spark, rows), batches=2, fanout=5, store=root)
    runs = linededup.LineRuns(spark, 10, 5, root)
    runs._write(runs._merged(runs.runs), (1, 0, 1))  # and the two runs below are still there
    assert linededup.LineRuns(spark, 10, 5, root).runs == [(1, 0, 1)]


def test_empty_and_clashing(spark):
    empty = _docs(spark, [])
    assert linededup.dedup_lines(empty).count() == 0
    rows = spark.createDataFrame([(1, "a\nb", "x", 7), (None, None, "y", 8)], "doc_id long, text string, kept_text string, n_lines int")
    got = linededup.dedup_lines(rows, names=("_k", "_n", "_d"))
    assert got.columns == ["doc_id", "text", "kept_text", "n_lines", "_k", "_n", "_d"]
    assert sorted((r["kept_text"], r["n_lines"], r["_k"], r["_n"], r["_d"]) for r in got.collect()) == [("x", 7, "a\nb", 2, 0), ("y", 8, "", 1, 0)]
