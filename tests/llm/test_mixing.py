"""Mixing against brute force: the same keys, sorted in one place."""

import collections

import pytest
from pyspark.sql import functions as F

from cellgraph.llm import mixing


def _brute(rows, targets):
    """taken by sorting each source's rows by (key, id, size) and filling the budget."""
    out = {}
    by = collections.defaultdict(list)
    for r in rows:
        by[r["source"]].append(r)
    for source, own in by.items():
        size = sum(r["size"] for r in own)
        epochs, rest = divmod(int(targets[source] + 0.5), size) if size else (0, 0)
        for r in sorted(own, key=lambda r: (r["mix_key"], r["id"], r["size"])):
            part = min(r["size"], rest)
            rest -= part
            out[r["id"]] = epochs * r["size"] + part
    return out


@pytest.mark.parametrize("cut_rows", [4096, 5, 1])
def test_against_sorting(spark, cut_rows):
    rows = [(i, ["a", "b", "c", None][(i * i) % 4 if i % 3 else 0], (i * 37) % 101) for i in range(3000)]
    df = spark.createDataFrame(rows, "doc_id long, source string, size long")
    got = mixing.mix(df, cut_rows=cut_rows).withColumnRenamed("doc_id", "id").collect()
    targets = {r["source"]: r["target"] for r in got}
    assert {r["id"]: r["taken"] for r in got} == _brute(got, targets)
    sizes = collections.Counter()
    for _, s, n in rows:
        sizes[s] += n
    assert targets == pytest.approx(mixing.plan_targets(list(sizes.items()), (5, 2, 1), 3))


@pytest.mark.parametrize("cut_rows", [4096, 1])
def test_ties_and_null_ids(spark, cut_rows):
    """Many rows of one id, many without: budgets are met to the word, whatever row they end in."""
    rows = [(None, "a", f"w {i % 50} x") for i in range(300)] + [(7, "a", "same words here")] * 100 + [(i, "b", "z " * 40) for i in range(20)] + [(500, None, None), (501, None, "")]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string")
    got = mixing.mix_documents(df, cut_rows=cut_rows).collect()
    taken, target = collections.Counter(), {}
    for r in got:
        taken[r["source"]] += r["taken"]
        target[r["source"]] = r["target"]
        assert 0 <= r["taken"] <= 3 * r["size"]
    assert len(got) == len(rows) and all(abs(taken[s] - t) <= 0.5 for s, t in target.items())
    again = mixing.mix_documents(df.orderBy(F.desc("text")), cut_rows=cut_rows).collect()
    key = lambda r: (r["doc_id"] or -1, r["source"] or "", r["size"], r["taken"])
    assert sorted(map(key, got)) == sorted(map(key, again))


def test_applied_mix(spark):
    rows = [(i, "ab"[i % 2], "w " * (i % 9), "kept") for i in range(400)] + [(None, None, None, "x"), (1000, "a", "", "y")]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string, size string")
    out = mixing.apply_mix(df)
    assert out.columns == df.columns
    copies = collections.Counter((r["doc_id"], r["size"]) for r in out.collect())
    want = collections.Counter()
    for r in mixing.mix_documents(df).collect():
        n = 1 if not r["size"] else int(r["taken"] / r["size"] + 0.5)
        if n:
            want[(r["doc_id"], {None: "x", 1000: "y"}.get(r["doc_id"], "kept"))] += n
    assert copies == want
    assert mixing.apply_mix(df.where("false")).count() == 0
