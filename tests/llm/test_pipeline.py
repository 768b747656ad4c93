"""All stages in order, on tables with awkward rows, and each stage against a plain version."""

import collections
import random

import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from cellgraph.llm import tokencount  # noqa: E402

TOXIC = "you pathetic idiot and utter moron go away"


def _table(spark, tmp_path, rows, labels):
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, n_lines string, kept_text int")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    return str(tmp_path)


def _rows():
    rng = random.Random(1)
    word = lambda: "".join(rng.choice("aeioustrnlmk") for _ in range(rng.randrange(3, 9)))
    text = lambda: "\n".join(" ".join(word() for _ in range(12)) for _ in range(4))
    rows = []
    for i in range(300):
        body = text()
        if i % 5 == 0:
            body = f"{body}\n{TOXIC}"
        if i % 3 == 0:
            body += "\nAll rights reserved by us"
        rows.append([i, body, "en", "abc"[i % 3], len(body), "n", i])
    rows += [[1000 + k, rows[1][1], "en", "a", rows[1][4], "n", 0] for k in range(5)]  # copies
    rows += [[2000, rows[2][1] + " tail", "en", "a", 1, "n", 0], [3000, None, None, None, None, None, None], [3001, "", "en", "b", 0, "n", 1]]
    rows += [[None, "without an id " + text(), "en", "c", 9, "n", 1], [4000, " " * 1_100_000 + "end", "en", "c", 9, "n", 1], [4001, "x" * 150_000, "en", "c", 9, "n", 1]]
    return [tuple(r) for r in rows]


def test_all_stages(spark, tmp_path):
    rows = _rows()
    labels = [(i, 1, int(i % 5 == 0)) for i in range(300)]
    sf = _table(spark, tmp_path, rows, labels)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r[0]: r[1] for r in rows}
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        docs = stage(spark, docs, sf)
        if name == "packing":
            break
        docs.write.parquet(f"{tmp_path}/{name}")
        docs = spark.read.parquet(f"{tmp_path}/{name}")
        assert docs.columns == before.columns
        kept = docs.collect()
        ids = [r["doc_id"] for r in kept]
        if name == "toxicity":
            assert not any(i is not None and i < 300 and i % 5 == 0 for i in ids)
            assert set(texts) - set(ids) <= {i for i in texts if i is not None and i < 300 and i % 5 == 0}
            assert {r["n_lines"] for r in kept} == {"n", None}
        if name == "line_dedup":
            line = "All rights reserved by us"
            assert sum(line in (r["text"] or "") for r in kept) == 1
            assert len(kept) == before.count() and all(r["n_chars"] == len(r["text"]) for r in kept if r["text"] and r["doc_id"] is not None and r["doc_id"] < 300)
            held = {r["doc_id"]: r["text"] for r in before.collect()}
            seen = collections.Counter(k for t in held.values() for k in {x.strip().lower() for x in (t or "").split("\n")} if k)
            for r in kept:
                own = (held[r["doc_id"]] or "").split("\n")
                assert [x for x in (r["text"] or "").split("\n") if seen[x.strip().lower()] < 10] == [x for x in own if seen[x.strip().lower()] < 10]
        if name == "near_duplicates":
            assert 1 in ids and not any(i is not None and 1000 <= i < 1010 for i in ids) and 2000 not in ids and None in ids
        if name == "mixing":
            before_ids = {r["doc_id"] for r in before.collect()}
            assert set(ids) <= before_ids and max(collections.Counter(ids).values()) <= 3
    library = Tokenizer.from_str(tokencount.read_tokenizer())
    want = sum(len(library.encode(r["text"] or "", add_special_tokens=False).ids) + 1 for r in before.collect())
    assert docs.agg(F.sum("length")).first()[0] == want


def test_empty_tables(spark, tmp_path):
    sf = _table(spark, tmp_path, [], [])
    assert corpus_pipeline.run(spark, sf).count() == 0


def test_stages_of_many_workers_begin_with_heap_given_back(spark):
    beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
    collected = lambda: sum(b.getCollectionCount() for b in beans if "Young" not in b.getName())
    docs = spark.createDataFrame([(1, "a b c d e f g"), (2, None)], "doc_id long, text string")
    for stage in (corpus_pipeline.near_duplicates, corpus_pipeline.packing):
        before = collected()
        assert stage(spark, docs, "").count() >= 2
        assert collected() > before
