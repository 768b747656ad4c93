"""Packing: ids of every text as the library gives them, windows that keep to the capacity."""

import collections
import random

import pytest
from tokenizers import Tokenizer

from cellgraph.llm import packing, tokencount


def _bpe():
    return tokencount.read_tokenizer()


@pytest.mark.parametrize("low, high, cuts", [(1, 129, 4), (1, 1023, 4), (600, 1023, 4), (600, 1023, 0), (1023, 1024, 4)])
def test_differencing_is_a_partition(low, high, cuts):
    rng = random.Random(2)
    sizes = [rng.randrange(low, high) for _ in range(700)]
    windows = packing.balanced_windows(sizes, 1024, cuts)
    covered = collections.defaultdict(list)
    for window in windows:
        assert sum(n for _, _, n in window) <= 1024
        for item, start, n in window:
            covered[item].append((start, n))
    for item, spans in covered.items():
        at = 0
        for start, n in sorted(spans):
            assert start == at and n > 0
            at += n
        assert at == sizes[item]
    assert len(covered) == 700
    if cuts:
        assert len(windows) <= -(-sum(sizes) // 1024) * 1.01 + 1


@pytest.mark.parametrize("unit, n", [(" ", 2_000_000), ("\n", 2_000_000), ("a", 2_000_000), ("  x", 250_000), (" ", packing.LONG)])
def test_ids_of_very_long_runs(unit, n):
    encode, library = packing.make_encoder(_bpe()), Tokenizer.from_str(_bpe())
    text = unit * n
    assert encode(text).tolist() == library.encode(text, add_special_tokens=False).ids


def test_ids_of_all_code_points():
    encode, library = packing.make_encoder(_bpe()), Tokenizer.from_str(_bpe())
    points = [c for c in range(0x110000) if not 0xD800 <= c < 0xE000]
    for at in range(0, len(points), 100_000):
        part = points[at : at + 100_000]
        for text in ("".join(map(chr, part)), "".join(f"{chr(c)}a 1" for c in part)):
            assert encode(text).tolist() == library.encode(text, add_special_tokens=False).ids, hex(part[0])


def test_long_rows_in_a_job(spark):
    rows = [(1, " " * 1_500_000), (2, "\n" * 1_200_000 + "end"), (3, None), (4, "x")]
    got = packing.pack_documents(spark.createDataFrame(rows, "doc_id long, text string"), _bpe()).collect()
    library = Tokenizer.from_str(_bpe())
    totals = {i: len(library.encode(t or "", add_special_tokens=False).ids) + 1 for i, t in rows}
    seen = collections.Counter()
    for r in got:
        seen[r["doc_id"]] += r["length"]
        assert r["doc_tokens"] == totals[r["doc_id"]]
    assert seen == totals


def test_padding_is_small(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").coalesce(2)
    rows = packing.pack_documents(docs, _bpe())
    got = rows.agg({"length": "sum", "*": "count"}).first()
    windows = rows.select("sequence_id").distinct().count()
    assert got["sum(length)"] / (windows * 1024) > 0.995
