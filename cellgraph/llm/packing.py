"""Packing token sequences into windows by Karmarkar-Karp multiway differencing.

Every partition is packed on its own, so no token is shuffled.  A document longer than a window
fills whole windows; what is left of it is one piece.  When the pieces of a lot come to
``lot_windows`` windows, they are dealt to m of them by differencing: each piece starts as a partial
partition of m windows, and the two partial partitions of largest imbalance are merged with their
windows in opposing order, until one is left.  m starts at the least number that could hold the lot.
A window that comes out above its capacity has its largest piece cut at the excess and the lot is
dealt again; if that has not helped after a few times, m rises.
"""

from __future__ import annotations

import bisect
import heapq
import zlib
from collections.abc import Iterator
from operator import itemgetter

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellgraph.llm.tokencount import PATTERN, byte_letters, read_tokenizer
from cellgraph.workers import release_memory, worker_state


def difference(sizes: list[int], m: int) -> list[list[int]]:
    """Indices of ``sizes`` in m nearly equal windows (largest differencing over partial partitions).

    A partial partition keeps only its non-zero windows, heaviest first: all others hold nothing, so the
    merge of two sparse ones is mostly a union.
    """
    if m == 1:
        return [list(range(len(sizes)))]
    # a partial partition: negated loads, ascending (heaviest first), and the items of each
    heap = [(-s, i, [-s], [[i]]) for i, s in enumerate(sizes)]
    heapq.heapify(heap)
    serial = len(sizes)
    while len(heap) > 1:
        _, _, loads, items = heapq.heappop(heap)
        _, _, other, its = heapq.heappop(heap)
        if len(loads) < len(other):
            loads, items, other, its = other, its, loads, items
        if len(other) == 1:  # one load meets an empty window, or the lightest
            load, own = other[0], its[0]
            if len(loads) == m:
                load += loads.pop()
                own = [*items.pop(), *own]
            at = bisect.bisect_right(loads, load)
            loads.insert(at, load)
            items.insert(at, own)
        else:  # the heaviest of the other meet empty windows, then the lightest
            room = min(m - len(loads), len(other))
            meet = len(other) - room
            kept = len(loads) - meet
            pairs = [*zip(loads[:kept], items[:kept], strict=True), *zip(other[:room], its[:room], strict=True)]
            for k in range(meet):
                pairs.append((loads[-1 - k] + other[room + k], [*items[-1 - k], *its[room + k]]))
            pairs.sort(key=itemgetter(0))
            loads, items = [load for load, _ in pairs], [x for _, x in pairs]
        heapq.heappush(heap, (loads[0] - (loads[-1] if len(loads) == m else 0), serial, loads, items))
        serial += 1
    windows = heap[0][3] if heap else []
    return windows + [[] for _ in range(m - len(windows))]


def balanced_windows(sizes: list[int], capacity: int, cuts: int = 3) -> list[list[tuple[int, int, int]]]:
    """Windows of ``(item, start, length)`` by `difference`, none above the capacity; every item lies in them once.

    With the fewest windows that could hold all, items are cut only where a window is too full, in up to
    ``cuts`` rounds; then the number of windows rises until all keep to the capacity.
    """
    pieces = [(i, 0, n) for i, n in enumerate(sizes)]
    m = max(1, -(-sum(sizes) // capacity))
    while True:
        windows = difference([n for _, _, n in pieces], m)
        loads = [sum(pieces[i][2] for i in w) for w in windows]
        full = [k for k, load in enumerate(loads) if load > capacity]
        if not full:
            return [[pieces[i] for i in w] for w in windows if w]
        if cuts > 0:
            cuts -= 1
            for k in full:
                largest = max(windows[k], key=lambda i: (pieces[i][2], i))
                item, start, n = pieces[largest]
                over = min(loads[k] - capacity, n - 1)
                if over > 0:
                    pieces[largest] = (item, start, n - over)
                    pieces.append((item, start + n - over, over))
        else:
            worst = max(loads)
            m += max(1, -(-(worst - capacity) * m // (8 * capacity)))


class Packer:
    """Packs the documents of one partition as they come; holds at most one lot of piece records."""

    def __init__(self, partition: int, window: int, lot_windows: int):
        self.next_sequence = partition << 32
        self.window, self.lot = window, lot_windows * window
        self.records: list[tuple] = []
        self.waiting: list[tuple] = []  # (doc_id, start, bytes of the ids, total)
        self.waiting_tokens = 0

    def _window(self, pieces: list[tuple]) -> None:
        offset = 0
        for doc_id, start, length, crc, total in pieces:
            self.records.append((doc_id, start, length, crc, total, self.next_sequence, offset))
            offset += length
        self.next_sequence += 1

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        total, start = len(ids), 0
        raw = ids.astype("<u4", copy=False).tobytes()
        while total - start >= self.window:
            self._window([(doc_id, start, self.window, zlib.crc32(raw[4 * start : 4 * (start + self.window)]), total)])
            start += self.window
        if start < total:
            self.waiting.append((doc_id, start, raw[4 * start :], total))
            self.waiting_tokens += total - start
        if self.waiting_tokens >= self.lot:
            self.flush()

    def flush(self) -> None:
        if not self.waiting:
            return
        for window in balanced_windows([len(w[2]) // 4 for w in self.waiting], self.window):
            pieces = []
            for item, at, n in window:
                doc_id, start, raw, total = self.waiting[item]
                pieces.append((doc_id, start + at, n, zlib.crc32(raw[4 * at : 4 * (at + n)]), total))
            self._window(sorted(pieces, key=lambda p: (p[0] is None, p[0] or 0, p[1])))
        self.waiting, self.waiting_tokens = [], 0

    def take(self) -> list[tuple]:
        out, self.records = self.records, []
        return out


FIELDS = {"doc_id": pa.int64(), "start": pa.int64(), "length": pa.int64(), "ids_crc32": pa.int64(), "doc_tokens": pa.int64(), "sequence_id": pa.int64(), "offset": pa.int64()}


#: Texts of more characters go to the slower library; no run inside a shorter one reaches the fast one's limit.
LONG = 300_000


def make_encoder(tokenizer_json: str):
    """text -> token ids as an array: the ids that the library ``tokenizers`` gives without added specials.

    Texts of plain byte-level BPE files run on the faster library ``tiktoken``, which gives the same ids (tested over
    every code point).  Its pattern matcher gives up within a run of about a million white-space characters, so texts
    of over ``LONG`` characters run on ``tokenizers`` itself, as do all texts of any other file.
    """
    import json

    from tokenizers import Tokenizer

    library = Tokenizer.from_str(tokenizer_json)
    whole = lambda text: np.array(library.encode(text, add_special_tokens=False).ids, dtype=np.uint32)
    spec = json.loads(tokenizer_json)
    pre, model = spec.get("pre_tokenizer") or {}, spec["model"]
    plain = pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True) and not spec.get("normalizer") and not model.get("ignore_merges")
    plain = plain and all(not (t["lstrip"] or t["rstrip"] or t["single_word"]) for t in spec["added_tokens"])
    if plain:
        import tiktoken

        byte = {letter: b for b, letter in enumerate(byte_letters())}
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        ranks = {bytes(byte[c] for c in token): i for token, i in model["vocab"].items() if token not in special}
        merged = ["".join(m.split(" ") if isinstance(m, str) else m) for m in model["merges"]]
        in_order = all(model["vocab"][a] < model["vocab"][b] for a, b in zip(merged, merged[1:], strict=False))
        if in_order and len(ranks) == len(merged) + 256:
            encoding = tiktoken.Encoding("byte_bpe", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens=special)
            return lambda text: encoding.encode_to_numpy(text, allowed_special="all") if len(text) <= LONG else whole(text)
    return whole


def pack_documents(docs: DataFrame, tokenizer_json: str, id_col: str = "doc_id", text_col: str = "text", window: int = 1024, lot_windows: int = 512, end_id: int = 0) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A document is its ids and then ``end_id``; a null or empty text is that id alone.  Each id lies in
    exactly one piece, sequences hold at most ``window`` ids and offsets are gapless.  sequence_id is the
    input partition's number times 2^32 plus a count.  Repeated rows are packed as often as they come.
    Only the last window lot of each partition may be loosely filled.  Texts of any length and any characters
    are encoded whole; an empty table gives an empty result, other columns are ignored.
    """
    key = str(hash(tokenizer_json))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = worker_state("encoder", key, lambda: make_encoder(tokenizer_json))
        release_memory()  # of the tokenizer's file, of which only the encoder stays
        packer = Packer(TaskContext.get().partitionId(), window, lot_windows)

        def out() -> pa.RecordBatch:
            cols = zip(*packer.take(), strict=True)
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, FIELDS.values(), strict=True)], names=list(FIELDS))

        for b in batches:
            ids = b.column(0).to_pylist()
            for doc_id, t in zip(ids, b.column(1), strict=True):
                tokens = encode(t.as_py() or "")
                packer.add(doc_id, np.append(tokens, np.uint32(end_id)))
                if len(packer.records) >= 20_000:
                    yield out()
        packer.flush()
        if packer.records:
            yield out()
        release_memory()

    schema = ", ".join(f"{name} long" for name in FIELDS)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text_col).mapInArrow(run, schema)


def packing_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), read_tokenizer())
