"""Token counts by heap-and-linked-list byte-pair merging.

A text is cut into the tokenizer's pre-tokens.  In each, the adjacent pair of lowest merge rank
(leftmost on ties) is popped from a heap and merged in a linked list until no pair has a rank; the
count is the initial symbols less the merges.  No token sequence is built.
"""

from __future__ import annotations

import heapq
import json
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellgraph.workers import worker_state

#: Fixed value: the pre-token pattern of byte-level BPE vocabularies of this family.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Code points on which character tables of different Unicode versions agree; texts with others are
#: cut by the tokenizer library's own pre-tokenizer.
SETTLED = r"[^\u0000-՗֐-ࢎऀ-౛ೠ-⁰₠-ꟍ가-￿]"


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in such vocabularies: printable Latin-1 bytes for
    themselves, all others from U+0100 on in order."""
    own = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b) if b in own else chr(next(spare)) for b in range(256)]


class MergeTable:
    """Merge ranks of a byte-level BPE tokenizer file, by pairs of integer symbols."""

    def __init__(self, tokenizer_json: str):
        spec = json.loads(tokenizer_json)
        symbols = {letter: i for i, letter in enumerate(byte_letters())}
        self.rank: dict[tuple[int, int], tuple[int, int]] = {}
        for r, pair in enumerate(spec["model"]["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            new = symbols.setdefault(a + b, len(symbols))
            self.rank[(symbols[a], symbols[b])] = (r, new)
        self.special = [t["content"] for t in spec.get("added_tokens", [])]

    def count(self, piece: bytes) -> int:
        """Tokens of one pre-token."""
        n = len(piece)
        if n < 2:
            return n
        rank = self.rank
        symbol = list(piece)
        heap = [(*found, i) for i in range(n - 1) if (found := rank.get((symbol[i], symbol[i + 1])))]
        if not heap:
            return n
        heap = [(r, i, new) for r, new, i in heap]
        heapq.heapify(heap)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        merges = 0
        while heap:
            r, i, new = heapq.heappop(heap)
            if symbol[i] < 0 or (j := after[i]) >= n:
                continue
            found = rank.get((symbol[i], symbol[j]))
            if found is None or found[0] != r:
                continue  # the pair that stood here has been merged into another
            symbol[i], symbol[j] = new, -1
            merges += 1
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if found := rank.get((new, symbol[k])):
                    heapq.heappush(heap, (found[0], i, found[1]))
            if (h := before[i]) >= 0 and (found := rank.get((symbol[h], new))):
                heapq.heappush(heap, (found[0], h, found[1]))
        return n - merges


class TokenCounter:
    """Counts the tokens of whole texts; remembers the counts of up to ``memory`` pre-tokens."""

    def __init__(self, tokenizer_json: str, memory: int = 400_000):
        import regex

        self.table = MergeTable(tokenizer_json)
        self.json, self.memory, self.known = tokenizer_json, memory, {}
        self.cut = regex.compile(PATTERN).findall
        self.odd = regex.compile(SETTLED).search
        self.special = regex.compile("|".join(map(regex.escape, self.table.special))) if self.table.special else None
        self._library = None

    def _library_pieces(self, text: str) -> list[str]:
        if self._library is None:
            from tokenizers import Tokenizer

            self._library = Tokenizer.from_str(self.json)
        return [text[a:b] for _, (a, b) in self._library.pre_tokenizer.pre_tokenize_str(text)]

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        total, parts = 0, [text]
        if self.special and (hits := len(self.special.findall(text))):
            total, parts = hits, self.special.split(text)
        known = self.known
        for part in parts:
            pieces = self._library_pieces(part) if self.odd(part) else self.cut(part)
            for piece, times in Counter(pieces).items():
                n = known.get(piece)
                if n is None:
                    n = self.table.count(piece.encode())
                    if len(piece) < 64:
                        if len(known) >= self.memory:
                            known.clear()
                        known[piece] = n
                total += n * times
        return total


def token_counts(docs: DataFrame, tokenizer_json: str, id_col: str = "doc_id", text_col: str = "text", limit: int = 1024) -> DataFrame:
    """``(id, n_bytes, n_tokens, over_limit)`` for every row: one pass, no shuffle.

    Null and empty texts have 0 bytes and 0 tokens.  Strings of special tokens inside a text count as one
    token each, as the library does by default.  Repeated rows get equal answers, ids may be null.
    """
    key = str(hash(tokenizer_json))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = worker_state("token-counter", key, lambda: TokenCounter(tokenizer_json))
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns[:2], pa.array([counter.count(t.as_py()) for t in b.column(2)], pa.int64())], names=["id", "n_bytes", "n_tokens"])

    sized = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.octet_length(text_col), F.lit(0)).cast("long").alias("n_bytes"), text_col)
    return sized.mapInArrow(run, "id long, n_bytes long, n_tokens long").select(F.col("id").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))


def read_tokenizer(path: str | None = None) -> str:
    """The tokenizer file as text, read on the driver; executors get it with the task."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("byte_bpe_50k.json")
    with open(path, encoding="utf-8") as f:
        return f.read()


def token_count_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(spark.read.parquet(f"{sf_dir}/documents.parquet"), read_tokenizer())
