"""Toxicity scoring behind a noisy-channel deobfuscator.

Writers hide words by look-alike characters, by spacing letters out and by repeating them.
Compatibility forms and letters of other alphabets that look like Latin ones are folded.  Each
suspicious word becomes a lattice: a position offers the letters that its character may stand for, a
repeated letter may be one letter, a separator may be nothing.  Viterbi decoding under a character
trigram model of the corpus picks the likeliest reading.  The restored words and their beginnings
are the features of a logistic model of the labels.
"""

from __future__ import annotations

import math
import re
import unicodedata
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellgraph.scratch import Scratch
from cellgraph.workers import release_memory, worker_state

#: Letters that a character may stand for, besides itself.
LOOKALIKES = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "gb", "7": "t", "8": "b", "9": "g",
    "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "(": "c", "<": "c", "€": "e", "£": "l", "¡": "i", "*": "",
}
#: Cyrillic and Greek letters that look like Latin ones, and those.
HOMOGLYPHS = str.maketrans("асеіјорѕухԁһӏкмтвнαειοκνρτυχ", "aceijopsyxdhlkmtbnaeioknptux")
_FOREIGN = re.compile(f"[{''.join(map(chr, HOMOGLYPHS))}]").search
SEPARATORS = ".-_*·~'"
N_SYMBOLS = 64  # the trigram model's alphabet: boundary, a-z, other letters folded into the rest
_PLAIN = re.compile(r"[^\W\d_]+\Z").match
_TRIPLE = re.compile(r"(.)\1\1").search
_DOUBLE = re.compile(r"(.)\1")
_SPACED = re.compile(r"(?<!\S)(?:[^\W_]|[@$!|+(]|[0-9])(?:[ .\-_*·~]{1,2}(?:[^\W_]|[@$!|+(])){2,}(?!\S)")
_EDGE = re.compile(r"^[^\w@$!|+(<€£¡]+|(?:[^\w@$+€]+|([@$+€])\1{2,})+\Z")
_TOKEN = re.compile(r"\S+")
_WORDS = re.compile(r"[^\W\d_]+")
_GAP = re.compile(r"[ .\-_*·~]")
_WIDE_GAP = re.compile(r"[ .\-_*·~]{2}")
_BREAK = re.compile(r"(?:[^\w@$!|+(<€£¡]|_)+")
_BREAK_AT = {c: re.compile(re.escape(c) + "+") for c in SEPARATORS}


def symbol(ch: str) -> int:
    """Index of a letter: 1-26 for a-z, 27-63 for others; 0 stands for a word's edge."""
    o = ord(ch) - 97
    return o + 1 if 0 <= o < 26 else 27 + ord(ch) % (N_SYMBOLS - 27)


def trigram_counts(texts: Iterable[str], block: int = 1 << 17) -> np.ndarray:
    """Trigram counts of the words of the texts, two edges before and one after each; ``block`` characters at a time."""
    flat = np.zeros(N_SYMBOLS**3, dtype=np.int64)
    for text in texts:
        lowered = f"  {text.lower()} "
        for at in range(0, len(lowered) - 2, block):
            cps = np.frombuffer(lowered[at : at + block + 2].encode("utf-32-le"), dtype=np.uint32)
            ascii_letter = (cps >= 97) & (cps <= 122)
            letter = ascii_letter | ((cps >= 0xC0) & (cps != 0xD7) & (cps != 0xF7) & ((cps < 0x2000) | (cps > 0x206F)))
            sym = np.where(ascii_letter, cps.astype(np.int64) - 96, np.where(letter, 27 + cps % (N_SYMBOLS - 27), 0)).astype(np.int64)
            code = (sym[:-2] * N_SYMBOLS + sym[1:-1]) * N_SYMBOLS + sym[2:]
            code = code[(sym[1:-1] != 0) | (sym[2:] != 0)]
            if len(code) > 50_000:
                flat += np.bincount(code, minlength=len(flat))
            else:
                np.add.at(flat, code, 1)
    return flat


class CharModel:
    """Log probabilities of a letter after two letters, interpolated with lower orders."""

    def __init__(self, counts: np.ndarray):
        tri = counts.reshape((N_SYMBOLS,) * 3).astype(float)
        bi = tri.sum(axis=0)
        uni = bi.sum(axis=0) + 0.5
        p1 = uni / uni.sum()
        p2 = (bi + 5 * p1) / (bi.sum(axis=1, keepdims=True) + 5)
        p3 = (tri + 5 * p2[None]) / (tri.sum(axis=2, keepdims=True) + 5)
        self.log = np.log(p3).tolist()

    def score(self, word: str) -> float:
        a = b = 0
        total = 0.0
        for ch in word:
            c = symbol(ch)
            total += self.log[a][b][c]
            a, b = b, c
        return total + self.log[a][b][0]


def lattice(token: str) -> list[list[tuple[str, float]]]:
    """Per run of equal characters the readings ('' for nothing) with their channel log probability."""
    out, i = [], 0
    while i < len(token):
        ch, n = token[i], 1
        while i + n < len(token) and token[i + n] == ch:
            n += 1
        i += n
        readings: dict[str, float] = {}
        letters = ([ch] if ch.isalpha() else []) + list(LOOKALIKES.get(ch, ""))
        for c in letters:
            swap = 0.0 if c == ch else -1.0
            readings[c] = swap - (0.0 if n == 1 else 1.5 * (n == 2) + 0.2 * (n > 2))
            if n >= 2:
                readings[c + c] = swap - (0.0 if n == 2 else 1.2)
        if not ch.isalpha():
            lone = -0.5 if ch in SEPARATORS else -2.5
            readings[""] = max(readings.get("", -math.inf), lone if letters else -0.5)
        out.append(list(readings.items()))
    return out


def decode(token: str, model: CharModel, breaks: bool = False) -> str:
    """The likeliest reading of a lower-cased token of any length; with ``breaks`` in words, with a space between them."""
    best: dict[tuple[int, int], tuple[float, tuple | None]] = {(0, 0): (0.0, None)}
    log = model.log
    for column in lattice(token):
        if breaks:
            total, read, a, b = max(((t + log[a][b][0], r, a, b) for (a, b), (t, r) in best.items() if b), default=(-math.inf, None, 0, 0), key=lambda x: x[0])
            if b and ((old := best.get((0, 0))) is None or total > old[0]):
                best[(0, 0)] = (total, (read, " "))
        reached: dict[tuple[int, int], tuple[float, tuple | None]] = {}
        for (a, b), (total, read) in best.items():
            for letters, cost in column:
                x, y, value = a, b, total + cost
                for ch in letters:
                    c = symbol(ch)
                    value += log[x][y][c] + 2.0  # the bonus offsets what every further letter costs, so that nothing is not favoured
                    x, y = y, c
                if (old := reached.get((x, y))) is None or value > old[0]:
                    reached[(x, y)] = (value, (read, letters) if letters else read)
        best = reached
    read = max(((total + (log[a][b][0] if b or not breaks else 0.0), read) for (a, b), (total, read) in best.items()), key=lambda x: x[0])[1]
    out = []
    while read is not None:  # readings are kept as links to what comes before
        read, letters = read
        out.append(letters)
    return "".join(reversed(out)).strip()


def features(word: str) -> list[str]:
    """The word itself, and its beginnings of 4 to 6 letters if it goes on (marked by ^)."""
    return [word, *("^" + word[:k] for k in (4, 5, 6) if len(word) > k)]


class Restorer:
    """Texts to restored words and their features; remembers what up to ``memory`` tokens gave.

    With ``wanted``, only those features are given.  Tokens of any length are decoded, as a whole and
    in the parts between their separators.
    """

    def __init__(self, model: CharModel, wanted: frozenset[str] | None = None, memory: int = 120_000):
        self.model, self.wanted, self.memory, self.known = model, wanted, memory, {}
        self.heads = frozenset(f.lstrip("^")[:3] for f in wanted or ())
        self.single = frozenset(_DOUBLE.sub(r"\1", f) for f in wanted or ())

    def _doubled(self, word: str) -> bool:
        """Whether a plain word with doubled letters could be a wanted one with single letters; only then its lattice is decoded."""
        if self.wanted is None or not _DOUBLE.search(word):
            return False
        thin = _DOUBLE.sub(r"\1", word)
        return thin in self.single or any("^" + thin[:k] in self.single for k in (3, 4, 5, 6) if len(thin) > k)

    def token_words(self, token: str) -> tuple[str, ...]:
        if token.isalpha() and not _DOUBLE.search(token):  # has no edges, no run and nothing to decode
            return (token,)
        core = _EDGE.sub("", token)
        if not core:
            return ()
        if _PLAIN(core) and not _TRIPLE(core):
            if self._doubled(core) and (read := decode(core, self.model)) != core:
                return (core, read)
            return (core,)
        pieces = tuple(w for w in _WORDS.findall(core) if len(w) > 1)
        if not any(c.isalpha() for c in core):
            return pieces
        more = dict.fromkeys(decode(part, self.model) for part in (core, *self._parts(core)))
        return (*(w for w in more if w and w not in pieces), *pieces)

    def _parts(self, core: str) -> set[str]:
        """What stands between separators and is no plain word; single characters in a row are one part, its separators left out."""
        found = set()
        for cut in (_BREAK, *(_BREAK_AT[c] for c in SEPARATORS if c in core)):
            row = ""
            for part in (*cut.split(core), ""):
                if len(part) == 1:
                    row += part
                    continue
                if len(row) > 2:
                    found.add(row)
                row = ""
                part = _EDGE.sub("", part)
                if part != core and len(part) > 1 and not (_PLAIN(part) and not _TRIPLE(part)) and any(c.isalpha() for c in part):
                    found.add(part)
        return found

    def _folded(self, token: str) -> tuple[str, ...]:
        """The words of the token with look-alikes of other alphabets folded, if it has any."""
        if token.isascii() or not _FOREIGN(token):
            return ()
        latin = token.translate(HOMOGLYPHS)
        mixed = any("a" <= c <= "z" for c in token)
        return self.token_words(latin) if mixed or latin.isascii() else ()

    def _features(self, words: Iterable[str]) -> tuple[str, ...]:
        if self.wanted is None:
            return tuple(f for w in words for f in features(w))
        return tuple(f for w in words if w[:3] in self.heads for f in features(w) if f in self.wanted)

    def features_of(self, text: str | None) -> set[str]:
        """Features of the distinct words of the whole text, lower-cased, in compatibility form."""
        if not text:
            return set()
        if not text.isascii():
            text = unicodedata.normalize("NFKC", text)
        text = text.lower()
        foreign = not text.isascii() and _FOREIGN(text) is not None
        known, out = self.known, set()
        heads, doubled = self.heads if self.wanted is not None else None, _DOUBLE.search
        for token in set(text.split()):
            found = known.get(token)
            if found is None:
                if heads is not None and token[:3] not in heads and token.isalpha() and not (doubled(token) or foreign and _FOREIGN(token)):
                    continue  # a plain word that begins like no wanted feature
                words = self.token_words(token)
                found = self._features((*words, *self._folded(token)) if foreign else words)
                if len(known) >= self.memory:
                    known.clear()
                known[token] = found
            if found:
                out.update(found)
        for m in _SPACED.finditer(text.translate(HOMOGLYPHS) if foreign else text):
            joined = _GAP.sub("", m[0])
            out.update(self._features([decode(joined, self.model), *decode(joined, self.model, breaks=True).split()]))
            if len(words := _WIDE_GAP.split(m[0])) > 1:
                out.update(self._features(decode(_GAP.sub("", w), self.model) for w in words))
        out.discard("")
        return out


class ToxicModel:
    """Sparse logistic model; a text without any known feature gets the bias alone."""

    def __init__(self, weights: dict[str, float], bias: float):
        self.weights, self.bias = weights, bias

    def score(self, found: set[str]) -> float:
        z = self.bias + sum(map(self.weights.__getitem__, found & self.weights.keys()))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def fit_logistic(rows: list[np.ndarray], y: np.ndarray, n: int, l2: float = 0.3, steps: int = 200) -> tuple[np.ndarray, float]:
    """Batch gradient ascent with momentum on binary sparse rows; the penalty is on the weights only."""
    w, b = np.zeros(n), math.log((y.sum() + 0.5) / (len(y) - y.sum() + 0.5))
    at = np.repeat(np.arange(len(rows)), [len(r) for r in rows]).astype(np.int64)
    col = np.concatenate([*rows, np.zeros(0, np.int32)]).astype(np.int64)
    seen = np.bincount(col, minlength=n) + l2
    mw, mb = np.zeros(n), 0.0
    for _ in range(steps):
        z = b + np.bincount(at, weights=w[col], minlength=len(rows))
        gap = y - 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        grad = np.bincount(col, weights=gap[at], minlength=n) - l2 * w
        mw = 0.9 * mw + grad / seen
        mb = 0.9 * mb + gap.mean()
        w, b = w + 0.4 * mw, b + 0.2 * mb
    return w, float(b)


def corpus_char_model(docs: DataFrame, text_col: str = "text") -> CharModel:
    """Trigram counts of all texts, summed on the executors; the driver gets one row per trigram of a fixed alphabet.

    Null and empty texts add nothing, and no texts at all give the uniform model; repeated rows count as often as they come.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(N_SYMBOLS**3, dtype=np.int64)
        for b in batches:
            part: list[str] = []
            size = 0
            for t in b.column(0):
                text = t.as_py()
                if text:
                    part.append(text)
                    size += len(text)
                if size > 200_000:
                    total += trigram_counts([" ".join(part)])
                    part, size = [], 0
            if part:
                total += trigram_counts([" ".join(part)])
        code = np.nonzero(total)[0]
        release_memory()
        yield pa.RecordBatch.from_arrays([pa.array(code), pa.array(total[code])], names=["code", "n"])

    counts = np.zeros(N_SYMBOLS**3, dtype=np.int64)
    for r in docs.select(text_col).mapInArrow(run, "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).collect():
        counts[r["code"]] = r["n"]
    return CharModel(counts)


def _slices(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


def fit_toxicity(docs: DataFrame, labels: DataFrame, may_learn, char_model: CharModel, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", min_docs: int = 3, min_gain: float = 7, min_lift: float = 1.5, max_features: int = 20_000, sample: int = 20_000, broadcast_labels: int = 2_000_000, seed: int = 9) -> ToxicModel:
    """Chooses features by their association with the label over all learnable rows, then fits weights.

    Feature counts are taken over every learnable labelled row, on the executors.  Features that are
    ``min_lift`` times as frequent among toxic rows as the label itself go on, at most ``max_features`` of highest
    log-likelihood ratio (at least ``min_gain``; the bound keeps the model that every task gets below some MB); their weights are fitted on the driver from the
    feature numbers of about ``sample`` rows, chosen by id hash.  Of several labels of an id the highest
    counts; rows without a label or id teach nothing; without toxic rows every score is near 0.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "toxicity")
    id_type = docs.schema[id_col].dataType.simpleString()
    marks = scratch.save(labels.where(F.col(label_col).isNotNull()).groupBy(F.col(id_col).alias("_label_id")).agg(F.max(label_col).cast("int").alias("_label")))
    marked = F.broadcast(marks) if marks.count() <= broadcast_labels else marks
    rows = docs.where(may_learn).select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(marked, F.col("id") == F.col("_label_id")).select("id", "text", "_label")
    key = uuid.uuid4().hex

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer = worker_state("restorer", key, lambda: Restorer(char_model, memory=60_000))
        for b in _slices(batches, 500):
            found = [list(restorer.features_of(t.as_py())) for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(found, pa.list_(pa.string()))], names=["id", "y", "found"])
        release_memory()

    seen = scratch.save(rows.mapInArrow(run, f"id {id_type}, y int, found array<string>"))
    totals = {r["y"]: r["n"] for r in seen.groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect()}
    n_pos, n_all = totals.get(1, 0), sum(totals.values())
    if not n_pos or n_pos == n_all:
        return ToxicModel({}, -30.0 if not n_pos else 30.0)
    rate = n_pos / n_all
    each = seen.select("y", F.explode("found").alias("f")).groupBy("f").agg(F.sum("y").cast("double").alias("p"), F.count(F.lit(1)).cast("double").alias("n"))
    part = lambda k, of, q: F.when(k > 0, k * F.log(k / (of * F.lit(q)))).otherwise(0.0)
    gain = 2 * (part(F.col("p"), F.col("n"), rate) + part(F.col("n") - F.col("p"), F.col("n"), 1 - rate))
    best = each.where((F.col("n") >= min_docs) & (F.col("p") >= F.col("n") * min(1.0, min_lift * rate))).withColumn("gain", gain)
    names = [r["f"] for r in best.where(F.col("gain") >= min_gain).orderBy(F.desc("gain"), "f").limit(max_features).select("f").collect()]
    index = {f: i for i, f in enumerate(names)}
    chosen = seen.where(F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(n_all)) < sample) if n_all > sample else seen

    def numbered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _slices(batches, 500):
            own = [np.array(sorted(index[f] for f in x if f in index), dtype=np.int32).tobytes() for x in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(own, pa.binary())], names=["id", "y", "found"])

    fitted = sorted(chosen.mapInArrow(numbered, f"id {id_type}, y int, found binary").collect(), key=lambda r: (r["id"], r["y"], r["found"]))
    sparse = [np.frombuffer(r["found"], dtype=np.int32) for r in fitted]
    w, bias = fit_logistic(sparse, np.array([r["y"] for r in fitted], dtype=float), len(index))
    scratch.drop(seen, marks)
    return ToxicModel({f: float(w[i]) for f, i in index.items() if abs(w[i]) > 1e-3}, bias)


def score_documents(docs: DataFrame, char_model: CharModel, model: ToxicModel, text_col: str = "text", out_col: str = "score", keep_text: bool = True) -> DataFrame:
    """``docs`` with a score from 0 to 1 of every whole text (last column): one pass, no shuffle.

    Null and empty texts, and texts of no known feature, get the score of the bias.
    """
    columns = [c for c in docs.columns if c != out_col]
    schema = docs.select(*(c for c in columns if keep_text or c != text_col)).schema.add(out_col, "double")
    names, at, key = schema.fieldNames(), columns.index(text_col), uuid.uuid4().hex

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer = worker_state("restorer", key, lambda: Restorer(char_model, frozenset(model.weights)))
        for b in _slices(batches, 1000):
            scores = pa.array([model.score(restorer.features_of(x.as_py())) for x in b.column(at)], pa.float64())
            kept = [c for i, c in enumerate(b.columns) if keep_text or i != at]
            yield pa.RecordBatch.from_arrays([*kept, scores], names=names)
        release_memory()

    return docs.select(*columns).mapInArrow(run, schema)


def train(docs: DataFrame, labels: DataFrame) -> tuple[CharModel, ToxicModel]:
    """The models of the query and of the pipeline: labels of rows whose crc32 remainder by 5 is 0 are never seen."""
    may_learn = F.crc32(F.col("doc_id").cast("string")) % 5 != 0
    chars = corpus_char_model(docs)
    return chars, fit_toxicity(docs, labels, may_learn, chars)


def toxicity_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    chars, model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = score_documents(docs, chars, model, keep_text=False)
    return scored.select("doc_id", F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def reject_toxic(docs: DataFrame, chars: CharModel, model: ToxicModel, threshold: float = 0.5) -> DataFrame:
    """``docs`` without the rows that score ``threshold`` or more; columns unchanged.

    Null and empty texts score the bias and stay as a rule; repeated rows share their fate; an empty table stays
    empty; a column named ``_toxicity`` is not expected.
    """
    return score_documents(docs, chars, model, out_col="_toxicity").where(F.col("_toxicity") < threshold).drop("_toxicity")
