"""Language identification with error-correcting output codes.

Each language has a codeword; for each bit a binary linear classifier on hashed byte n-grams learns
to tell the languages whose bit is 1 from the others.  A text's bit margins are decoded to the
codeword of least logistic loss; a text whose two best codewords cost nearly the same is flagged.
"""

from __future__ import annotations

import itertools
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DIM = 4096
_LETTER = re.compile(r"[^\W\d_]").search


def has_letter(text: str | None) -> bool:
    return bool(text) and _LETTER(text) is not None


def ngram_frequencies(text: str) -> np.ndarray:
    """Share of each hashed byte 1- to 3-gram of the whole text, A-Z lower-cased."""
    b = np.frombuffer(b" " + text.encode().lower() + b" ", dtype=np.uint8).astype(np.int64)
    one = (b * 31) % DIM
    two = (b[:-1] * 7919 + b[1:] * 104729 + 17) % DIM
    three = (b[:-2] * 15485863 + b[1:-1] * 32452843 + b[2:] * 49979687 + 29) % DIM
    counts = np.bincount(one, minlength=DIM) + np.bincount(two, minlength=DIM) + np.bincount(three, minlength=DIM)
    return np.sqrt(counts / max(1, len(one) + len(two) + len(three)))


def codewords(n: int, seed: int = 5) -> np.ndarray:
    """(n, bits) of +1 and -1: the exhaustive code up to 5 classes, else the best of many random ones by least distance."""
    if n <= 1:
        return np.ones((n, 1))
    if n <= 5:
        columns = [(1, *rest) for rest in itertools.product((1, -1), repeat=n - 1) if -1 in rest]
        return np.array(columns, dtype=float).T
    bits = int(np.ceil(10 * np.log2(n)))
    rng, best, best_gap = np.random.default_rng(seed), None, -1
    for _ in range(200):
        code = rng.choice((-1.0, 1.0), size=(n, bits))
        gap = min((code[i] != code[j]).sum() for i in range(n) for j in range(i))
        if gap > best_gap and (np.abs(code.sum(axis=0)) < n).all():
            best, best_gap = code, gap
    return best


class LanguageModel:
    def __init__(self, languages: list[str], code: np.ndarray, weights: np.ndarray, bias: np.ndarray, ambiguity: float = 0.1):
        self.languages, self.code, self.weights, self.bias, self.ambiguity = languages, code, weights, bias, ambiguity

    @classmethod
    def fit(cls, texts: list[str | np.ndarray], labels: list[str], steps: int = 300, rate: float = 2.0, l2: float = 1e-4) -> LanguageModel:
        """Full-batch logistic regression for all bits at once, from texts or their n-gram shares; classes weigh alike."""
        languages = sorted(set(labels))
        code = codewords(len(languages))
        x = np.stack([ngram_frequencies(t) if isinstance(t, str) else t for t in texts]).astype(np.float32) if texts else np.zeros((0, DIM), np.float32)
        which = np.searchsorted(languages, labels) if texts else np.zeros(0, int)
        y = code[which]
        share = np.bincount(which, minlength=len(languages)) if len(which) else np.ones(1)
        w8 = (1.0 / share[which] / max(1, len(languages)))[:, None] if len(which) else np.zeros((0, 1))
        w, b = np.zeros((DIM, code.shape[1]), np.float32), np.zeros(code.shape[1], np.float32)
        mw, mb = np.zeros_like(w), np.zeros_like(b)
        for _ in range(steps if len(texts) else 0):
            pull = (w8 * y / (1 + np.exp(np.clip(y * (x @ w + b), -30, 30)))).astype(np.float32)
            mw = 0.9 * mw + x.T @ pull - l2 * w
            mb = 0.9 * mb + pull.sum(axis=0)
            w, b = w + rate * mw, b + rate * mb
        return cls(languages, code, w, b)

    def losses(self, text: str) -> np.ndarray:
        margins = ngram_frequencies(text) @ self.weights + self.bias
        return np.logaddexp(0, -margins[None, :] * self.code).sum(axis=1)

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        """(language, score from 0 to 1, whether the two best codewords are nearly as good)."""
        if not self.languages or not has_letter(text):
            return "und", 0.0, True
        loss = self.losses(text)
        chance = np.exp(loss.min() - loss)
        chance /= chance.sum()
        best = int(np.argmin(loss))
        second = np.partition(loss, 1)[1] if len(loss) > 1 else np.inf
        return self.languages[best], float(chance[best]), bool(second - loss[best] < self.ambiguity * loss.shape[0])


def fit_languages(docs: DataFrame, may_learn, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id", per_language: int = 400, seed: int = 3) -> LanguageModel:
    """Fits on the ``per_language`` rows of least id hash of each language among those that ``may_learn``.

    That bounds what reaches the driver: ids of a few times that many rows, then the n-gram shares of the
    chosen ones, which executors take from the whole texts.  Rows are ranked by id and language alone; a
    text that is null or has no letter teaches nothing, and a null id or language is not chosen.
    """
    ranked = docs.where(may_learn & F.col(lang_col).isNotNull() & F.col(id_col).isNotNull()).select(F.col(lang_col).alias("lang"), F.col(id_col).alias("id"), F.xxhash64(F.lit(seed), id_col).alias("h"))
    limits = {r["lang"]: r["n"] for r in ranked.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    # a hash threshold expected to pass a few times the wanted rows, then the exact smallest of those
    cut = F.lit(False)
    for lang, n in limits.items():
        share = min(1.0, 3.0 * per_language / n)
        cut = cut | ((F.col("lang") == lang) & (F.pmod("h", F.lit(1_000_000)) < int(share * 1_000_000) + 1))
    chosen: dict[str, list] = {}
    for r in ranked.where(cut).toLocalIterator():
        chosen.setdefault(r["lang"], []).append((r["h"], r["id"]))
    ids = sorted({i for rows in chosen.values() for _, i in sorted(rows)[:per_language]})
    if not ids:
        return LanguageModel.fit([], [])
    wanted = docs.sparkSession.createDataFrame([(i,) for i in ids], f"_id {docs.schema[id_col].dataType.simpleString()}")
    rows = docs.join(F.broadcast(wanted), F.col(id_col) == F.col("_id"), "left_semi").where(may_learn & F.col(lang_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                text = b.column(2)[i].as_py()
                if has_letter(text):
                    shares = ngram_frequencies(text).astype(np.float32)
                    at = np.flatnonzero(shares).astype(np.uint16)
                    yield pa.RecordBatch.from_arrays([b.column(0).slice(i, 1), b.column(1).slice(i, 1), pa.array([at.tobytes()]), pa.array([shares[at].tobytes()])], names=["id", "lang", "at", "share"])

    schema = rows.select("id", "lang").schema.add("at", "binary").add("share", "binary")
    found = sorted(rows.mapInArrow(run, schema).collect(), key=lambda r: (r["id"], r["lang"], r["at"], r["share"]))
    x = []
    for r in found:
        dense = np.zeros(DIM, dtype=np.float32)
        dense[np.frombuffer(r["at"], dtype=np.uint16)] = np.frombuffer(r["share"], dtype=np.float32)
        x.append(dense)
    return LanguageModel.fit(x, [r["lang"] for r in found])


def identify(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, lang_pred, score, ambiguous)`` from whole texts: one pass, no shuffle.

    A null text, or one without a letter, is ``und`` with score 0.  Repeated rows get equal answers.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [model.predict(t.as_py()) for t in b.column(1)]
            lang, score, doubt = zip(*found, strict=True) if found else ((), (), ())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(doubt, pa.bool_())], names=["id", "lang_pred", "score", "ambiguous"])

    return docs.select(F.col(id_col).cast("long").alias("id"), text_col).mapInArrow(run, "id long, lang_pred string, score double, ambiguous boolean").withColumnRenamed("id", id_col)


def langid_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    held_out = F.crc32(F.col("doc_id").cast("string")) % 3 == 1
    model = fit_languages(docs, ~held_out)
    return identify(docs, model).select("doc_id", F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False)).alias("held_out"), "lang_pred", "score", "ambiguous")
