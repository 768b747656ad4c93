"""A corpus from raw documents to packed sequences, each stage one operator over all its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellgraph.llm.linededup import dedup_lines
from cellgraph.llm.mixing import apply_mix
from cellgraph.llm.packing import pack_documents
from cellgraph.llm.resemblance import drop_near_duplicates
from cellgraph.llm.tokencount import read_tokenizer
from cellgraph.llm.toxicity import reject_toxic, train
from cellgraph.scratch import Scratch
from cellgraph.workers import executors_give_back


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents that score 0.5 or more; the models are learned from this stage's input and the labels."""
    chars, model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return reject_toxic(docs, chars, model)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in at least 10 documents stay only in the first of them; documents stay, n_chars follows the text.

    The first keeps them so that a group of copies is not emptied before the next stage picks one of it.
    """
    names = [f"_line_dedup_{n}" for n in ("text", "lines", "dropped")]
    out = dedup_lines(docs, keep_first=True, names=tuple(names))
    changed = F.col(names[2]) > 0
    new = {"text": F.when(changed, F.col(names[0])).otherwise(F.col("text")), "n_chars": F.when(changed, F.length(names[0]).cast("long")).otherwise(F.col("n_chars")) if "n_chars" in docs.columns else None}
    return out.select(*[new[c].alias(c) if c in new else F.col(c) for c in docs.columns])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document stays of each group of five-word-shingle similarity 0.8 or more; whole shingle sets decide, not fingerprints (see README)."""
    executors_give_back(spark)
    return drop_near_duplicates(docs)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources at weights 5, 2, 1, at most three epochs; documents come as often as the mix takes them."""
    return apply_mix(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Windows of 1024 tokens.  Each worker loads the tokenizer, for which the stages before make room."""
    executors_give_back(spark)
    return pack_documents(docs, read_tokenizer())


STAGES = [("toxicity", toxicity), ("line_dedup", line_dedup), ("near_duplicates", near_duplicates), ("mixing", mixing), ("packing", packing)]

#: The first stage scores by a fitted model, which SQL cannot express; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; every stage's result is written as Parquet and read again."""
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        previous, docs = docs, scratch.save(stage(spark, docs, sf_dir))
        scratch.drop(previous)
    return docs
