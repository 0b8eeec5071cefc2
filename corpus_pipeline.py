"""Cleaning pipeline over ``documents``: toxicity, recurring lines, near copies,
benchmark passages, packing.  Every stage takes (spark, docs, sf_dir), works on
all rows that its predecessor kept, and its decisions take effect."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tickspace.llm import decontam, jaccard, linededup, packing, toxicity
from tickspace.llm.queries import tokenizer_path
from tickspace.llm.shared import materialise, table


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that the random field scores as toxic.  The field learns
    from all labels of the input's documents."""
    return toxicity.drop_toxic(docs, toxicity.train_model(docs, table(spark, sf_dir, "labels")))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts recurring lines and sentences out of all documents but the first;
    a document that loses all its words so goes."""
    return linededup.drop_recurring_lines(docs, drop_emptied=True)


def near_copy_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group: five words, similarity 0.8 or more."""
    return jaccard.keep_one(docs)


def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold ten or more words of a benchmark item in a row."""
    return decontam.remove_contaminated(docs, table(spark, sf_dir, "benchmark"))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs the documents' tokens into windows of 2048."""
    return packing.pack_documents(docs, tokenizer_path())


STAGES = [("toxicity", toxicity_stage), ("line_dedup", line_stage), ("ngram_jaccard", near_copy_stage), ("decontamination", benchmark_stage), ("packing", packing_stage)]

#: a trained model and token ids are beyond SQL: the tests hold the stages
#: against brute-force versions
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return docs
