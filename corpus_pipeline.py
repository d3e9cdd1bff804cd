"""The corpus pipeline: five stages over documents, each written as Parquet and read again by the next.

All stages but the last return the columns of documents. Rows without an id pass the stages that decide by id.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from veilwalk.llm import decontaminate, language, packing, pii, simhash
from veilwalk.llm.common import Scratch, table

#: Texts whose leading language holds a smaller share of the letters are rejected, as are texts without a letter of a
#: learned script and texts that the background explains better than their leading language by half a nat per letter
#: (texts of a few words of another kind, such as a notice alone, lie a little below zero; prose at three).
LEAST_SHARE, LEAST_MARGIN = 0.35, -0.5


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in one of the learned languages."""
    model = language.fit(docs.where(~language.held_out()))
    found = language.predict(docs, model, margin=True)
    return found.where(f"lang_pred <> 'und' and score >= {LEAST_SHARE} and margin >= {LEAST_MARGIN}").select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates, that of the smallest id: SimHash fingerprints and bands of minima give
    candidates, the exact similarity decides."""
    return simhash.keep_first(docs).select(*docs.columns)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item within its error budget."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def redact_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data in their texts replaced by its kind."""
    return pii.redacted(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their places in training sequences."""
    return packing.packed(docs)


STAGES = [
    ("language", identify_language),
    ("near-duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark_leaks),
    ("personal data", redact_personal_data),
    ("packing", pack_sequences),
]

#: SQL cannot tokenize, hash shingles or run Viterbi; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, scratch = table(spark, sf_dir, "documents"), Scratch(spark, "pipeline")
    for k, (_, stage) in enumerate(STAGES[:-1]):
        docs = scratch.save(stage(spark, docs, sf_dir), f"stage{k}")
    return scratch.save(STAGES[-1][1](spark, docs, sf_dir), "packed")
