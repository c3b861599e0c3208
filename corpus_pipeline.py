"""A training corpus from raw documents: five stages of the operators in llm.

Each stage takes (spark, docs, sf_dir), works on all rows its predecessor kept and returns a
DataFrame; the caller writes it as Parquet and reads it back for the next. All but the last
return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from llm import decontamination, language_id, near_duplicates, packing, suffix_dedup
from llm.store import keep, small_batches, table, workspace


#: Near duplicates of the pipeline: Jaccard similarity in percent. 85 is the rule of op1 only.
NEAR_PERCENT = 80


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language that the classifier recognises; it is learned from the given lang column."""
    small_batches(spark)
    known = language_id.fit(docs, condition=f"not ({language_id.HELD_OUT})")
    return language_id.filter_stage(docs, known)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates (five-word shingles, similarity of 0.8 and more): the one with the smallest doc_id."""
    return near_duplicates.keep_one_of_each(docs, percent=NEAR_PERCENT)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the passages of 200 bytes and more that occur more than once."""
    return suffix_dedup.remove_repeats(docs)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark item is found."""
    small_batches(spark)
    return decontamination.clean(docs, decontamination.item_blocks(table(spark, sf_dir, "benchmark")))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents, packed into sequences."""
    return packing.pack(packing.pieces(docs))


STAGES = [
    ("language_id", identify_language),
    ("near_duplicates", drop_near_duplicates),
    ("suffix_dedup", cut_repeats),
    ("decontamination", drop_benchmark_leaks),
    ("packing", pack_sequences),
]

#: Trained networks, edit distances and a packing plan are beyond SQL; tests/llm compares the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = workspace(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = keep(docs, f"{path}/{i}-{name}")
    return docs
