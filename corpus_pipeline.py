"""The corpus pipeline: documents in, token ids of a deduplicated, mixed and filtered corpus out.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last keep the columns
of documents. ``run`` writes each stage's result to the shared folder and reads it back as the next
stage's input, so that a lost executor costs one stage at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from idfold.llm import exact_dedup, mixing, piece_lattice, shingle_dedup, weak_quality
from idfold.llm.common import settle, table


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the weak-label scorer rejects go."""
    return weak_quality.keep_good(docs)


def exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts stays."""
    return exact_dedup.keep_winners(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of near copies (five-word shingles, similarity 0.8 or more) stays."""
    return shingle_dedup.keep_first(docs)


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are drawn by probabilities that are raked under the bound of one."""
    return mixing.sample(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, number of tokens and token ids of every document left."""
    return piece_lattice.encode(docs, piece_lattice.load_pieces()).select("doc_id", "n_tokens", "ids")


STAGES = [
    ("quality_classifier", quality_classifier),
    ("exact_dedup", exact_copies),
    ("simhash_near_dedup", near_copies),
    ("mixing", source_mixing),
    ("sentencepiece", tokens),
]

#: The scorer's training and the fingerprints' components have no SQL form; tests use brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
