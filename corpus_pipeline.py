"""From raw documents to token blocks: quality, near-duplicates, benchmark leaks, mixing, tokens.

Each stage takes what its predecessor kept, written as Parquet and read back, and all
but the last return the columns of ``documents``. Stages read every row and whole texts.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from relstrata.llm import decontaminate, mixing, near_copies, quality, token_output
from relstrata.llm.common import load, without, written

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that repeat themselves or that the forest rejects go; short ones stay if they are clean.

    Rows that share an id (or have none) are judged each by its own text.
    """
    judged = quality.judge_quality(docs, load(spark, sf_dir, "labels"), min_words=0)
    return without(docs, judged.where("not kept")).select(*COLUMNS)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest doc_id of each group of near copies stays: five-word shingles, similarity 0.8 or more, verified."""
    return near_copies.dedup(docs).select(*COLUMNS)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return decontaminate.decontaminated(docs, load(spark, sf_dir, "benchmark")).select(*COLUMNS)


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Copies by the sources' target weights, in an order without regard to where they came from."""
    return mixing.replicate(docs).select(*COLUMNS)


def token_blocks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token blocks on disk; one row per document copy, read back from them."""
    return token_output.documents_of(token_output.write_tokens(docs))


STAGES = [
    ("quality rules", quality_rules),
    ("near dedup", near_dedup),
    ("benchmark decontamination", benchmark_decontamination),
    ("source mixing", source_mixing),
    ("token output", token_blocks),
]

#: Forests, fingerprint groups and coded blocks are beyond SQL; the tests hold a brute-force version against run().
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select(*COLUMNS)
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
