"""Training-data pipeline over ``documents``: name languages, drop near duplicates, cut repeated strings, mix, pack.

Each stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept; its result is written as Parquet in the
shared folder and read again as the next one's input. All stages but the last return the columns of ``documents``. An
empty table passes through every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from freqspark.llm import language_id, mixing, near_dedup, packing, suffix_dedup
from freqspark.llm.common import documents, drop_written, written


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the model names; those without a letter or with a doubtful language go."""
    return language_id.keep_identified(docs)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that shares 0.8 of its five-word shingles, by links."""
    return near_dedup.deduplicated(docs)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without strings of 100 bytes that stand earlier in the corpus; texts with nothing left go."""
    return suffix_dedup.without_repeats(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources at their target weights; a document stands as often as the mix takes it."""
    return mixing.mixed_documents(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of full sequences in the order of the space-filling curve."""
    return packing.pack(docs)


STAGES = [
    ("language_id", identify_language),
    ("near_dedup", drop_near_duplicates),
    ("suffix_dedup", cut_repeats),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: No SQL expresses the stages; tests hold each one against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        after = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
        drop_written(docs)
        docs = after
    return written(STAGES[-1][1](spark, docs, sf_dir), "pipeline-packing")
