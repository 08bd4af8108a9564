"""Training-data pipeline: toxicity, line dedup, near-dedup, decontamination, sampled encodings.

Every stage keeps all columns of its input, whatever their names, but the last. Null texts pass all stages
(they have no words, lines or windows; equal ones are near copies of each other, and a null text encodes as an
empty one). Rows with a null id stay where an id decides. Rows that repeat an id are judged alike; ties go to the
smaller id. Empty tables give empty results.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rpqframe.llm import decontaminate, line_dedup, shingle_dedup, sp_sampling, toxicity
from rpqframe.llm.common import ensure_checkpoint_dir, read_table, release


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model rejects go."""
    return toxicity.drop_toxic(docs, toxicity.train_model(docs, read_table(spark, sf_dir, "labels")))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that stand earlier elsewhere, within one edit, go; so do documents of which nothing stays."""
    return line_dedup.dedup_lines(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: near SimHash fingerprints and shared shingles, verified at a similarity of 0.8 or more."""
    return shingle_dedup.drop_near_duplicates(docs)


def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Contaminated documents go."""
    return decontaminate.remove_contaminated(docs, read_table(spark, sf_dir, "benchmark"))


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id and its sampled segmentations with their scores."""
    return sp_sampling.sample_segmentations(docs)


#: The stage named simhash verifies pairs of near fingerprints first; what fingerprints of 64 bits do not separate it finds by shared shingles.
STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", toxicity_stage),
    ("line_dedup", line_stage),
    ("simhash", near_stage),
    ("decontamination", benchmark_stage),
    ("sentencepiece", encoding_stage),
]

#: Fingerprints, edit distances and sampled segmentations have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written to the shared checkpoint folder and reread."""
    ensure_checkpoint_dir(spark)
    root = spark.sparkContext.getCheckpointDir()
    docs = read_table(spark, sf_dir, "documents")
    at = spark.range(1).select(F.uuid()).first()[0]
    for name, stage in STAGES:
        path = f"{root}/pipeline-{at}/{name}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        release()
    return docs
