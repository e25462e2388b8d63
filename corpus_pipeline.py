"""The corpus pipeline: each stage works on all rows that the one before it kept.

Toxic texts go, then exact copies, then near copies (five-word shingles, similarity 0.8), then texts
that repeat benchmark passages; what is left is encoded. Every stage is written as Parquet in the
shared scratch folder and read again, so a lost executor repeats one stage at most.

Defined results: a null text counts as empty, and of all empty texts one row stays; of rows that
repeat an id and a text one stays; an id that stands on several texts is judged text by text; an empty
table gives an empty result; extra columns are carried to the last stage, which returns its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from arrayfactor.llm import decontaminate, exactdup, neardup, pieces, toxicity
from arrayfactor.llm.runtime import materialise, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.surviving_rows(docs, table(spark, sf_dir, "labels"))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exactdup.surviving_rows(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return neardup.surviving_rows(docs, shingle=5, percent=80)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pieces.encode(docs, with_ids=True)


STAGES = [
    ("toxicity", drop_toxic),
    ("exact_dedup", drop_copies),
    ("near_dedup", drop_near_copies),
    ("decontamination", drop_contaminated),
    ("encoding", encode_pieces),
]
#: Classifier and encoder are beyond SQL; tests hold the pipeline against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``: doc_id, n_pieces, ids_sha256, round_trip, ids of every row that stays."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
