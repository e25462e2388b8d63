"""Exact duplicates by a tree merge of sorted digest runs, with DataFrame operators only.

1. Runs: rows are dealt to ``2 ** rounds`` runs. Each task sorts its digests and merges equal
   neighbours in one stream, before anything is moved: a text that a third of all rows share leaves
   every task as one record a run. A record is a digest with its check values, the identifier that
   would stay (with the run it came from), and its row count.
2. Rounds: in every round run r meets run r + half. The two runs are brought together by digest,
   sorted, and merged in one stream: of equal neighbours one record stays, with the better identifier
   and the sum of the counts. After the last round one run, split over all tasks by digest, is left.

The record that stays is an ordered pair, which Spark aggregates by sorting: every level of the
plan is a Sort and a SortAggregate on both sides of an exchange, which spill to disk and hold one
group at a time.

A digest is the SHA-256 of the text; it is verified at every level by the text's length and a
second, independent hash, which are part of the merge key: records that differ in any of them never
merge. The result joins rows to survivors by digest; that join may be split by Spark where one
digest is very frequent.

Defined results: null counts as empty text; rows that repeat both id and text are one another's
copies and all of them carry the surviving id, so all are marked kept (``surviving_rows`` leaves
one); a group keeps a null id only if no row has another, and then ``surviving_rows`` leaves one row;
one id on several texts is judged text by text; an empty table gives an empty result; extra columns
are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .runtime import materialise, one_of_each, table

ROUNDS = 3
KEY = ["digest", "n_bytes", "check"]


def fingerprints(docs: DataFrame, normalised: Column | None = None) -> DataFrame:
    """(doc_id, digest, n_bytes, check) of each row; ``normalised`` is the text to compare, null as empty."""
    text = F.coalesce(F.col("text") if normalised is None else normalised, F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.unhex(F.sha2(text, 256)), F.lit(b"")).alias("digest"), F.octet_length(text).alias("n_bytes"), F.xxhash64(text).alias("check"))


def _merged(run: DataFrame, keep: str) -> DataFrame:
    """Sorted neighbours with equal digests of a run become one record."""
    pick = {"least": F.min, "largest": F.max}[keep]
    return run.groupBy(*KEY, "run").agg(pick("stays").alias("stays"), F.sum("rows").alias("rows"))


def merge_runs(prints: DataFrame, keep: str = "least", rounds: int = ROUNDS) -> DataFrame:
    """(digest, n_bytes, check, keep_id, group_size): the last run of the tree."""
    run = F.pmod(F.xxhash64("doc_id"), F.lit(1 << rounds))
    stays = F.when(F.col("doc_id").isNotNull(), F.struct(F.col("doc_id").alias("id"), run.alias("origin")))
    level = _merged(prints.select(*KEY, run.alias("run"), stays.alias("stays"), F.lit(1).cast("long").alias("rows")), keep)
    for r in reversed(range(rounds)):
        level = _merged(level.withColumn("run", F.pmod("run", F.lit(1 << r))), keep)
    return level.select(*KEY, F.col("stays.id").alias("keep_id"), F.col("rows").alias("group_size"))


def _judged(docs: DataFrame, keep: str, rounds: int, normalised: Column | None = None) -> DataFrame:
    prints = fingerprints(docs, normalised)
    joined = prints.join(merge_runs(prints, keep, rounds), KEY)
    return joined.select("doc_id", "digest", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"))


def exact_duplicates(docs: DataFrame, keep: str = "least", rounds: int = ROUNDS, normalised: Column | None = None) -> DataFrame:
    """One row per row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256."""
    return _judged(docs, keep, rounds, normalised).select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


def surviving_rows(docs: DataFrame, keep: str = "least", rounds: int = ROUNDS) -> DataFrame:
    """The rows of ``docs`` that stay, all columns: one of each group of equal texts."""
    return one_of_each(docs, materialise(_judged(docs, keep, rounds).select("doc_id", "digest", "kept"), "judged"))


def op3_exactdup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_duplicates(table(spark, sf_dir, "documents"), keep="largest")


ORACLE = """
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW w AS (PARTITION BY coalesce(text, ''))
"""
