"""A bounded, reproducible sample of labelled texts for the classifiers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fold_of(folds: int):
    """crc32 of the id as text, modulo ``folds``; null for a null id."""
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(folds))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, usable, limit_per_class: int) -> DataFrame:
    """(doc_id, text, y): at most ``limit_per_class`` labelled rows of each class that satisfy ``usable``.

    Rows with a null id or label are left out; an id labelled more than once takes its largest
    label. The chosen ids (a bounded number, hence broadcast) are the least by hash.
    """
    clean = labels.filter(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1) & usable).groupBy("doc_id").agg(F.max(F.col(label)).cast("int").alias("y"))
    chosen = None
    for y in (0, 1):
        part = clean.filter(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(limit_per_class)
        chosen = part if chosen is None else chosen.unionByName(part)
    return docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("doc_id", "text", "y")
