"""Session helpers shared by the training-data operators."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark alone (the path may be any store Spark knows)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """The shared folder for intermediate tables: ``spark.checkpoint.dir`` of the session.

    Only where that is unset and all of Spark is one process a temporary folder of our own is made;
    on a cluster, where executors would each write to a disk of their own, that is an error.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if "dir" not in _OWN:
        _OWN["dir"] = tempfile.mkdtemp(prefix="corpus_scratch_")
    return "file://" + _OWN["dir"]


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` once to the shared scratch folder and return the table read back.

    This cuts the lineage (a lost executor costs no more than a re-read) and lets several
    consumers use one computation. The files go when the driver exits.
    """
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/corpus-{spark.sparkContext.applicationId}/{label}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    _remove_at_exit(spark, path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession, df: DataFrame) -> None:
    """Delete the files of a table made by :func:`materialise` that no later plan reads."""
    for name in df.inputFiles():
        folder = spark._jvm.org.apache.hadoop.fs.Path(name).getParent()
        fs = folder.getFileSystem(spark._jsc.hadoopConfiguration())
        if "/corpus-" in folder.toString() and fs.exists(folder):
            fs.delete(folder, True)


BROADCAST_ROWS = 500_000


def text_digest(text: Column) -> Column:
    """SHA-256 of a text, null as empty: with the id, what tells the rows of a table apart."""
    return F.unhex(F.sha2(F.coalesce(text, F.lit("")), 256))


def without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """Rows of ``docs`` whose (doc_id, text) is not in ``gone`` (doc_id, digest); null ids are values like others.

    ``gone`` is written first; where it is short (a checked number of 40-byte rows) it is broadcast
    and the texts stay where they are, otherwise both sides are shuffled.
    """
    gone = materialise(gone.select(F.col("doc_id").alias("gone_id"), F.col("digest").alias("gone_digest")).distinct(), "gone")
    side = F.broadcast(gone) if gone.count() <= BROADCAST_ROWS else gone.hint("shuffle_hash")
    same = F.col("gone_digest").eqNullSafe(text_digest(docs["text"])) & F.col("gone_id").eqNullSafe(docs["doc_id"].cast("long"))
    return docs.join(side, same, "left_anti").select(*[docs[c] for c in docs.columns])


def one_of_each(docs: DataFrame, judged: DataFrame) -> DataFrame:
    """Rows of ``docs`` that stay, given ``judged`` (doc_id, digest, kept) with one row per row of ``docs``.

    Rows that repeat both id and text are told apart by nothing; of those one stays.
    """
    rest = without(docs, judged.filter(~F.col("kept")))
    repeated = materialise(judged.filter("kept").groupBy("doc_id", "digest").count().filter("count > 1").select("doc_id", "digest"), "repeated")
    if not repeated.limit(1).count():
        return rest
    own = F.broadcast(repeated.select(F.col("doc_id").alias("gone_id"), F.col("digest").alias("gone_digest"))) if repeated.count() <= BROADCAST_ROWS else repeated.select(F.col("doc_id").alias("gone_id"), F.col("digest").alias("gone_digest"))
    same = F.col("gone_digest").eqNullSafe(text_digest(rest["text"])) & F.col("gone_id").eqNullSafe(rest["doc_id"].cast("long"))
    again = rest.join(own, same, "left_semi").dropDuplicates(["doc_id", "text"])
    return without(rest, repeated).unionByName(again)


def _remove_at_exit(spark: SparkSession, path: str) -> None:
    def remove() -> None:
        try:
            target = spark._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
        except Exception:  # the session is gone: the folder goes with the cluster's scratch space
            pass

    atexit.register(remove)
