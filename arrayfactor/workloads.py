"""The experiment workloads on the given tables, as arrays and as models; each function takes (spark, sf_dir)."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.hashing import keyed, uniform
from .operators import arrays
from .sources.tables import checkpointed, table

TOP = 200  # words of the text triples; the functions take any other number, up to the 20,000 of the reference
TOKEN = "[^a-zà-öø-ÿœæ]+"
LETTERS = bytes(32 if re.fullmatch(TOKEN, bytes([b]).decode("cp1252", "replace")) else b for b in range(256))
GAP = b"\x01"  # between texts
CHUNK = 16_000_000  # bytes of texts split at a time


def tokens(text) -> object:
    """Lower-cased words of a text by an explicit letter class, which other engines read alike."""
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), TOKEN), "")


def top_tokens(words: DataFrame, n: int) -> DataFrame:
    """The n most frequent words; ties by the word. At most n rows."""
    return words.select(F.explode("w").alias("t")).groupBy("t").agg(F.count("*").alias("c")).orderBy(F.desc("c"), "t").limit(n).select("t")


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[bytes, np.ndarray, np.ndarray, np.ndarray]]:
    """(bytes, starts, lengths, heads) of the words of some texts at a time, as ``tokens`` splits them.

    A byte stands for each letter of the class, a space for all else; two words ``GAP`` follow each text. The head of a word
    is its first eight bytes as a number: the word itself unless it is longer.
    """
    for batch in batches:
        parts, size = [], 0
        for k, text in enumerate(batch.column(0), 1):
            own = (text.as_py() or "").lower().encode("cp1252", "replace").translate(LETTERS)
            parts += (own, GAP, GAP)
            size += len(own)
            if size < CHUNK and k < len(batch):
                continue
            blob = b" ".join(parts) + b" " * 8
            edges = np.flatnonzero(np.diff(np.frombuffer(blob, np.uint8) != 32, prepend=False, append=False))
            starts, n = edges[::2], edges[1::2] - edges[::2]
            yield blob, starts, n, _heads(blob, starts, n)
            parts, size = [], 0


def _heads(blob: bytes, starts: np.ndarray, n: np.ndarray) -> np.ndarray:
    windows = np.ndarray((len(blob) - 7,), "<u8", blob, strides=(1,))
    masks = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
    return windows[starts] & masks[np.minimum(n, 8)]


def frequent_words(docs: DataFrame, n: int) -> list[str]:
    """``top_tokens`` of texts in order, most frequent first: words are split and counted in the tasks."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for blob, starts, size, heads in _chunks(batches):
            short, often = np.unique(heads[size <= 8], return_counts=True)
            seen = Counter(blob[a : a + m] for a, m in zip(starts[size > 8].tolist(), size[size > 8].tolist(), strict=True))
            words = b" ".join([*short.astype("<u8").view("S8").tolist(), *seen]).decode("cp1252").split(" ")
            yield pa.RecordBatch.from_pydict({"t": pa.array(words, pa.string()), "c": pa.array([*often.tolist(), *seen.values()], pa.int64())})

    counted = docs.select("text").mapInArrow(count, "t string, c long").filter(F.col("t") != GAP.decode()).groupBy("t").agg(F.sum("c").alias("c"))
    return [r.t for r in counted.orderBy(F.desc("c"), "t").limit(n).collect()]  # at most n rows


def frequent_runs(docs: DataFrame, frequent: list[str]) -> DataFrame:
    """(i1, i2, i3, n): counts of three words in a row, all in the list, by their places in it from 1; other runs stay in the tasks."""
    places, base = {t.encode("cp1252"): k for k, t in enumerate(frequent, 1)}, len(frequent) + 1

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blob = b" ".join(places) + b" " * 8
        size = np.array([len(t) for t in places], np.int64)
        listed = _heads(blob, np.cumsum(size + 1) - size - 1, size)
        short = sorted((h, k) for k, (h, m) in enumerate(zip(listed.tolist(), size.tolist(), strict=True), 1) if m <= 8)
        keys, of, long = np.array([h for h, _ in short], np.uint64), np.array([0, *(k for _, k in short)], np.int64), np.unique(listed[size > 8])
        for blob, starts, size, heads in _chunks(batches):
            at = np.searchsorted(keys, heads)
            ids = of[np.where((size <= 8) & (keys.take(at, mode="clip") == heads), at + 1, 0)] if len(keys) else np.zeros(len(heads), np.int64)
            for k in np.flatnonzero((size > 8) & np.isin(heads, long)).tolist():
                ids[k] = places.get(blob[starts[k] : starts[k] + size[k]], 0)
            a, b, c = ids[:-2], ids[1:-1], ids[2:]
            inside = (a > 0) & (b > 0) & (c > 0)
            runs, n = np.unique((a[inside] * base + b[inside]) * base + c[inside], return_counts=True)
            yield pa.RecordBatch.from_pydict({"i1": runs // base**2, "i2": runs // base % base, "i3": runs % base, "n": n.astype(np.int64)})

    return docs.select("text").mapInArrow(count, "i1 long, i2 long, i3 long, n long").groupBy("i1", "i2", "i3").agg(F.sum("n").alias("n"))


def triple_counts(spark: SparkSession, sf_dir: str, top: int = TOP, quality: bool = False) -> DataFrame:
    """Counts of three words in a row, all among the most frequent: subject, verb and object of a text fact."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return _triples(docs, frequent_words(docs, top), table(spark, sf_dir, "labels") if quality else None)


def _triples(docs: DataFrame, frequent: list[str], labels: DataFrame | None = None) -> DataFrame:
    """(w1, w2, w3, n) of the runs of frequent words, in documents of good quality where labels are given."""
    if labels is not None:
        docs = docs.join(labels.filter("quality = 1").select("doc_id").distinct(), "doc_id", "left_semi")
    out, words = frequent_runs(docs, frequent), ranked(docs.sparkSession, frequent)
    for k in (1, 2, 3):  # the list has at most ``top`` rows
        out = out.join(F.broadcast(words.select(F.col("t").alias(f"w{k}"), F.col("idx").alias(f"i{k}"))), f"i{k}")
    return out.select("w1", "w2", "w3", "n")


def ranked(spark: SparkSession, frequent: list[str]) -> DataFrame:
    """(t, idx) of a list of words, from 1."""
    return spark.range(1).select(F.posexplode(F.lit(frequent).cast("array<string>")).alias("k", "t")).select("t", (F.col("k") + 1).cast("long").alias("idx"))


def log_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", F.get_json_object("props", "$.k").alias("k"), "value")


LOG = ("user_id", "event_type", "k")


def log_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    return arrays.build_array(log_records(spark, sf_dir), LOG)


def encoded_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    arr = log_array(spark, sf_dir)
    return arrays.encode(arr, arrays.mode_dictionary(arr, LOG), LOG)


def stored_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The encoded array written once, for plans that read it several times."""
    return checkpointed(encoded_log(spark, sf_dir), "log")


def encoded_triples(spark: SparkSession, sf_dir: str, top: int = TOP, least: int = 1) -> DataFrame:
    """Triples with one shared word dictionary in every mode, indices by frequency rank."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    frequent = frequent_words(docs, top)
    words = ranked(spark, frequent)
    out = _triples(docs, frequent).filter(F.col("n") >= least)
    for k in (1, 2, 3):
        out = out.join(F.broadcast(words.select(F.col("t").alias(f"w{k}"), F.col("idx").alias(f"i{k}"))), f"w{k}")
    return out.select("i1", "i2", "i3", F.lit(1.0).alias("y"))


def sizes_of(arr: DataFrame) -> list[int]:
    """Largest index of every mode."""
    return [int(v) for v in arr.agg(*[F.max(f"i{k}") for k in range(1, arrays.order_of(arr) + 1)]).first()]


def order_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", "l_returnflag", "l_discount")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority")
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey)


def nation_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = order_lines(spark, sf_dir).filter("l_returnflag = 'R' AND l_discount >= 0.09 AND o_orderpriority = '1-URGENT'")
    customer = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey")
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand", "p_type")
    supplier = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    return lines.join(customer, "o_custkey").join(part, "l_partkey").join(supplier, "l_suppkey")


def trade_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = order_lines(spark, sf_dir)
    customer = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").alias("nation"))
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), F.col("p_brand").alias("brand"))
    return lines.join(customer, "o_custkey").join(part, "l_partkey").select("nation", "brand", F.date_format("l_shipdate", "yyyy-MM").alias("month"), "l_extendedprice")


def planted(spark: SparkSession, side: int = 24, share: float = 0.15, linear: bool = False, seed: int = 3) -> DataFrame:
    """An array with known structure: nonzeros (i1, i2, i3, y), ones in the top share of all cells.

    The nonlinear truth mixes products of waves of hidden coordinates; the linear twin is a positive
    rank-two product, on which a multilinear model has nothing to lose.
    """
    ids = spark.range(1, side + 1)
    u = lambda k, d: uniform(keyed(seed, "t", k, F.col(f"i{k}"), d))
    cells = ids.toDF("i1").join(F.broadcast(ids.toDF("i2")), F.lit(True)).join(F.broadcast(ids.toDF("i3")), F.lit(True))
    if linear:
        truth = u(1, 0) * u(2, 0) * u(3, 0) + u(1, 1) * u(2, 1) * u(3, 1)
    else:
        truth = F.sin(2 * 3.141592653589793 * u(1, 0)) * F.sin(2 * 3.141592653589793 * (u(2, 0) + u(3, 0))) + 0.5 * F.cos(2 * 3.141592653589793 * u(1, 1) * u(2, 1))
    cells = checkpointed(cells.withColumn("truth", truth), "planted")
    cut = cells.agg(F.expr(f"percentile(truth, {1 - share})").alias("c")).first().c
    return cells.filter(F.col("truth") > cut).select("i1", "i2", "i3", F.lit(1.0).alias("y"))
