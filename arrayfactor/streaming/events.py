"""Arrays that grow: windows, presence arrays, state and model updates on streams of records.

Each operator works on a batch or a streaming DataFrame alike; ``replayed`` runs one to its end with
the ``availableNow`` trigger and gives the result table, which the tasks write to the shared scratch folder.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.arrays import build_array


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").option("recursiveFileLookup", "true").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def event_stream_by_week(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of one file a week, in order, one micro-batch each: an array that grows."""
    from ..sources.tables import scratch

    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    weeks = events.select(F.date_trunc("week", "ts").alias("week")).distinct().orderBy("week").collect()  # one row a week
    path = f"{scratch(spark)}/weeks-{uuid.uuid4().hex[:12]}"
    for r in weeks:
        events.filter(F.date_trunc("week", "ts") == F.lit(r.week)).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)


def replayed(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a streaming DataFrame over all that is there now; batches are written by the tasks, none comes to the driver.

    The result is all batches, or with "complete" the last one, which holds the whole table.
    """
    from ..sources.tables import scratch

    spark = df.sparkSession
    path = f"{scratch(spark)}/stream-{uuid.uuid4().hex[:12]}"
    written: dict[int, str] = {}

    def write(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{n}")  # a batch that is tried again replaces its own rows
        written[n] = f"{path}/{n}"

    query = df.writeStream.outputMode(mode).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).foreachBatch(write).start()
    query.awaitTermination()
    if not written:
        return spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(*([written[max(written)]] if mode == "complete" else written.values()))


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", "1 day").groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "1 day", slide: str = "12 hours") -> DataFrame:
    return events.withWatermark("ts", "1 day").groupBy(F.window("ts", width, slide), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events.withWatermark("ts", "1 day").groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def presence(events: DataFrame, modes: list[str]) -> DataFrame:
    """Nonzeros of a growing presence array: each coordinate once."""
    return events.select(*modes).dropDuplicates(modes).withColumn("y", F.lit(1.0))


def static_encode(events: DataFrame, dictionary: DataFrame, column: str, mode: int) -> DataFrame:
    """A stream joined to a fixed dictionary."""
    own = dictionary.filter(F.col("mode") == mode).select(F.col("key").alias("_key"), F.col("idx"))
    return events.join(own, events[column].cast("string") == F.col("_key")).drop("_key")


def user_weights(events: DataFrame) -> DataFrame:
    """Running slice weight of each user, kept as state across micro-batches."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        weight = state.get[0] if state.exists else 0
        weight += sum(len(f) for f in frames)
        state.update((weight,))
        yield pd.DataFrame({"user_id": [key[0]], "weight": [weight]})

    return events.select("user_id").groupBy("user_id").applyInPandasWithState(update, "user_id long, weight long", "weight long", "update", GroupStateTimeout.NoTimeout)


def fit_stream(stream: DataFrame, modes: list[str], update: Callable[[DataFrame, int], None]) -> None:
    """Each micro-batch's new nonzeros go to ``update`` with the batch's number; it refits from the last factors."""
    query = stream.writeStream.foreachBatch(lambda df, n: update(build_array(df, modes), n)).trigger(availableNow=True).start()
    query.awaitTermination()
