"""A coordinate-text data source: one ``i1 ... iK y`` line a nonzero, read and written by Spark tasks.

``spark.read.format("coo").option("modes", 3).load(path)`` and ``df.write.format("coo").save(path)``. It works on
folders that executors share as files; other stores are read with ``read_coordinates``.
"""

from __future__ import annotations

import os
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, path: str, modes: int):
        self.path, self.modes = path, modes

    def partitions(self):
        return [_File(os.path.join(self.path, f)) for f in sorted(os.listdir(self.path)) if f.endswith(".coo")] or [_File("")]

    def read(self, partition):
        if partition.path:
            with open(partition.path) as lines:
                for line in lines:
                    if line.strip():
                        *at, y = line.split()
                        yield (*[int(a) for a in at], float(y))


class _Writer(DataSourceWriter):
    def __init__(self, path: str):
        self.path = path
        os.makedirs(path, exist_ok=True)

    def write(self, rows):
        name = os.path.join(self.path, f"part-{uuid.uuid4().hex}.coo.tmp")
        with open(name, "w") as out:
            for row in rows:
                out.write(" ".join([*(str(int(v)) for v in row[:-1]), repr(float(row[-1]))]) + "\n")
        return _Done(name)

    def commit(self, messages):
        for m in messages:
            if m is not None:
                os.replace(m.name, m.name.removesuffix(".tmp"))

    def abort(self, messages):
        for m in messages:
            if m is not None and os.path.exists(m.name):
                os.remove(m.name)


class _Done(WriterCommitMessage):
    def __init__(self, name: str):
        self.name = name


class CoordinateSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "coo"

    def schema(self) -> str:
        return ", ".join(f"i{k} long" for k in range(1, int(self.options.get("modes", 3)) + 1)) + ", y double"

    def reader(self, schema):
        return _Reader(self.options["path"], int(self.options.get("modes", 3)))

    def writer(self, schema, overwrite):
        return _Writer(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(CoordinateSource)


def read_coordinates(spark: SparkSession, path: str, modes: int) -> DataFrame:
    """The same lines from any store that Spark reads."""
    parts = F.split(F.trim("value"), r"\s+")
    return spark.read.text(path).filter(F.length(F.trim("value")) > 0).select(*[F.get(parts, F.lit(k)).cast("long").alias(f"i{k + 1}") for k in range(modes)], F.get(parts, F.lit(modes)).cast("double").alias("y"))
