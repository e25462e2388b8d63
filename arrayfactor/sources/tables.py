"""Reading tables and keeping intermediate ones in the shared scratch folder."""

from __future__ import annotations

import pickle
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; where that is unset, a temporary folder if all of Spark is one process."""
    if not spark.conf.get("spark.checkpoint.dir", None) and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    root = spark.conf.get("spark.checkpoint.dir", None) or _OWN.setdefault("dir", "file://" + tempfile.mkdtemp(prefix="arrayfactor_"))
    return f"{root.rstrip('/')}/arrayfactor-{spark.sparkContext.applicationId}"


def checkpointed(df: DataFrame, label: str) -> DataFrame:
    """``df`` written once to the shared scratch folder and read back: lineage ends here."""
    path = f"{scratch(df.sparkSession)}/{label}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def by_mode(df: DataFrame, value: str) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """mode: (idx, value) of a table (mode, idx, value) in the order of idx, for sizes that were checked.

    The tasks pack them into arrays: a row is its numbers alone on the driver, not objects of some hundred bytes.
    """

    def pack(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            parts = [(int(k), g["idx"].to_numpy(np.int64), np.array(g[value].tolist(), float)) for k, g in frame.groupby("mode")]
            yield pd.DataFrame({"part": [pickle.dumps(parts)]})

    parts = [x for r in df.select("mode", "idx", value).mapInPandas(pack, "part binary").collect() for x in pickle.loads(r.part)]
    out = {}
    for k in sorted({k for k, _, _ in parts}):
        idx, values = (np.concatenate([x[n] for x in parts if x[0] == k]) for n in (1, 2))
        order = np.argsort(idx, kind="stable")
        out[k] = idx[order], values[order]
    return out
