"""Lineage cuts, shared storage and phase timings."""

from __future__ import annotations

import os
import re
import tempfile
import time
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``, which all executors share; only a session on one machine may leave it unset."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root and not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    return root or "file://" + os.path.join(tempfile.gettempdir(), "incdep-shared")


def new_folder(spark: SparkSession, tag: str) -> str:
    """A fresh folder name below the shared root; nothing is created yet."""
    return f"{shared_root(spark).rstrip('/')}/{tag}-{uuid.uuid4().hex[:12]}"


def delete(spark: SparkSession, path: str) -> None:
    """Delete a folder of the shared root."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(where, True)


def written(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: later plans start there, and survive lost executors."""
    out = new_folder(df.sparkSession, tag)
    df.write.parquet(out)
    return df.sparkSession.read.schema(df.schema).parquet(out)


class Phases:
    """Wall-clock seconds of materialised phases: preprocessing, candidate generation, validation, filling, checking."""

    def __init__(self) -> None:
        self.seconds: dict[str, float] = {}

    @contextmanager
    def __call__(self, name: str):
        began = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began
