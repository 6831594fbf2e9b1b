"""Sinks: column files, results and reports."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..discover import flatten


def column_files(values: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """(attr, v) as one folder a column, sorted in each file; a large column has many files."""
    values.repartitionByRange("attr", "v").sortWithinPartitions("attr", "v").write.mode(mode).partitionBy("attr").parquet(path)


def report(inds: DataFrame, path: str, fmt: str = "csv", mode: str = "errorifexists") -> None:
    """Dependencies as flat rows."""
    writer = flatten(inds).write.mode(mode)
    (writer.option("header", "true") if fmt == "csv" else writer).format(fmt).save(path)


def totals(inds: DataFrame) -> DataFrame:
    """(dep_table, arity, n): counts by table and arity with subtotals, NULL for all."""
    return inds.rollup("dep_table", "arity").agg(F.count(F.lit(1)).alias("n"))
