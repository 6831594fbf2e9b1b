"""Catalogs from files, folders and tables."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..catalog import Catalog

FORMATS = ("parquet", "orc", "json", "csv", "text")


def from_paths(spark: SparkSession, paths: dict[str, str], fmt: str = "parquet", nested: str = "skip", **options: str) -> Catalog:
    """Table name to path (a file, a folder or a glob). CSV is read with a header and as text, unless ``inferSchema`` is given."""
    if fmt not in FORMATS:
        raise ValueError(f"fmt={fmt!r}")
    options = ({"header": "true"} | options) if fmt == "csv" else options
    return Catalog({n: spark.read.format(fmt).options(**options).load(p) for n, p in paths.items()}, nested)


def from_tables(spark: SparkSession, names: dict[str, str] | list[str], nested: str = "skip") -> Catalog:
    """Tables or views of the session's catalog."""
    names = names if isinstance(names, dict) else {n.rpartition(".")[2]: n for n in names}
    return Catalog({n: spark.table(t) for n, t in names.items()}, nested)
