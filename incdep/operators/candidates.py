"""Unary candidates and sound filters on them. All relations here have a size in attributes, not in rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..catalog import Catalog


def unary(catalog: Catalog, typed: bool = False) -> DataFrame:
    """(dep, ref): all ordered pairs of different attributes; ``typed`` keeps pairs of one type class only."""
    one = catalog.dictionary(catalog.spark)
    dep, ref = one.select(F.col("attr").alias("dep"), F.col("type_class").alias("t")), one.select(F.col("attr").alias("ref"), F.col("type_class").alias("u"))
    return dep.crossJoin(F.broadcast(ref)).filter("dep <> ref" + " and t = u" * typed).select("dep", "ref")


def prune(candidates: DataFrame, stats: DataFrame, by_max: bool = True, by_min: bool = False, by_count: bool = False) -> DataFrame:
    """Drop candidates that bounds rule out.

    A dependent column whose largest value is above the referenced column's can't be included; likewise one whose smallest
    is below, or that has more distinct values. Empty dependent columns stay.
    """
    dep = stats.select(F.col("attr").alias("dep"), F.col("max_v").alias("dmax"), F.col("min_v").alias("dmin"), F.col("distinct_values").alias("dn"))
    ref = stats.select(F.col("attr").alias("ref"), F.col("max_v").alias("rmax"), F.col("min_v").alias("rmin"), F.col("distinct_values").alias("rn"))
    keep = F.lit(True)
    if by_max:
        keep &= F.col("dmax") <= F.col("rmax")
    if by_min:
        keep &= F.col("dmin") >= F.col("rmin")
    if by_count:
        keep &= F.col("dn") <= F.col("rn")
    return candidates.join(F.broadcast(dep), "dep").join(F.broadcast(ref), "ref").filter((F.col("dn") == 0) | F.coalesce(keep, F.lit(False))).select("dep", "ref")
