"""Tasks on dependencies: validation, partial dependencies, foreign keys, joins, reduction."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import Catalog
from .exact import shared_counts


def _distinct(df: DataFrame, cols: list[str], nulls: str) -> DataFrame:
    out = df.select(*(F.col(f"`{c}`").cast("string").alias(f"c{k}") for k, c in enumerate(cols))).distinct()
    return out.dropna() if nulls == "ignore" else out


def violations(dep: DataFrame, dep_cols: list[str], ref: DataFrame, ref_cols: list[str], nulls: str = "equal") -> DataFrame:
    """Distinct dependent tuples (c0, c1, ... as text) that the referenced side lacks."""
    left, right = _distinct(dep, dep_cols, nulls), _distinct(ref, ref_cols, nulls)
    on = [left[c].eqNullSafe(right[c]) for c in left.columns]
    return left.join(right, on, "left_anti")


def validate(dep: DataFrame, dep_cols: list[str], ref: DataFrame, ref_cols: list[str], nulls: str = "equal") -> DataFrame:
    """(holds, dep_distinct, missing, error) of one declared dependency."""
    left, right = _distinct(dep, dep_cols, nulls), _distinct(ref, ref_cols, nulls).withColumn("_in", F.lit(1))
    both = left.join(right, [left[c].eqNullSafe(right[c]) for c in left.columns], "left")
    n, miss = F.count(F.lit(1)), F.count_if(F.col("_in").isNull())
    return both.agg(n.alias("dep_distinct"), miss.alias("missing")).select((F.col("missing") == 0).alias("holds"), "dep_distinct", "missing", F.when(F.col("dep_distinct") > 0, F.col("missing") / F.col("dep_distinct")).otherwise(0.0).alias("error"))


def partial_inds(values: DataFrame, n: int, eps: float) -> DataFrame:
    """(dep, ref, dep_distinct, missing, error) of pairs that lack at most a share ``eps`` of the dependent's distinct values."""
    c = shared_counts(values, n)
    c = c.select("dep", "ref", F.col("distinct_values").alias("dep_distinct"), (F.col("distinct_values") - F.col("shared")).alias("missing"))
    return c.withColumn("error", F.col("missing") / F.col("dep_distinct")).filter(F.col("error") <= eps)


def named(pairs: DataFrame, catalog: Catalog) -> DataFrame:
    """(dep, ref, ...) with dep_table, dep_col, ref_table, ref_col."""
    one = catalog.dictionary(catalog.spark)
    for side in ("dep", "ref"):
        pairs = pairs.join(F.broadcast(one.select(F.col("attr").alias(side), F.col("table_name").alias(f"{side}_table"), F.col("column_name").alias(f"{side}_col"))), side)
    return pairs


def fk_candidates(pairs: DataFrame, stats: DataFrame, catalog: Catalog) -> DataFrame:
    """Foreign-key suggestions among unary ``pairs``: the referenced column is unique and has no NULL; best first for each dependent.

    Ranked by the share of the referenced values in use and the edit distance of the column names without their prefix.
    """
    s = stats.select("attr", "rows", "nulls", "distinct_values")
    dep = s.select(F.col("attr").alias("dep"), F.col("distinct_values").alias("dep_distinct"))
    ref = s.filter("rows > 0 and nulls = 0 and distinct_values = rows").select(F.col("attr").alias("ref"), F.col("distinct_values").alias("ref_distinct"))
    got = named(pairs.join(F.broadcast(dep), "dep").join(F.broadcast(ref), "ref"), catalog)
    bare = lambda c: F.regexp_replace(c, "^[a-z]+_", "")
    got = got.withColumn("name_distance", F.levenshtein(bare("dep_col"), bare("ref_col"))).withColumn("coverage", F.col("dep_distinct") / F.col("ref_distinct"))
    order = Window.partitionBy("dep").orderBy("name_distance", F.desc("coverage"), "ref")
    return got.withColumn("place", F.row_number().over(order)).select("dep_table", "dep_col", "ref_table", "ref_col", "name_distance", "coverage", "place")


def join_on(catalog: Catalog, dep_table: str, dep_cols: list[str], ref_table: str, ref_cols: list[str], how: str = "inner") -> DataFrame:
    """The two tables joined on a dependency; NULL meets NULL."""
    left, right = catalog.tables[dep_table].alias("dep"), catalog.tables[ref_table].alias("ref")
    on = [F.col(f"dep.`{d}`").cast("string").eqNullSafe(F.col(f"ref.`{r}`").cast("string")) if dict(left.dtypes)[d] != dict(right.dtypes)[r] else F.col(f"dep.`{d}`").eqNullSafe(F.col(f"ref.`{r}`")) for d, r in zip(dep_cols, ref_cols, strict=True)]
    return left.join(right, on, how)


def classes(pairs: DataFrame, n: int) -> DataFrame:
    """(attr, class_id): attributes that include each other have equal value sets; a class is named by its smallest attribute."""
    back = pairs.select(F.col("ref").alias("dep"), F.col("dep").alias("ref"))
    same = pairs.join(back, ["dep", "ref"]).groupBy("dep").agg(F.min("ref").alias("m"))
    every = pairs.sparkSession.range(n, numPartitions=1).select(F.col("id").cast("int").alias("dep"))
    return every.join(same, "dep", "left").select(F.col("dep").alias("attr"), F.least("dep", F.coalesce("m", "dep")).alias("class_id"))


def reduce_pairs(pairs: DataFrame, n: int) -> DataFrame:
    """(dep, ref) between classes, without those that follow from two others."""
    c = classes(pairs, n)
    between = pairs.join(F.broadcast(c.select(F.col("attr").alias("dep"), F.col("class_id").alias("d"))), "dep").join(F.broadcast(c.select(F.col("attr").alias("ref"), F.col("class_id").alias("r"))), "ref")
    between = between.filter("d <> r").select(F.col("d").alias("dep"), F.col("r").alias("ref")).distinct()
    two = between.join(between.select(F.col("dep").alias("ref"), F.col("ref").alias("far")), "ref").select("dep", F.col("far").alias("ref"))
    return between.join(two, ["dep", "ref"], "left_anti")
