"""The relation of attributes and values, and its statistics."""

from __future__ import annotations

from collections.abc import Collection
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..catalog import Attribute, Catalog
from ..functions import fingerprint_sql, folded, quoted, token_sql
from ..plans import written

COMBOS_AT_ONCE = 32  # combinations that one pass over a table's hashes computes, so that its generated code stays small


def column_cells(catalog: Catalog, a: Attribute, nulls: str = "equal", compact: bool = True) -> DataFrame:
    """(attr, v) of one attribute with repeats: a narrow scan of its table; an array's elements are its values."""
    df, x = catalog.tables[a.table], quoted(a.column)
    if (a.table, a.column) in catalog.element_columns:
        df, x = df.selectExpr(f"explode({x}) as e"), "e"
    cells = df.selectExpr(f"{a.id} as attr", f"{token_sql(x, nulls, compact)} as v")
    return cells.filter("v is not null") if nulls == "ignore" else cells


def plain_attributes(catalog: Catalog, table: str) -> list[Attribute]:
    """The table's attributes that are columns, not array elements."""
    return [a for a in catalog.of(table) if (table, a.column) not in catalog.element_columns]


def token_table(catalog: Catalog, table: str, nulls: str = "equal", compact: bool = True) -> DataFrame:
    """A column a<attr> of tokens for each plain attribute, in row order."""
    return catalog.tables[table].selectExpr(*(f"{token_sql(quoted(a.column), nulls, compact)} as a{a.id}" for a in plain_attributes(catalog, table)))


def table_cells(catalog: Catalog, table: str, nulls: str = "equal", compact: bool = True) -> DataFrame:
    """(attr int, v string) of one table with repeats."""
    parts = [column_cells(catalog, a, nulls, compact) for a in catalog.of(table) if (table, a.column) in catalog.element_columns]
    if plain_attributes(catalog, table):
        wide = token_table(catalog, table, nulls, compact)
        parts.append(wide.unpivot([], wide.columns, "attr", "v").select(F.substring("attr", 2, 9).cast("int").alias("attr"), "v"))
    cells = reduce(DataFrame.unionByName, parts)
    return cells.filter("v is not null") if nulls == "ignore" else cells


def unpivot_all(catalog: Catalog, nulls: str = "equal", compact: bool = True) -> DataFrame:
    """(attr int, v string) with repeats: one scan of each table, one row a cell; nothing is shuffled."""
    return reduce(DataFrame.unionByName, [table_cells(catalog, t, nulls, compact) for t in catalog.tables if catalog.of(t)])


def hashed_columns(catalog: Catalog, nulls: str = "equal", needed: Collection[int] | None = None) -> dict[str, DataFrame]:
    """Per table two independent 64-bit hashes g<attr> and h<attr> of each column, written once for all levels; array elements have none.

    ``needed`` has the attributes that combinations use; other columns, and tables without any, are left out.
    """
    out = {}
    for name, df in catalog.tables.items():
        toks = {a.id: token_sql(quoted(a.column), nulls, compact=False) for a in plain_attributes(catalog, name) if needed is None or a.id in needed}
        cols = [f"{fingerprint_sql(t, seed=seed)} as {n}{a}" for a, t in toks.items() for n, seed in (("g", None), ("h", 1))]
        if cols:
            out[name] = written(df.selectExpr(*cols), "hashed")
    return out


def unpivot_combos(hashed: dict[str, DataFrame], catalog: Catalog, combos: list[tuple[int, ...]]) -> DataFrame:
    """(attr, v) of column combinations, numbered by their place in ``combos``; each is within one table.

    v is the tuple as two independent 64-bit hashes, each combined from its values' hashes: 16 bytes a cell,
    whatever the columns hold. Among n distinct tuples two share both with a probability of about n^2 / 2^129.
    """
    by_id = {a.id: a for a in catalog.attributes}
    parts = []
    for name, df in hashed.items():
        every = [(k, c) for k, c in enumerate(combos) if by_id[c[0]].table == name]
        for at in range(0, len(every), COMBOS_AT_ONCE):
            mine = every[at : at + COMBOS_AT_ONCE]
            pairs = [tuple(f"{n}{a}" for a in c) for _, c in mine for n in "gh"]
            wide, names = folded(df.select(*sorted({c for p in pairs for c in p})), pairs)
            cells = ", ".join(f"named_struct('attr', {k}, 'g', {g}, 'h', {h})" for (k, _), g, h in zip(mine, names[::2], names[1::2], strict=True))
            parts.append(wide.selectExpr(f"explode(array({cells})) as c").select("c.attr", "c.g", "c.h"))
    return reduce(DataFrame.unionByName, parts).filter("g is not null").select("attr", F.struct("g", "h").alias("v"))


def attr_stats(catalog: Catalog) -> DataFrame:
    """(attr, rows, nulls, distinct_values, min_v, max_v): NULL counts as a value of its own; bounds are of tokens, in text order.

    Cells are counted by (attr, v) first, so the second step sees each distinct value once and hot values are combined map-side.
    """
    counted = unpivot_all(catalog).groupBy("attr", "v").agg(F.count(F.lit(1)).alias("n"))
    got = counted.groupBy("attr").agg(
        F.sum("n").alias("rows"),
        F.sum(F.when(F.col("v") == "n", F.col("n")).otherwise(0)).alias("nulls"),
        F.count(F.lit(1)).alias("distinct_values"),
        F.min("v").alias("min_v"),
        F.max("v").alias("max_v"),
    )
    zero = F.lit(0).cast("long")
    every = catalog.dictionary(catalog.spark).select("attr").join(got, "attr", "left")
    return every.withColumns({c: F.coalesce(c, zero) for c in ("rows", "nulls", "distinct_values")})
