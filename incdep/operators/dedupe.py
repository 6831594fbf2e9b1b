"""Preprocessing of the exact method: each attribute's values without repeats, by the variants that are compared.

All return (attr, v) with distinct rows; they differ in where repeats die and in what is sorted.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..catalog import Catalog
from ..functions import quoted, token_sql
from .attr_values import column_cells, plain_attributes, token_table, unpivot_all

SCHEMA = "attr int, v string"
KINDS = ("column_scan", "set", "sort", "view", "pair", "chunked", "set_single", "auto")


def column_scan(catalog: Catalog, nulls: str = "equal") -> DataFrame:
    """One scan for each column, as the baseline profiler does: narrow reads, many of them."""
    return reduce(DataFrame.unionByName, [column_cells(catalog, a, nulls).distinct() for a in catalog.attributes])


def as_set(catalog: Catalog, nulls: str = "equal") -> DataFrame:
    """One scan of each table; repeats die in the partial aggregation, before the shuffle."""
    return unpivot_all(catalog, nulls).distinct()


def column_tables(catalog: Catalog, nulls: str = "equal") -> list[DataFrame]:
    """Tokens in columns a<attr> as they are stored, nothing unpivoted: a table's plain attributes together, array elements each alone."""
    tables = [token_table(catalog, t, nulls) for t in catalog.tables if plain_attributes(catalog, t)]
    return tables + [column_cells(catalog, a, nulls).select(F.col("v").alias(f"a{a.id}")) for a in catalog.attributes if a.id in catalog.element_ids]


def raw_tables(catalog: Catalog) -> list[tuple[DataFrame, dict[str, str]]]:
    """Columns a<attr> as numbers where that is exact, else as text, by table, and which of them are integers, dates (days) or doubles; array elements each alone."""

    def raw(df: DataFrame, x: str, a: int) -> tuple[str, str]:
        kind = df.select(F.expr(x).alias("x")).schema[0].dataType
        if isinstance(kind, T.IntegralType):
            return f"cast({x} as bigint) as a{a}", "integer"
        if isinstance(kind, T.DateType):
            return f"cast(unix_date({x}) as bigint) as a{a}", "date"
        return (f"{x} as a{a}", "double") if isinstance(kind, T.DoubleType) else (f"cast({x} as string) as a{a}", "text")

    out = []
    for t, df in catalog.tables.items():
        if plain := plain_attributes(catalog, t):
            cols = {f"a{a.id}": raw(df, quoted(a.column), a.id) for a in plain}
            out.append((df.selectExpr(*(c for c, _ in cols.values())), {n: k for n, (_, k) in cols.items()}))
    for a in catalog.attributes:
        if a.id in catalog.element_ids:
            df = catalog.tables[a.table].selectExpr(f"explode({quoted(a.column)}) as e")
            cell, kind = raw(df, "e", a.id)
            out.append((df.selectExpr(cell), {f"a{a.id}": kind}))
    return out


def as_set_single(catalog: Catalog, nulls: str = "equal", limit_bytes: int = 64 << 20) -> DataFrame:
    """The set variant outside the JVM: values die on insertion, and all sets of a task are flushed together, sorted, whenever they hold ``limit_bytes``.

    A task is a part of a table, so its sets are filled by one thread; a column's values are inserted a batch at a time, numbers as they are stored (doubles
    by their bits). The flushed runs get the canonical text, once a value that is left, and are merged by an aggregation.
    """

    def filler(kinds: dict[str, str]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
        stored = {"integer": pa.int64(), "date": pa.int64(), "double": pa.float64(), "text": pa.large_string()}

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seen: dict[str, list[pa.Array]] = {}  # a column's set, and values that came since, which may repeat it

            def flush() -> Iterator[pa.RecordBatch]:
                for name, parts in seen.items():
                    values = pc.unique(pa.chunked_array(parts))
                    values = values.take(pc.array_sort_indices(values))
                    if kinds[name] == "double":
                        values = values.view(pa.float64())
                    for at in range(0, len(values), 50_000):
                        some = values.slice(at, 50_000).cast(pa.string())
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), int(name[1:]), "i4")), some], names=["attr", "v"])

            for b in batches:
                for name, column in zip(b.schema.names, b.columns, strict=True):
                    parts = seen.setdefault(name, [])
                    column = column.cast(stored[kinds[name]])
                    column = column.view(pa.int64()) if kinds[name] == "double" else column
                    parts.append(pc.unique(column.drop_null() if nulls == "ignore" else column))
                    if len(parts) > 1 and sum(p.nbytes for p in parts[1:]) > max(parts[0].nbytes, 1 << 18):
                        seen[name] = [pc.unique(pa.chunked_array(parts))]
                if sum(p.nbytes for parts in seen.values() for p in parts) >= limit_bytes:
                    yield from flush()
                    seen = {}
            yield from flush()

        return run

    tables = raw_tables(catalog)
    of = {kind: [int(n[1:]) for _, kinds in tables for n, k in kinds.items() if k == kind] for kind in ("date", "double")}
    text = F.col("v")
    if of["date"]:
        text = F.when(F.col("attr").isin(of["date"]), F.expr("cast(date_from_unix_date(try_cast(v as int)) as string)")).otherwise(text)
    if of["double"]:
        text = F.when(F.col("attr").isin(of["double"]), F.expr("cast(try_cast(v as double) as string)")).otherwise(text)
    left = reduce(DataFrame.unionByName, [t.mapInArrow(filler(kinds), SCHEMA) for t, kinds in tables])
    return left.select("attr", text.alias("t")).selectExpr("attr", f"{token_sql('t', nulls)} as v").distinct()


def _neighbours(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Drop rows that repeat the one before, in a sorted stream."""
    last: tuple | None = None
    for b in batches:
        if not b.num_rows:
            continue
        a, v = b.column(0), b.column(1)
        new = pc.or_(pc.not_equal(a.slice(1), a.slice(0, len(a) - 1)), pc.not_equal(v.slice(1), v.slice(0, len(v) - 1)))
        first = (a[0].as_py(), v[0].as_py()) != last
        last = (a[-1].as_py(), v[-1].as_py())
        yield b.filter(pa.concat_arrays([pa.array([first]), new]))


def by_sort(catalog: Catalog, nulls: str = "equal") -> DataFrame:
    """All values are kept, range-sorted by (attribute, value), and neighbours that repeat are dropped; a column spans many partitions."""
    laid = unpivot_all(catalog, nulls).repartitionByRange("attr", "v").sortWithinPartitions("attr", "v")
    return laid.mapInArrow(_neighbours, SCHEMA)


def by_reference(catalog: Catalog, wide: bool, chunk_bytes: int = 64 << 20, nulls: str = "equal") -> DataFrame:
    """Sort references to each column's values inside parts of rows and emit a part's distinct values; the parts are merged by an aggregation.

    ``wide`` refers by 64-bit offsets; else by 32-bit ones, which takes less memory and caps a part at 2 GiB. Columns come as they
    are stored, one array each: nothing is unpivoted, and only distinct values leave the task.
    """
    kind = pa.large_string() if wide else pa.string()
    cap = chunk_bytes if wide else min(chunk_bytes, (1 << 31) - 1)

    def parts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        size = 0

        def flush() -> Iterator[pa.RecordBatch]:
            for k, name in enumerate(held[0].schema.names):
                column = pa.chunked_array([b.column(k) for b in held]).cast(kind).combine_chunks().drop_null()
                column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
                done = column.take(pc.array_sort_indices(column))
                if len(done):
                    done = done.filter(pa.concat_arrays([pa.array([True]), pc.not_equal(done.slice(1), done.slice(0, len(done) - 1))]))
                for at in range(0, len(done), 50_000):
                    some = done.slice(at, 50_000).cast(pa.string())
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), int(name[1:]), "i4")), some], names=["attr", "v"])

        for b in batches:
            if b.num_rows:
                held.append(b)
                size += b.nbytes
            if size >= cap // 2:  # the rest of the part's memory is for the sorted copy
                yield from flush()
                held, size = [], 0
        if held:
            yield from flush()

    return reduce(DataFrame.unionByName, [t.mapInArrow(parts, SCHEMA) for t in column_tables(catalog, nulls)]).distinct()


def distinct_values(catalog: Catalog, kind: str = "set", chunk_bytes: int = 64 << 20, nulls: str = "equal") -> DataFrame:
    """(attr, v) by the named variant; ``auto`` takes 32-bit references while a part fits their cap, 64-bit ones beyond."""
    if kind == "column_scan":
        return column_scan(catalog, nulls)
    if kind == "set":
        return as_set(catalog, nulls)
    if kind == "set_single":
        return as_set_single(catalog, nulls, chunk_bytes)
    if kind == "sort":
        return by_sort(catalog, nulls)
    if kind in ("view", "pair", "chunked"):
        return by_reference(catalog, kind == "view", min(chunk_bytes, 1 << 20) if kind == "chunked" else chunk_bytes, nulls)
    if kind == "auto":
        return by_reference(catalog, chunk_bytes >= 1 << 31, chunk_bytes, nulls)
    raise ValueError(f"kind={kind!r}")


def summary(values: DataFrame) -> DataFrame:
    """(attr, distinct_values, min_v, max_v) of a deduplicated relation."""
    return values.groupBy("attr").agg(F.count(F.lit(1)).alias("distinct_values"), F.min("v").alias("min_v"), F.max("v").alias("max_v"))
