"""The input of discovery: named tables and their numbered attributes."""

from __future__ import annotations

import re
from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

CORE = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")
EXTRA = ("events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def type_class(dtype: T.DataType) -> str:
    """integer, fractional, boolean, timestamp, binary or string."""
    if isinstance(dtype, T.IntegralType):
        return "integer"
    if isinstance(dtype, (T.FractionalType, T.DecimalType)):
        return "fractional"
    if isinstance(dtype, T.BooleanType):
        return "boolean"
    if isinstance(dtype, (T.DateType, T.TimestampType, T.TimestampNTZType)):
        return "timestamp"
    return "binary" if isinstance(dtype, T.BinaryType) else "string"


def is_nested(dtype: T.DataType) -> bool:
    return isinstance(dtype, (T.ArrayType, T.MapType, T.StructType)) or dtype.typeName() == "variant"


@dataclass(frozen=True)
class Attribute:
    id: int
    table: str
    column: str
    type_class: str


@dataclass
class Catalog:
    """Tables by name. Attributes are numbered over sorted table names and column positions.

    Nested columns are left out (``nested="skip"``), turned into JSON text (``"json"``) or, for arrays of atomic values,
    replaced by one attribute of their elements (``"explode"``), which takes part in unary dependencies only. Binary values count as
    their hexadecimal text.
    """

    tables: dict[str, DataFrame]
    nested: str = "skip"
    attributes: list[Attribute] = field(init=False)

    def __post_init__(self) -> None:
        if self.nested not in ("skip", "json", "explode"):
            raise ValueError(f"nested={self.nested!r}")
        self.element_columns: set[tuple[str, str]] = set()
        self.attributes = []
        for name in sorted(self.tables):
            df = self.tables[name]
            for f in df.schema.fields:
                kind = f.dataType
                if is_nested(kind):
                    if self.nested == "skip":
                        continue
                    if self.nested == "explode" and isinstance(kind, T.ArrayType) and not is_nested(kind.elementType):
                        self.element_columns.add((name, f.name))
                        kind = kind.elementType
                    else:
                        df = df.withColumn(f.name, F.to_json(F.col(f"`{f.name}`")))
                        kind = T.StringType()
                elif isinstance(kind, T.BinaryType):
                    df = df.withColumn(f.name, F.hex(F.col(f"`{f.name}`")))
                if isinstance(kind, T.BinaryType) and (name, f.name) in self.element_columns:
                    df = df.withColumn(f.name, F.transform(F.col(f"`{f.name}`"), F.hex))
                self.attributes.append(Attribute(len(self.attributes), name, f.name, type_class(kind)))
            self.tables[name] = df

    @classmethod
    def from_dir(cls, spark: SparkSession, path: str, names: Iterable[str] | None = None, fmt: str = "parquet", nested: str = "skip", **options: str) -> Catalog:
        """``path``/name.``fmt`` for each name."""
        reader = spark.read.format(fmt).options(**options)
        return cls({n: reader.load(f"{path}/{n}.{fmt}") for n in (names or CORE + EXTRA)}, nested)

    def of(self, table: str) -> list[Attribute]:
        return [a for a in self.attributes if a.table == table]

    @property
    def element_ids(self) -> list[int]:
        """Attributes of array elements: they have no row in common with other columns."""
        return [a.id for a in self.attributes if (a.table, a.column) in self.element_columns]

    def find(self, table: str, column: str) -> Attribute:
        return next(a for a in self.attributes if (a.table, a.column) == (table, column))

    def select(self, include: str | None = None, exclude: str | None = None) -> Catalog:
        """Only attributes whose ``table.column`` matches ``include`` and not ``exclude`` (regular expressions)."""
        keep = {t: [a.column for a in self.of(t) if (include is None or re.search(include, f"{t}.{a.column}")) and not (exclude and re.search(exclude, f"{t}.{a.column}"))] for t in self.tables}
        return Catalog({t: self.tables[t].select(*(F.col(f"`{c}`") for c in cols)) for t, cols in keep.items() if cols}, self.nested)

    def where(self, **conditions: str) -> Catalog:
        """Row conditions by table name."""
        return Catalog({t: df.where(conditions[t]) if t in conditions else df for t, df in self.tables.items()}, self.nested)

    def dictionary(self, spark: SparkSession) -> DataFrame:
        """(attr, table_name, column_name, type_class): one row an attribute."""
        return spark.createDataFrame([(a.id, a.table, a.column, a.type_class) for a in self.attributes], "attr int, table_name string, column_name string, type_class string")

    @property
    def spark(self) -> SparkSession:
        return next(iter(self.tables.values())).sparkSession
