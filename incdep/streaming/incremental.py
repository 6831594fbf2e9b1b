"""Incremental discovery on a stream: the state, the distinct (attr, v), merges by union, so batches may come in any order, late or twice."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..catalog import Catalog
from ..operators.attr_values import table_cells
from ..operators.exact import bitset
from ..plans import delete, new_folder

STATE = "attr int, v string, source string"


class IncrementalInds:
    """Keeps the distinct (attr, v) of each batch in a folder of its own below ``root``, next to the streams' checkpoints.

    A batch's folder is named by its table and number and is overwritten if the batch comes again, so repeats change nothing, and a
    restarted program that is given the same ``root`` goes on where the last one ended: nothing is kept in the driver. A batch writes its own values
    only; ``compact`` merges what has gathered. Validity isn't monotone: a new dependent value breaks a dependency, a new referenced
    value may mend it, so ``inds`` is always taken from the whole state.
    """

    def __init__(self, catalog: Catalog, static: tuple[str, ...] = (), root: str | None = None):
        """``catalog`` has all tables' schemas; those in ``static`` are read once, the others come in batches."""
        self.catalog, self.spark = catalog, catalog.spark
        self.root = (root or new_folder(self.spark, "stream")).rstrip("/")
        for t in static:
            self._write(table_cells(catalog, t), f"static-{t}")

    def _write(self, cells: DataFrame, source: str) -> None:
        cells.distinct().write.mode("overwrite").parquet(f"{self.root}/state/source={source}")

    def _sources(self) -> list[str]:
        jvm = self.spark._jvm
        where = jvm.org.apache.hadoop.fs.Path(f"{self.root}/state")
        fs = where.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf())
        return sorted(s.getPath().getName().partition("=")[2] for s in fs.listStatus(where)) if fs.exists(where) else []

    @property
    def state(self) -> DataFrame:
        """(attr, v), with repeats between batches."""
        if not self._sources():
            return self.spark.createDataFrame([], STATE).drop("source")
        return self.spark.read.schema(STATE).parquet(f"{self.root}/state").drop("source")

    def add(self, table: str, rows: DataFrame, batch: int | None = None) -> None:
        """Merge rows of a table; a batch number that comes again takes the place of the first."""
        cells = table_cells(Catalog({table: rows}, self.catalog.nested), table)
        cells = cells.select((F.col("attr") + self.catalog.of(table)[0].id).cast("int").alias("attr"), "v")
        self._write(cells, f"{table}-{uuid.uuid4().hex if batch is None else batch}")

    def compact(self, table: str) -> None:
        """Merge all batches of a table into one folder; only when none of them will come again, as after a stream has ended."""
        mine = [s for s in self._sources() if s.startswith(f"{table}-")]
        if len(mine) > 1:
            whole = f"{table}-all-{uuid.uuid4().hex}"
            self._write(self.spark.read.schema("attr int, v string").parquet(*(f"{self.root}/state/source={s}" for s in mine)), whole)
            for s in mine:  # a folder that is left behind by a crash here only repeats what the merged one has
                delete(self.spark, f"{self.root}/state/source={s}")

    def inds(self) -> DataFrame:
        """(dep, ref) of the state."""
        return bitset(self.state, len(self.catalog.attributes))

    def follow(self, table: str, stream: DataFrame) -> StreamingQuery:
        """Run over all that ``stream`` has now; its checkpoint is below the same root as the state."""
        return stream.writeStream.foreachBatch(lambda df, k: self.add(table, df, k)).option("checkpointLocation", f"{self.root}/checkpoint-{table}").trigger(availableNow=True).start()


def windowed_distinct(stream: DataFrame, time: str, column: str, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """(start, value_count, values_seen): approximate distinct values of a column in tumbling windows; rows later than ``late`` are dropped."""
    seen = stream.withColumn("_t", F.col(time).cast("timestamp")).withWatermark("_t", late).groupBy(F.window("_t", width))
    return seen.agg(F.count(column).alias("value_count"), F.hll_sketch_agg(F.xxhash64(F.col(column).cast("string")), 12).alias("s")).select(F.col("window.start").alias("start"), "value_count", F.hll_sketch_estimate("s").alias("values_seen"))
