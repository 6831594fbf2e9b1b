"""Helpers shared by the training-data operators: shared storage, lineage cuts, prefix sums and components."""

from __future__ import annotations

import gc
import os
import re
import tempfile
import uuid
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

WORD = r"[^\x20\x09-\x0D]+"
CHUNK = 1 << 16  # rows of an input file whose numbers are one file


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``. Only a session on one machine may leave it unset."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = "file://" + os.path.join(tempfile.gettempdir(), "incdep-shared")
    return root if "://" in root or root.startswith("file:") else "file://" + os.path.abspath(root)


def new_folder(spark: SparkSession, tag: str) -> str:
    """A fresh folder name below the shared root; nothing is created yet."""
    return f"{shared_root(spark).rstrip('/')}/{tag}-{uuid.uuid4().hex[:12]}"


@contextmanager
def settings(spark: SparkSession, values: dict[str, str]):
    """Spark's settings while a job is planned and run; the ones before hold again afterwards."""
    before = {name: spark.conf.get(name, None) for name in values}
    for name, value in values.items():
        spark.conf.set(name, value)
    try:
        yield
    finally:
        for name, value in before.items():
            spark.conf.unset(name) if value is None else spark.conf.set(name, value)


def small_batches(spark: SparkSession, rows: int = 1000, size: int = 8 << 20):
    """While a job is planned and run: at most ``rows`` rows and about ``size`` bytes in an Arrow batch, so that batches of long texts stay small.

    Elsewhere Spark's own bound on bytes holds (``spark.sql.execution.arrow.maxBytesPerBatch``, 64 MB unless set).
    """
    conf = spark._jsparkSession.sessionState().conf()
    bounds = {"spark.sql.execution.arrow.maxRecordsPerBatch": (rows, conf.arrowMaxRecordsPerBatch()), "spark.sql.execution.arrow.maxBytesPerBatch": (size, conf.arrowMaxBytesPerBatch())}
    return settings(spark, {name: str(min(most, now) if now > 0 else most) for name, (most, now) in bounds.items()})


def written(df: DataFrame, tag: str) -> DataFrame:
    """Cut lineage: write ``df`` as Parquet in the shared folder and read it back; the job's shuffle files go at its end."""
    spark = df.sparkSession
    out = new_folder(spark, tag)
    with small_batches(spark), settings(spark, {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}):
        df.write.parquet(out)
    back = spark.read.schema(df.schema).parquet(out)
    back.shared_folder = out
    return back


def with_row_key(df: DataFrame, name: str) -> DataFrame:
    """``df`` with a column that tells its rows apart, the same in every run: file and row number where it is read from files, else from a written copy."""
    try:
        place = df.metadataColumn("_metadata")
        return df.select("*", F.struct(F.xxhash64(place["file_path"]).alias("file"), place["row_index"].alias("row")).alias(name))
    except AnalysisException:
        return with_row_key(written(df, "keyed"), name)


def with_numbers(df: DataFrame, key: str, name: str, numbers: DataFrame) -> DataFrame:
    """``df`` with a column ``name``: for each row the number of ``numbers(key, name)``, from 0 to 255, or 0 if it has none there.

    ``key`` is from ``with_row_key``; no column of ``df`` may be named ``key`` and more. Numbers are laid out as they are read, a
    byte a row, in shared files of at most ``CHUNK`` rows of an input file; a task reads the bytes of its own rows. So only numbers
    are shuffled, not the rows, however wide they are. The broadcast has a row for each of those files.
    """
    file, chunk, path = (f"{key}_{x}" for x in ("file", "chunk", "path"))
    out = new_folder(df.sparkSession, "numbers")

    def lay(t: pa.Table) -> pa.Table:
        place = t.column("place").to_numpy()
        number = t.column("number").to_numpy()
        if number.min() < 0 or number.max() > 255:
            raise ValueError("numbers must be from 0 to 255")
        flat = np.zeros(place.max() + 1, "u1")
        flat[place] = number
        uri = f"{out}/{uuid.uuid4().hex}"
        write_file(uri, flat.tobytes())
        return pa.table([t.column(file)[:1], t.column(chunk)[:1], pa.chunked_array([[uri]])], names=[file, chunk, path])

    def look_up(uri: pa.Array, place: pa.Array) -> pa.Array:
        uri, at = uri.dictionary_encode(), place.to_numpy()
        got, which = np.zeros(len(at), "i8"), uri.indices.fill_null(-1).to_numpy()
        for k, own in ((k, np.flatnonzero(which == k)) for k in range(len(uri.dictionary))):
            least, most = int(at[own].min()), int(at[own].max())
            flat = np.frombuffer(read_file(uri.dictionary[k].as_py(), least, most + 1 - least), "u1")
            own = own[at[own] - least < len(flat)]
            got[own] = flat[at[own] - least]
        return pa.array(got)

    row = F.col(key)["row"]
    place = F.pmod(row, F.lit(CHUNK)).cast("long")
    where = [F.col(key)["file"].alias(file), F.floor(row / CHUNK).cast("long").alias(chunk)]
    rows = numbers.select(*where, place.alias("place"), F.col(name).cast("long").alias("number"))
    laid = written(rows.groupBy(file, chunk).applyInArrow(lay, f"`{file}` long, `{chunk}` long, `{path}` string"), "numbers-files")
    found = df.select("*", *where).join(F.broadcast(laid), [file, chunk], "left")
    number = F.arrow_udf(look_up, "long").asNondeterministic()  # so that no step is moved below it with a call of its own
    return found.select(*df.columns, number(F.col(path), place).alias(name))


def discard(*tables: DataFrame) -> None:
    """Delete tables that ``written`` made and nothing reads any more, and let Spark drop finished shuffles' files."""
    for df in tables:
        jvm, out = df.sparkSession._jvm, df.shared_folder
        path = jvm.org.apache.hadoop.fs.Path(out)
        path.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def release(spark: SparkSession) -> None:
    """Collect dropped DataFrames on the driver; Spark's cleaner then removes the shuffle files that only they held."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def filesystem(uri: str) -> tuple[pafs.FileSystem, str]:
    """Filesystem and path of a shared URI, on the driver or on an executor."""
    return pafs.FileSystem.from_uri(uri)


def write_file(uri: str, *chunks: bytes) -> int:
    """Write a whole file under a name of its own; readers learn names from committed manifests only, so what a lost or repeated task attempt leaves behind is never read."""
    fs, path = filesystem(uri)
    fs.create_dir(path.rpartition("/")[0], recursive=True)
    with fs.open_output_stream(path) as out:
        for chunk in chunks:
            out.write(chunk)
    return sum(map(len, chunks))


def read_file(uri: str, offset: int = 0, length: int | None = None) -> bytes:
    fs, path = filesystem(uri)
    with fs.open_input_file(path) as f:
        size = f.size()
        end = size if length is None else min(size, offset + length)
        return f.read_at(max(0, end - offset), offset) if offset < size else b""


def mapped(uri: str, dtype: str):
    """The file as a NumPy array: memory-mapped where it is local, read whole elsewhere."""
    fs, path = filesystem(uri)
    if isinstance(fs, pafs.LocalFileSystem):
        return np.memmap(path, dtype=dtype, mode="r") if os.path.getsize(path) else np.empty(0, dtype)
    return np.frombuffer(read_file(uri), dtype)


def running_total(df: DataFrame, group: list[str], order: list[str], value: str, out: str, tag: str) -> DataFrame:
    """Inclusive running sum of ``value`` inside ``group`` by ``order``, for groups of any size.

    Rows are range-partitioned by (group, order), written, and summed inside each partition; totals of the
    partitions before are added from a table with one row per (group, partition). A hot group spans many
    partitions. ``group`` columns must be free of nulls.
    """
    laid = df.repartitionByRange(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), *group, *order)
    laid = written(laid.withColumn("_part", F.spark_partition_id()), tag)
    before = Window.partitionBy(*group).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    bases = laid.groupBy(*group, "_part").agg(F.sum(value).alias("_sum")).withColumn("_base", F.coalesce(F.sum("_sum").over(before), F.lit(0))).drop("_sum")
    inside = Window.partitionBy(*group, "_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return laid.withColumn(out, F.sum(value).over(inside)).join(bases, [*group, "_part"]).withColumn(out, F.col(out) + F.col("_base")).drop("_part", "_base")


def components(edges: DataFrame, rounds: int = 40) -> DataFrame:
    """Connected components of ``edges(a, b)`` as (node, component): the smallest node reachable.

    Alternating star contraction. Each half round is an aggregation with map-side combine and an equi-join on
    plain rows, so a hub with very many neighbours is never gathered into one value. Lineage is cut in every
    round by a written table. Self loops are allowed and keep a node in the answer.
    """
    spark = edges.sparkSession
    hi, lo = F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")
    now = written(edges.select(hi, lo).distinct(), "cc")

    def mark(df: DataFrame):
        return df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()

    seen = mark(now)
    for _ in range(rounds):
        real = now.filter("a <> b")
        both = real.unionByName(real.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.unionByName(now.filter("a = b")).distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a")
        small = small.select("a", F.col("m").alias("b")).unionByName(small.select(F.col("b").alias("a"), F.col("m").alias("b")))
        now, old = written(small.select(hi, lo).distinct(), "cc"), now
        discard(old)
        if (then := mark(now)) == seen:
            break
        seen = then
    else:
        raise RuntimeError("components did not settle")
    nodes = now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component")))
    return nodes.groupBy("node").agg(F.min("component").alias("component"))


def may_match(df: DataFrame, key: str, keys: DataFrame, bits: int = 1 << 22) -> DataFrame:
    """``df`` with a boolean column ``_may``: false means that ``key`` is surely not among ``keys`` (one column of that name).

    The broadcast is a bit table of fixed size (``bits`` / 64 rows at most), however many keys there are; a full table only
    stops helping. Null keys are never marked.
    """
    place = F.pmod(F.xxhash64(key), F.lit(bits))
    word, bit = (place / 64).cast("int"), (place % 64).cast("int")
    words = keys.filter(F.col(key).isNotNull()).select(word.alias("_word"), F.call_function("shiftleft", F.lit(1).cast("long"), bit).alias("_bit"))
    words = words.groupBy("_word").agg(F.bit_or("_bit").alias("_bits"))
    hit = F.call_function("getbit", F.coalesce("_bits", F.lit(0).cast("long")), bit) == 1
    return df.withColumn("_word", word).join(F.broadcast(words), "_word", "left").withColumn("_may", hit & F.col(key).isNotNull()).drop("_word", "_bits")


def without(df: DataFrame, key: str, keys: DataFrame) -> DataFrame:
    """Rows of ``df`` whose ``key`` is not among ``keys``; only rows that the bit table can't clear are shuffled."""
    marked = may_match(df, key, keys)
    clear = marked.filter(~F.col("_may")).drop("_may")
    return clear.unionByName(marked.filter("_may").drop("_may").join(keys.select(key).distinct(), key, "left_anti"))
