"""Data sets and experiments: deterministic projections of the given tables that stand for the traits compared."""

from __future__ import annotations

import contextlib
import os
import threading
import time
from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .catalog import CORE, Catalog
from .discover import levels, levels_of
from .operators import attr_values, candidates, dedupe, exact, lattice, sketch
from .plans import Phases, new_folder, written

HIGH_ARITY = ("l_orderkey", "l_suppkey", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_shipdate")
BRAND = "Brand#19"
PROSE = ("documents", "pages", "conversations", "benchmark", "labels")
DECLARED = (
    ("orders", ("o_custkey",), "customer", ("c_custkey",)),
    ("lineitem", ("l_orderkey",), "orders", ("o_orderkey",)),
    ("lineitem", ("l_partkey",), "part", ("p_partkey",)),
    ("lineitem", ("l_suppkey",), "supplier", ("s_suppkey",)),
    ("customer", ("c_nationkey",), "nation", ("n_nationkey",)),
    ("supplier", ("s_nationkey",), "nation", ("n_nationkey",)),
    ("nation", ("n_regionkey",), "region", ("r_regionkey",)),
    ("orders", ("o_orderkey",), "lineitem", ("l_orderkey",)),
    ("lineitem", ("l_shipdate",), "orders", ("o_orderdate",)),
    ("lineitem", ("l_linenumber", "l_linestatus"), "orders", ("o_custkey", "o_orderstatus")),
)


def core(spark: SparkSession, sf_dir: str) -> Catalog:
    """The seven star-schema tables."""
    return Catalog.from_dir(spark, sf_dir, CORE)


def everything(spark: SparkSession, sf_dir: str) -> Catalog:
    """All fourteen tables."""
    return Catalog.from_dir(spark, sf_dir)


def worked_example(spark: SparkSession, sf_dir: str) -> Catalog:
    """People with a licence number that some share, and the licences that anyone has: orders and their customers."""
    orders, customer = spark.read.parquet(f"{sf_dir}/orders.parquet"), spark.read.parquet(f"{sf_dir}/customer.parquet")
    people = orders.select(F.concat(F.lit("P"), F.col("o_orderkey").cast("string")).alias("uid"), F.col("o_orderpriority").alias("name"), F.col("o_custkey").alias("dln"))
    licences = customer.select(F.col("c_custkey").alias("dlid"), F.col("c_mktsegment").alias("country")).join(people, F.col("dlid") == F.col("dln"), "left_semi")
    return Catalog({"people": people, "licences": licences})


def high_arity(spark: SparkSession, sf_dir: str) -> Catalog:
    """Seven columns of the line items of one brand's parts, and of all line items under other names: one dependency of arity seven with all its projections."""
    items, part = spark.read.parquet(f"{sf_dir}/lineitem.parquet"), spark.read.parquet(f"{sf_dir}/part.parquet")
    dep = items.join(part, F.col("l_partkey") == F.col("p_partkey")).filter(F.col("p_brand") == BRAND)
    return Catalog({"dep": dep.select(*HIGH_ARITY), "ref": items.select(*(F.col(c).alias(n) for c, n in zip(HIGH_ARITY, "osedtfh", strict=True)))})


def sparse(spark: SparkSession, sf_dir: str) -> Catalog:
    """Two views of orders with many NULLs."""
    o = spark.read.parquet(f"{sf_dir}/orders.parquet")
    k, null = F.col("o_orderkey"), F.lit(None).cast("string")
    a = o.select(k.alias("k"), F.when(k % 3 == 0, F.col("o_custkey")).alias("c"), F.when(k % 5 == 0, F.col("o_orderstatus")).alias("s"), F.when(k % 7 == 0, F.col("o_orderpriority")).alias("p"), null.alias("z"))
    b = o.select(k.alias("k2"), F.when(k % 2 == 0, F.col("o_custkey")).alias("c2"), F.col("o_orderstatus").alias("s2"), F.when(k % 2 == 0, F.col("o_orderpriority")).alias("p2"), F.when(k % 11 == 0, F.col("o_orderstatus")).alias("z2"))
    return Catalog({"a": a, "b": b})


def wide(spark: SparkSession, sf_dir: str, width: int = 64) -> Catalog:
    """One table of ``width`` residues: column j is included in column k exactly if j <= k."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    return Catalog({"residues": e.select(*((F.col("event_id") % (2 + j)).alias(f"m{j:03d}") for j in range(width)))})


def prose(spark: SparkSession, sf_dir: str) -> Catalog:
    """Tables with long strings."""
    return Catalog.from_dir(spark, sf_dir, PROSE)


DATASETS: dict[str, Callable[[SparkSession, str], Catalog]] = {"core": core, "all": everything, "high_arity": high_arity, "sparse": sparse, "wide": wide, "prose": prose}


def wide_all(spark: SparkSession, sf_dir: str) -> Catalog:
    """As many columns as the widest data set of the comparison has."""
    return wide(spark, sf_dir, 259)


def level_counts(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("core", "sparse", "high_arity")) -> DataFrame:
    """(dataset, arity, candidates, valid): how many candidates each lattice level has and how many of them hold."""
    found = levels_of({n: DATASETS[n](spark, sf_dir) for n in names})
    rows = [(n, c["arity"], c["candidates"], c.get("valid")) for n in names for c in found[n][0]]
    return spark.createDataFrame(rows, "dataset string, arity int, candidates long, valid long")


def explosion_guard(spark: SparkSession, sf_dir: str, width: int = 32, max_candidates: int = 50_000) -> DataFrame:
    """(arity, candidates, valid): the levels of ``wide``, whose candidates grow with the fourth power of its columns, up to the level that is refused."""
    counts, _ = levels(wide(spark, sf_dir, width), None, max_candidates)
    return spark.createDataFrame([(c["arity"], c["candidates"], c.get("valid")) for c in counts], "arity int, candidates long, valid long")


def index_lookups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(table_name, combos, row_count, lookups) of the unary level of the core tables."""
    catalog = core(spark, sf_dir)
    return sketch.lookups(sketch.hash_tables(catalog), [(a.id,) for a in catalog.attributes], catalog)


class PeakMemory:
    """Largest resident MB of the JVM and of all Python workers below it while a block runs, sampled; for a session on one machine."""

    def __init__(self, spark: SparkSession, every: float = 0.05):
        self.top, self.every = int(spark._jvm.java.lang.ProcessHandle.current().pid()), every
        self.jvm_mb = self.python_mb = 0.0

    def _sample(self) -> None:
        parents, rss = {}, {}
        for p in filter(str.isdigit, os.listdir("/proc")):
            with contextlib.suppress(OSError, IndexError):
                with open(f"/proc/{p}/stat") as f:
                    fields = f.read().rpartition(")")[2].split()
                parents[int(p)], rss[int(p)] = int(fields[1]), int(fields[21]) * os.sysconf("SC_PAGE_SIZE") / 1e6
        below, more = set(), {self.top}
        while more := {p for p, up in parents.items() if up in more} - below:
            below |= more
        self.jvm_mb = max(self.jvm_mb, rss.get(self.top, 0.0))
        self.python_mb = max(self.python_mb, sum(rss[p] for p in below))

    def __enter__(self) -> PeakMemory:
        self._stop = threading.Event()

        def run() -> None:
            while not self._stop.wait(self.every):
                self._sample()

        self._thread = threading.Thread(target=run, daemon=True)
        self._thread.start()
        return self

    def __exit__(self, *_: object) -> None:
        self._stop.set()
        self._thread.join()
        self._sample()


def measured(run: Callable[[], DataFrame], repeat: int = 5) -> dict[str, float]:
    """Mean and least seconds of ``repeat`` runs with Spark's own caches cleared before each (the system's file cache stays), and peak memory."""
    took, jvm, python = [], 0.0, 0.0
    for _ in range(repeat):
        df = run()
        df.sparkSession.catalog.clearCache()
        df.sparkSession.sparkContext._jvm.System.gc()
        with PeakMemory(df.sparkSession) as peak:
            began = time.perf_counter()
            run().write.format("noop").mode("overwrite").save()
            took.append(time.perf_counter() - began)
        jvm, python = max(jvm, peak.jvm_mb), max(python, peak.python_mb)
    return {"mean_s": round(sum(took) / len(took), 3), "min_s": round(min(took), 3), "jvm_mb": round(jvm), "python_mb": round(python)}


def speedups(rows: list[dict], variant: str, baseline: str, seconds: str = "mean_s") -> list[dict]:
    """Each row's speedup over its data set's ``baseline``; then, for each variant, the mean of the ratios and the ratio of the means."""
    base = {r["dataset"]: r[seconds] for r in rows if r[variant] == baseline}
    out = [r | {f"{seconds[:-2]}_speedup": round(base[r["dataset"]] / r[seconds], 2)} for r in rows]
    for v in dict.fromkeys(r[variant] for r in rows):
        mine = [r for r in out if r[variant] == v]
        total = sum(base[r["dataset"]] for r in mine)
        out.append({"dataset": "*", variant: v, "of": seconds, "mean_of_ratios": round(sum(base[r["dataset"]] / r[seconds] for r in mine) / len(mine), 2), "ratio_of_means": round(total / sum(r[seconds] for r in mine), 2)})
    return out


def sketch_variants(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(DATASETS), engines: tuple[str, ...] = ("row", "htab", "batch", "vector", "sql"), repeat: int = 5, sample_n: int = 500, hll_error: float = 0.001) -> list[dict]:
    """Phases of the sketch method's unary level by filling engine: preprocessing, filling, checking, their sum, and speedups over the row engine."""
    out = []
    for name in names:
        catalog = DATASETS[name](spark, sf_dir)
        combos = [(a.id,) for a in catalog.attributes]
        first = lattice.with_combo_ids(lattice.as_level(candidates.unary(catalog), catalog), combos)
        phases = Phases()
        with phases("preprocess"):
            hashed = sketch.hash_tables(catalog, keep=True)
            keys = written(sketch.index_keys({k: sketch.sample_rows(v, sample_n) for k, v in hashed.items()}, combos, catalog), "keys")
        lgk = sketch.lgk_for(hll_error)
        filled = written(sketch.fill(hashed, combos, keys, catalog, lgk), "filled")
        with phases("check"):
            accepted = sketch.check(first, filled, len(combos)).count()
        for engine in engines:
            fill = measured(lambda e=engine: sketch.fill(hashed, combos, keys, catalog, lgk, e), repeat)
            rest = phases.seconds["preprocess"] + phases.seconds["check"]
            out.append({"dataset": name, "engine": engine, "keys": keys.count(), "accepted": accepted, "preprocess_s": round(phases.seconds["preprocess"], 3), "check_s": round(phases.seconds["check"], 3), "fill_s": fill["mean_s"], "overall_s": round(fill["mean_s"] + rest, 3), "jvm_mb": fill["jvm_mb"], "python_mb": fill["python_mb"]})
    return speedups(speedups(out, "engine", "row", "fill_s")[: len(out)], "engine", "row", "overall_s") + speedups(out, "engine", "row", "fill_s")[len(out) :]


def as_csv(spark: SparkSession, catalog: Catalog) -> Catalog:
    """The same tables as row-wise text files, all columns text: what the published comparison reads."""
    folder = new_folder(spark, "csv")
    for name, df in catalog.tables.items():
        df.select(*(F.col(f"`{a.column}`").cast("string") for a in catalog.of(name))).write.option("header", "true").option("escape", '"').csv(f"{folder}/{name}")
    return Catalog({n: spark.read.option("header", "true").option("escape", '"').option("multiLine", "true").csv(f"{folder}/{n}") for n in catalog.tables})


def merge_variants(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(DATASETS), repeat: int = 5, kinds: tuple[str, ...] = ("column_scan", "set", "set_single", "sort", "view", "pair", "chunked"), csv: bool = False) -> list[dict]:
    """Preprocessing time and peak memory of each variant, validation alone on its result, and speedups over the baseline of column scans; ``csv`` reads row-wise files."""
    out = []
    for name in names:
        catalog = DATASETS[name](spark, sf_dir)
        catalog = as_csv(spark, catalog) if csv else catalog
        for kind in kinds:
            pre = measured(lambda k=kind: dedupe.distinct_values(catalog, k), repeat)
            values = written(dedupe.distinct_values(catalog, kind), "dedupe")
            check = measured(lambda v=values: exact.merge_inds(v, len(catalog.attributes)), 1)
            out.append({"dataset": name, "kind": kind, "source": "csv" if csv else "parquet", **pre, "validate_s": check["mean_s"], "overall_s": round(pre["mean_s"] + check["mean_s"], 3)})
    return speedups(speedups(out, "kind", "column_scan")[: len(out)], "kind", "column_scan", "overall_s") + speedups(out, "kind", "column_scan")[len(out) :]


def memory_caps(spark: SparkSession, sf_dir: str, caps: tuple[int, ...] = (1 << 20, 2 << 20, 8 << 20, 32 << 20, 1 << 30), repeat: int = 5) -> list[dict]:
    """Preprocessing time and peak memory by memory cap: smaller parts, more of them to merge. Owned strings are sorted by Spark, whose memory the session sets."""
    catalog = core(spark, sf_dir)
    return [{"cap": cap, "kind": kind, **measured(lambda c=cap, k=kind: dedupe.distinct_values(catalog, k, c), repeat)} for cap in caps for kind in ("set_single", "view", "pair")]


def contention(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("core", "wide"), repeat: int = 5) -> list[dict]:
    """Filling the index with sets against bit vectors, where values repeat little (core) and much (wide)."""
    out = []
    for name in names:
        catalog = DATASETS[name](spark, sf_dir)
        combos = [(a.id,) for a in catalog.attributes]
        hashed = sketch.hash_tables(catalog, keep=True)
        keys = written(sketch.index_keys({k: sketch.sample_rows(v) for k, v in hashed.items()}, combos, catalog), "keys")
        out += [{"dataset": name, "members": m, **measured(lambda m=m: sketch.fill_index(hashed, combos, keys, catalog, m), repeat)} for m in ("set", "bits")]
    return speedups(out, "members", "set")


def partitions_by_columns(spark: SparkSession, sf_dir: str, partitions: tuple[int, ...] = (1, 2, 4, 8), widths: tuple[int, ...] = (8, 32, 64), repeat: int = 3) -> list[dict]:
    """Exact unary discovery by the number of partitions, for tables of more and more columns."""
    key, out = "spark.sql.shuffle.partitions", []
    before = spark.conf.get(key)
    try:
        for width in widths:
            table = wide(spark, sf_dir, width).tables["residues"]
            for n in partitions:
                spark.conf.set(key, str(n))
                catalog = Catalog({"residues": table.repartition(n)})
                out.append({"columns": width, "partitions": n, **measured(lambda c=catalog: exact.bitset(attr_values.unpivot_all(c), len(c.attributes)), repeat)})
    finally:
        spark.conf.set(key, before)
    return out


EXPERIMENTS: dict[str, Callable[..., list[dict]]] = {
    "sketch_variants": sketch_variants, "merge_variants": merge_variants, "merge_variants_csv": partial(merge_variants, csv=True), "memory_caps": memory_caps, "contention": contention, "partitions_by_columns": partitions_by_columns,
}


def accuracy_sweep(spark: SparkSession, sf_dir: str, samples: tuple[int | None, ...] = (0, 100, 500, None), lgks: tuple[int, ...] = (4, 8, 12, 16, 20)) -> DataFrame:
    """(sample_n, lgk, accepted, false_inds, missed): the sketch method's unary answer on the core tables against the exact one; NULL is a sample of all rows."""
    catalog = core(spark, sf_dir)
    n = len(catalog.attributes)
    combos = [(a.id,) for a in catalog.attributes]
    true = written(exact.bitset(attr_values.unpivot_all(catalog), n), "exact")
    total = true.count()
    hashed = sketch.hash_tables(catalog, keep=True)
    first = lattice.with_combo_ids(lattice.as_level(candidates.unary(catalog), catalog), combos)
    rows = []
    for s in samples:
        keys = None if s == 0 else written(sketch.index_keys({k: v if s is None else sketch.sample_rows(v, s) for k, v in hashed.items()}, combos, catalog), "keys")
        for lgk in lgks:
            got = sketch.check(first, written(sketch.fill(hashed, combos, keys, catalog, lgk), "filled"), n).select(F.col("d").alias("dep"), F.col("r").alias("ref"))
            both = got.join(true.withColumn("real", F.lit(1)), ["dep", "ref"], "left").agg(F.count(F.lit(1)).alias("n"), F.count("real").alias("t")).first()
            rows.append((s, lgk, both["n"], both["n"] - both["t"], total - both["t"]))
    return spark.createDataFrame(rows, "sample_n int, lgk int, accepted long, false_inds long, missed long")
