"""Derived tasks, sources, sinks, streaming and the registered queries."""

import duckdb
import pytest

from incdep import Catalog, discover
from incdep import workloads as W
from incdep.discover import unary_pairs
from incdep.operators import attr_values, derived
from incdep.oracles import oracle_sql
from incdep.queries import queries
from incdep.sources import readers, writers
from incdep.streaming.incremental import IncrementalInds, windowed_distinct

FAST = [
    "attr_stats", "combined_hash_md5", "dataset_profile", "events_incremental_inds", "exact_nary_sparse", "exact_unary_all", "exact_unary_typed", "fill_sets",
    "fk_candidates", "ind_classes", "ind_reduced", "ind_totals", "join_suggestion", "lattice_candidates_2", "partial_inds", "prose_unary", "sketch_index_keys_md5",
    "sketch_registers_md5", "sketch_sample_md5", "sketch_unary_default", "sketch_unary_hll_only", "sketch_estimates", "sketch_nary_high_arity", "fill_vector", "fill_bits", "fill_row", "level_counts",
    "explosion_guard", "index_lookups", "exact_unary_merge_baseline", "exact_unary_merge_set_single", "validate_declared", "violations", "wide_unary", "worked_example",
]


@pytest.mark.parametrize("name", FAST)
def test_query_matches_its_sql(spark, small, name):
    con = duckdb.connect()
    for t in W.CORE + ("events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"):
        con.sql(f"create view {t} as select * from '{small}/{t}.parquet'")
    df = queries()[name](spark, small)
    cols = sorted(df.columns)
    want = con.sql(f"select {', '.join(chr(34) + c + chr(34) for c in cols)} from ({oracle_sql()[name]})").fetchall()
    key = lambda r: tuple(map(repr, r))
    assert sorted((tuple(r) for r in df.select(*cols).collect()), key=key) == sorted(want, key=key)


def test_worked_example(spark, small):
    catalog = W.worked_example(spark, small)
    assert all(any(t in name for name in df.inputFiles()) for df, t in ((catalog.tables["people"], "orders"), (catalog.tables["licences"], "customer")))
    got = {(r["dep_table"], r["ref_table"], *r["dep_cols"], *r["ref_cols"]) for r in discover(catalog).collect()}
    assert got == {("people", "licences", "dln", "dlid"), ("licences", "people", "dlid", "dln")}


def test_partial(spark, data):
    catalog = W.core(spark, data)
    values = attr_values.unpivot_all(catalog).distinct().persist()
    assert [derived.partial_inds(values, 37, e).count() for e in (0.01, 0.05, 0.1, 0.2)] == [101, 113, 113, 118]


def test_validate_with_nulls_and_empty(spark):
    a, b = spark.createDataFrame([(None,), (1,)], "x int"), spark.createDataFrame([(1,)], "y int")
    r = derived.validate(a, ["x"], b, ["y"]).first()
    assert (r["holds"], r["dep_distinct"], r["missing"], r["error"]) == (False, 2, 1, 0.5)
    assert derived.validate(a, ["x"], b, ["y"], nulls="ignore").first()["holds"]
    assert derived.validate(a.limit(0), ["x"], b, ["y"]).first()["holds"]
    assert [tuple(r) for r in derived.violations(a, ["x"], b, ["y"]).collect()] == [(None,)]


def test_stream_of_files(spark, small, tmp_path):
    events = spark.read.parquet(f"{small}/events.parquet")
    late = events.orderBy("ts").repartitionByRange(4, "ts")
    late.write.parquet(str(tmp_path / "events"))
    catalog = Catalog({"customer": spark.read.parquet(f"{small}/customer.parquet").select("c_custkey"), "events": events})
    state = IncrementalInds(catalog, ("customer",))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "events"))
    state.follow("events", stream).awaitTermination()
    want = {tuple(r) for r in unary_pairs(catalog).collect()}
    assert {tuple(r) for r in state.inds().collect()} == want
    state.add("events", events.limit(5), 10)  # values that came before change nothing
    assert {tuple(r) for r in state.inds().collect()} == want
    again = IncrementalInds(catalog, root=state.root)  # a restarted program has all of it
    assert {tuple(r) for r in again.inds().collect()} == want
    again.compact("events")
    assert {tuple(r) for r in again.inds().collect()} == want and len(again._sources()) == 2


def test_stream_goes_on_after_a_restart(spark, small, tmp_path):
    events = spark.read.parquet(f"{small}/events.parquet")
    catalog = Catalog({"customer": spark.read.parquet(f"{small}/customer.parquet").select("c_custkey"), "events": events})
    for part in range(2):
        events.filter(f"event_id % 2 = {part}").write.mode("append").parquet(str(tmp_path / "events"))
        state = IncrementalInds(catalog, ("customer",) if part == 0 else (), f"file://{tmp_path}/root")
        state.follow("events", spark.readStream.schema(events.schema).parquet(str(tmp_path / "events"))).awaitTermination()
    assert {tuple(r) for r in state.inds().collect()} == {tuple(r) for r in unary_pairs(catalog).collect()}


def test_measures(spark, small):
    with W.PeakMemory(spark) as peak:
        spark.range(100_000).mapInArrow(lambda it: it, "id long").count()
    assert peak.jvm_mb > 100 and peak.python_mb > 10
    rows = W.merge_variants(spark, small, ("prose",), 1, ("column_scan", "pair"), csv=True)
    assert {r["kind"] for r in rows} == {"column_scan", "pair"} and rows[0]["mean_speedup"] == 1.0 and "mean_of_ratios" in rows[-1]
    got = {(r["members"], r["dataset"]) for r in W.contention(spark, small, ("wide",), 1)}
    assert got == {("set", "wide"), ("bits", "wide"), ("set", "*"), ("bits", "*")}
    rows = W.sketch_variants(spark, small, ("sparse",), ("row", "vector"), 1)
    assert all(r["accepted"] == 14 for r in rows if "accepted" in r) and "fill_speedup" in rows[0] and "overall_speedup" in rows[0]


def test_speedups():
    rows = [{"dataset": d, "kind": k, "mean_s": s} for d, k, s in (("a", "x", 4.0), ("a", "y", 2.0), ("b", "x", 3.0), ("b", "y", 3.0))]
    got = W.speedups(rows, "kind", "x")
    assert [r["mean_speedup"] for r in got[:4]] == [1, 2, 1, 1] and got[-1] == {"dataset": "*", "kind": "y", "of": "mean_s", "mean_of_ratios": 1.5, "ratio_of_means": 1.4}


def test_windowed_distinct(spark, small, tmp_path):
    events = spark.read.parquet(f"{small}/events.parquet")
    events.write.parquet(str(tmp_path / "e"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "e"))
    q = windowed_distinct(stream, "ts", "user_id", "1 day").writeStream.outputMode("complete").format("memory").queryName("seen").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("seen").groupBy().sum("value_count").first()[0] == events.count()


def test_sources_and_sinks(spark, small, tmp_path):
    nation = spark.read.parquet(f"{small}/nation.parquet")
    nation.write.option("header", "true").csv(str(tmp_path / "n.csv"))
    nation.write.orc(str(tmp_path / "n.orc"))
    nation.createOrReplaceTempView("nation_view")
    want = {tuple(r) for r in unary_pairs(Catalog({"n": nation})).collect()}
    for c in (readers.from_paths(spark, {"n": str(tmp_path / "n.csv")}, "csv"), readers.from_paths(spark, {"n": str(tmp_path / "n.orc")}, "orc"), readers.from_tables(spark, {"n": "nation_view"})):
        assert {tuple(r) for r in unary_pairs(c).collect()} == want
    values = attr_values.unpivot_all(Catalog({"n": nation})).distinct()
    writers.column_files(values, str(tmp_path / "cols"))
    assert spark.read.parquet(str(tmp_path / "cols")).count() == values.count()
    writers.report(discover(W.core(spark, small), view="inds"), str(tmp_path / "r"))
    assert spark.read.option("header", "true").csv(str(tmp_path / "r")).count() == 95
    assert spark.sql("select count(*) from inds").first()[0] == 95
    with pytest.raises(ValueError):
        readers.from_paths(spark, {}, "xml")


def test_include_exclude_where(spark, small):
    c = W.core(spark, small).select(include=r"key$", exclude=r"^lineitem")
    assert all(a.column.endswith("key") and a.table != "lineitem" for a in c.attributes)
    assert W.core(spark, small).where(orders="o_orderkey < 5").tables["orders"].count() == 5


def test_entry_imports_without_the_llm_folder(tmp_path):
    import os
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(f"{root}/incdep", tmp_path / "incdep", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'exact_unary_core' in q and 'pipeline' not in q; assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={**os.environ, "PYTHONPATH": str(tmp_path)})
