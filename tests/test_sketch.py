"""The sketch method: no false negatives, engines agree, the sample covers, registers merge."""

import pytest
from pyspark.sql import functions as F

from incdep import Catalog, discover, flatten
from incdep import workloads as W
from incdep.discover import unary_pairs
from incdep.operators import sketch


def rows(df) -> set:
    return {tuple(r) for r in flatten(df).collect()}


@pytest.mark.parametrize("sample_n,lgk", [(0, 4), (0, 12), (100, 8), (500, 12), (None, 4)])
def test_recall_is_one(spark, small, sample_n, lgk):
    catalog = W.core(spark, small)
    want, got = rows(discover(catalog)), rows(discover(catalog, "sketch", sample_n=sample_n, lgk=lgk))
    assert want <= got
    if sample_n is None:
        assert want == got


def test_verified_equals_exact(spark, small):
    catalog = W.core(spark, small)
    assert rows(discover(catalog, "sketch", sample_n=0, lgk=4, verify=True)) == rows(discover(catalog))


def test_high_arity(spark, small):
    catalog = W.high_arity(spark, small)
    want = rows(discover(catalog, max_arity=3))
    assert want <= rows(discover(catalog, "sketch", max_arity=3, lgk=14))
    assert rows(discover(catalog, "sketch", max_arity=3, lgk=10, verify=True)) == want


def test_engines_and_members_agree(spark, small):
    catalog = W.core(spark, small)
    combos = [(a.id,) for a in catalog.attributes]
    hashed = sketch.hash_tables(catalog)
    keys = sketch.index_keys({k: sketch.sample_rows(v, 20) for k, v in hashed.items()}, combos, catalog).persist()
    want = {tuple(r) for r in sketch.fill(hashed, combos, keys, catalog, 10).collect()}
    for engine in sketch.ENGINES:
        assert {tuple(r) for r in sketch.fill(hashed, combos, keys, catalog, 10, engine).collect()} == want, engine
    filled = sketch.fill(hashed, combos, keys, catalog, 10)
    sets = {r["h"]: r["members"] for r in sketch.index_members(filled, len(combos), "set").collect()}
    bits = {r["h"]: [k for k in range(len(combos)) if r["w0"] >> k & 1] for r in sketch.index_members(filled, len(combos), "bits").collect()}
    assert sets == bits


def test_sample_covers_every_column(spark, small):
    hashed = sketch.hash_tables(W.core(spark, small))["lineitem"]
    got = sketch.sample_rows(hashed, 30)
    for c in hashed.columns:
        assert got.select(c).distinct().count() >= min(30, hashed.select(c).distinct().count())
    again = sketch.sample_rows(hashed.repartition(9), 30)
    assert got.exceptAll(again).isEmpty() and again.exceptAll(got).isEmpty()


def test_registers_merge(spark, small):
    catalog = W.core(spark, small).select("orders")
    combos = [(a.id,) for a in catalog.attributes]
    reg = lambda df: sketch.registers(sketch.fill(sketch.hash_tables(Catalog({"orders": df})), combos, None, catalog, 6))
    whole = catalog.tables["orders"]
    parts = reg(whole.filter("o_orderkey % 2 = 0")).union(reg(whole.filter("o_orderkey % 2 = 1"))).union(reg(whole))
    assert {tuple(r) for r in parts.groupBy("combo", "bucket").agg(F.max("rho")).collect()} == {tuple(r) for r in reg(whole).collect()}


def test_estimate_is_close(spark, data):
    catalog = W.core(spark, data).select(r"orders\.o_orderkey|lineitem\.l_partkey")
    filled = sketch.fill(sketch.hash_tables(catalog), [(a.id,) for a in catalog.attributes], None, catalog, 12)
    got = {r["combo"]: r["estimate"] for r in sketch.estimate(sketch.registers(filled), 12).collect()}
    for a in catalog.attributes:
        n = catalog.tables[a.table].select(a.column).distinct().count()
        assert abs(got[a.id] / n - 1) < 0.06


def test_sweep_follows_the_parameters(spark, small):
    got = {(r["sample_n"], r["lgk"]): r for r in W.accuracy_sweep(spark, small, (0, 100), (4, 8, 12)).collect()}
    assert all(r["missed"] == 0 for r in got.values())
    assert got[0, 4]["false_inds"] >= got[0, 8]["false_inds"] >= got[0, 12]["false_inds"]
    assert got[100, 4]["false_inds"] <= got[0, 4]["false_inds"]


def test_nulls(spark, data):
    catalog = W.sparse(spark, data)
    for nulls in ("equal", "ignore"):
        want = {tuple(r) for r in unary_pairs(catalog, nulls=nulls).collect()}
        assert len(want) <= discover(catalog, "sketch", nulls=nulls).count()


def test_sample_covers_columns_with_a_null_in_every_row(spark):
    df = spark.createDataFrame([(k if k % 2 else None, None if k % 2 else k, None) for k in range(40)], "a int, b int, c int")
    hashed = sketch.hash_tables(Catalog({"t": df}), nulls="ignore")["t"]
    got = sketch.sample_rows(hashed, 12)
    for c, n in zip(hashed.columns, (12, 12, 0), strict=True):
        assert got.filter(f"{c} is not null").select(c).distinct().count() == n
    want = {tuple(r) for r in unary_pairs(Catalog({"t": df}), nulls="ignore").collect()}
    for n in (3, 500, None):
        got = discover(Catalog({"t": df}), "sketch", nulls="ignore", sample_n=n)
        names = {"a": 0, "b": 1, "c": 2}
        assert {(names[r["dep_cols"][0]], names[r["ref_cols"][0]]) for r in got.collect()} == want


def test_dominance_of_registers(spark):
    import itertools
    import random

    r = random.Random(4)
    regs = {(c, b): r.randint(1, 4) for c in range(70) for b in range(6) if r.random() < 0.5 and c != 5}
    df = spark.createDataFrame([(c, b, p) for (c, b), p in regs.items()], "combo int, bucket int, rho int")
    want = {(d, e) for d, e in itertools.product(range(70), repeat=2) if all(p <= regs.get((e, b), 0) for (c, b), p in regs.items() if c == d)}
    assert {tuple(x) for x in sketch.dominated(df, 70).collect()} == want


@pytest.mark.parametrize("nulls", ["equal", "ignore"])
def test_arrays_of_registers_agree_with_entries(spark, small, nulls):
    """A level of several columns leaves the tasks as a few arrays a combination, not as entries by row; they hold and reject the same."""
    import numpy as np

    catalog = W.sparse(spark, small)
    mine = {t: [a.id for a in catalog.of(t)] for t in catalog.tables}
    combos = [(i, j) for ids in mine.values() for i in ids for j in ids if i != j] + [tuple(ids[:3]) for ids in mine.values()]
    hashed = sketch.hash_tables(catalog, nulls=nulls, keep=True)
    pairs = [(d, r) for d, c in enumerate(combos) for r, e in enumerate(combos) if d != r and len(c) == len(e)]
    level = spark.createDataFrame(pairs, "d int, r int")
    for lgk, keys in ((6, None), (14, sketch.index_keys({k: sketch.sample_rows(v, 9) for k, v in hashed.items()}, combos, catalog).persist())):
        filled = sketch.fill(hashed, combos, keys, catalog, lgk).persist()
        local = np.sort(np.asarray([r[0] for r in keys.collect()] if keys is not None else [], np.int64))
        arrays = sketch.fill_arrays(hashed, combos, local, catalog, lgk).persist()
        assert arrays.count() < 40 * len(combos)
        hits, regs = set(), {}
        for r in arrays.collect():
            if r["part"] == -1:
                hits |= {(r["combo"], x) for x in np.frombuffer(r["data"], np.int64).tolist()}
                continue
            for at, p in enumerate(r["data"]):
                if p:
                    key = r["combo"], (r["part"] << min(lgk, sketch.PART_LGK)) + at
                    regs[key] = max(p, regs.get(key, 0))
        assert hits == {(r["combo"], r["k"]) for r in filled.filter("hit").collect()}
        assert regs == {(r["combo"], r["bucket"]): r["rho"] for r in sketch.registers(filled).collect()}
        kept = {(r["d"], r["r"]) for r in sketch.check(level, filled, len(combos)).collect()}
        assert 0 < len(kept) < len(pairs) and set(pairs) - kept == {tuple(r) for r in sketch.refuted(arrays, pairs).collect()}
