"""Exact engines, preprocessing variants and filters against set inclusion."""

import importlib
import itertools
import math

import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from incdep import Catalog, discover, flatten
from incdep import workloads as W
from incdep.discover import unary_pairs
from incdep.operators import attr_values, candidates, dedupe, exact, lattice

find = importlib.import_module("incdep.discover")  # the package has a function of that name
ENGINES = ["bitset", "merge", "inverted", "pairwise"]


def truth(tables: dict[str, tuple[list[str], list[tuple]]]) -> set:
    cols = [(t, c, {("v", str(r[k])) if r[k] is not None else ("n",) for r in rows}) for t, (names, rows) in sorted(tables.items()) for k, c in enumerate(names)]
    return {(a[0], a[1], b[0], b[1]) for a in cols for b in cols if a is not b and a[2] <= b[2]}


def build(spark, tables) -> Catalog:
    return Catalog({t: spark.createDataFrame(rows, ", ".join(f"{c} string" for c in names)) for t, (names, rows) in tables.items()})


def answer(df) -> set:
    return {(r["dep_table"], r["dep_cols"], r["ref_table"], r["ref_cols"]) for r in flatten(df).collect()}


TRAPS = {
    "max rule": {"t": (["a"], [("1",)]), "u": (["b"], [("1",), ("2",)])},
    "two lists": {"t": (["a"], [("1",), ("2",)]), "u": (["d"], [("2",)])},
    "nulls": {"t": (["a", "b", "z"], [(None, "1", None), ("1", "1", None)]), "u": (["c"], [("1",), ("n",), (None,)])},
    "empty": {"t": (["a"], []), "u": (["b", "c"], [("1", "2")])},
    "twins": {"t": (["a", "b"], [("1", "x"), ("2", "y")]), "u": (["a", "b"], [("1", "x"), ("2", "y")])},
    "single row": {"t": (["a", "b"], [("1", "1")])},
}


@pytest.mark.parametrize("method", ENGINES)
@pytest.mark.parametrize("name", TRAPS)
def test_traps(spark, method, name):
    assert answer(discover(build(spark, TRAPS[name]), method)) == truth(TRAPS[name])


cell = st.one_of(st.none(), st.sampled_from(["1", "2", "3", "n", "v1", ""]))


@settings(max_examples=8, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.lists(st.tuples(cell, cell, cell), max_size=6), st.lists(st.tuples(cell, cell), max_size=6))
def test_engines_agree_with_sets(spark, one, two):
    tables = {"t": (["a", "b", "c"], one), "u": (["x", "y"], two)}
    catalog = build(spark, tables)
    want = truth(tables)
    for method in ("bitset", "merge", "inverted"):
        assert answer(discover(catalog, method)) == want


def test_counts_of_the_data_sets(spark, data):
    assert discover(W.core(spark, data)).count() == 100
    assert discover(W.core(spark, data), typed=True).count() == 100
    assert discover(W.core(spark, data), "merge", prune_max=True).count() == 100
    assert discover(W.everything(spark, data)).count() == 319
    assert discover(W.prose(spark, data)).count() == 25


def test_wide_needs_several_words(spark, small):
    w = 70
    catalog = W.wide(spark, small, w)
    got = {(r[0], r[1]) for r in unary_pairs(catalog).collect()}
    assert got == {(j, k) for j in range(w) for k in range(w) if j < k} and len(got) == w * (w - 1) // 2


def test_null_policy(spark, data):
    assert discover(W.sparse(spark, data), max_arity=2).filter("dep_table = 'a' and ref_table = 'b'").groupBy("arity").count().orderBy("arity").collect() == [(1, 6), (2, 4)]
    ignored = answer(discover(W.sparse(spark, data), nulls="ignore"))
    assert ("a", "s", "b", "s2") in ignored and ("a", "z", "b", "k2") in ignored


def test_filters_keep_all_dependencies(spark, data):
    catalog = W.core(spark, data)
    stats = attr_values.attr_stats(catalog).persist()
    every = candidates.unary(catalog)
    assert every.count() == 37 * 36 and candidates.unary(catalog, typed=True).count() == 400
    assert candidates.prune(every, stats).count() == 681
    tight = candidates.prune(every, stats, True, True, True)
    assert tight.count() == 196
    assert unary_pairs(catalog).join(tight, ["dep", "ref"], "left_anti").isEmpty()


@pytest.mark.parametrize("kind", dedupe.KINDS)
def test_dedupe_variants(spark, small, kind):
    catalog = W.everything(spark, small)
    want = {tuple(r) for r in attr_values.unpivot_all(catalog).distinct().collect()}
    got = [tuple(r) for r in dedupe.distinct_values(catalog, kind, chunk_bytes=1 << 16).collect()]
    assert len(got) == len(want) and set(got) == want


def test_partitions_and_order_do_not_matter(spark, small):
    c = W.core(spark, small)
    shuffled = Catalog({t: df.orderBy(F.rand(3)).repartition(7) for t, df in c.tables.items()})
    want = answer(discover(c))
    assert answer(discover(shuffled)) == want and answer(discover(shuffled, "merge")) == want


def test_answers_are_transitive_and_irreflexive(spark, small):
    pairs = {tuple(r) for r in unary_pairs(W.everything(spark, small)).collect()}
    assert all(a != b for a, b in pairs)
    after: dict = {}
    for a, b in pairs:
        after.setdefault(a, set()).add(b)
    assert all(c == a or (a, c) in pairs for a, b in pairs for c in after.get(b, ()))


def test_set_single_takes_a_task_a_part(spark, small):
    parts = spark.read.parquet(f"{small}/orders.parquet").select("o_custkey", "o_orderpriority").repartition(7)
    catalog = Catalog({"orders": parts})
    assert "Coalesce 1" not in dedupe.as_set_single(catalog)._jdf.queryExecution().toString()
    want = sorted(map(tuple, dedupe.as_set(catalog).collect()))
    for limit in (1, 3000, 64 << 20):  # every batch is flushed, some, none
        assert sorted(map(tuple, dedupe.as_set_single(catalog, limit_bytes=limit).collect())) == want


def test_merge_counts_work(spark, small):
    catalog = W.core(spark, small)
    row = exact.merge_counters(dedupe.as_set(catalog), len(catalog.attributes)).first()
    assert 0 < row["steps"] <= row["read"]


def test_nary(spark, data):
    catalog = W.high_arity(spark, data)
    level, counts = lattice.climb(lattice.as_level(unary_pairs(catalog), catalog), lattice.exact_check(catalog), None)
    across = level.filter("dep_table = 'dep' and ref_table = 'ref'").groupBy(F.size("dep").alias("arity")).count().orderBy("arity").collect()
    assert [r["count"] for r in across] == [8, 23, 36, 35, 21, 7, 1]
    assert sum(c["valid"] for c in counts) == level.count() and all(c["candidates"] >= c["valid"] for c in counts[1:])
    rows = {(tuple(r["dep"]), tuple(r["ref"])) for r in level.collect()}
    for dep, ref in rows:
        for k in range(len(dep)):
            if len(dep) > 1:
                assert (dep[:k] + dep[k + 1 :], ref[:k] + ref[k + 1 :]) in rows


def test_wide_dependencies_spare_checks(spark, small):
    catalog = W.high_arity(spark, small)
    first, check, asked = lattice.written(lattice.as_level(unary_pairs(catalog), catalog), "level"), lattice.exact_check(catalog), []

    def watched(candidates, combos):
        asked.extend(combos)
        return check(candidates, combos)

    plain, counts = lattice.climb(first, check, None)
    got, counts_ahead = lattice.climb(first, watched, None, tables=[a.table for a in catalog.attributes])
    assert counts_ahead == counts and counts[-1]["arity"] == 7
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, plain.collect()))
    assert sum(len(c) > 3 for c in asked) <= 4  # the sides of the widest one, and of one that it does not cover; 128 combinations without it


def test_wide_guesses_that_fail(spark):
    rows = [(k, k % 2, k % 3, k % 5, k % 7) for k in range(300)]
    tables = {"t": (list("abcde"), rows[:200]), "u": (list("vwxyz"), [(a, b, c, d, (e + (a >= 100)) % 7) for a, b, c, d, e in rows])}
    catalog = build(spark, tables)
    first, check = lattice.written(lattice.as_level(unary_pairs(catalog), catalog), "level"), lattice.exact_check(catalog)
    plain, counts = lattice.climb(first, check, None)
    got, counts_ahead = lattice.climb(first, check, None, tables=[a.table for a in catalog.attributes])
    assert counts_ahead == counts and sorted(map(tuple, got.collect())) == sorted(map(tuple, plain.collect()))


def test_rows_of_the_next_level(spark, data):
    catalog = W.core(spark, data)
    level = lattice.written(lattice.as_level(unary_pairs(catalog), catalog), "level")
    rows = [(t, u, tuple(d), tuple(r)) for t, u, d, r in level.collect()]
    want = sorted((t, u, tuple(d), tuple(r)) for t, u, d, r in lattice.next_level(level, 1).collect())
    assert lattice.next_rows(rows, 1) == want and want
    assert lattice.next_rows([("t", "u", (0,), (k,)) for k in range(200)], 1) is None  # too many pairs for the driver


def test_binary_against_brute_force(spark):
    rows = [("1", "2", "3"), ("2", "1", "3"), ("1", "1", "1"), (None, "2", "3")]
    tables = {"t": (["a", "b", "c"], rows), "u": (["x", "y", "z"], [*rows, ("3", "3", "3")])}
    names = {t: names for t, (names, _) in tables.items()}
    want = truth(tables)
    for (t, (tn, tr)), (u, (un, ur)) in itertools.product(tables.items(), repeat=2):
        for i, j in itertools.combinations(range(3), 2):
            for k, m in itertools.permutations(range(3), 2):
                if not (t == u and {i, j} & {k, m}) and {(r[i], r[j]) for r in tr} <= {(r[k], r[m]) for r in ur}:
                    want.add((t, f"{tn[i]},{tn[j]}", u, f"{un[k]},{un[m]}"))
    assert names and answer(discover(build(spark, tables), max_arity=2)) == want


def test_too_many_candidates(spark, small):
    catalog = W.wide(spark, small, 12)
    with pytest.raises(lattice.TooManyCandidates):
        discover(catalog, max_arity=None, max_candidates=10)


def test_nested_columns(spark):
    df = spark.createDataFrame([(1, [1, 2]), (2, [2])], "k int, xs array<int>")
    assert [a.column for a in Catalog({"t": df}).attributes] == ["k"]
    assert answer(discover(Catalog({"t": df}, nested="explode"))) == {("t", "xs", "t", "k"), ("t", "k", "t", "xs")}
    assert len(Catalog({"t": df}, nested="json").attributes) == 2


def included(catalog: Catalog, nulls: str) -> set:
    """Unary dependencies by sets of Python values, array elements and bytes among them."""
    sets = []
    for a in catalog.attributes:
        cells = [r[0] for r in catalog.tables[a.table].select(a.column).collect()]
        if (a.table, a.column) in catalog.element_columns:
            cells = [x for c in cells if c is not None for x in c]
        sets.append((a, {None if x is None else str(x) for x in cells if x is not None or nulls == "equal"}))
    return {(a.id, b.id) for a, s in sets for b, t in sets if a.id != b.id and s <= t}


@pytest.fixture(scope="module")
def mixed(spark):
    one = spark.createDataFrame([(1, [1, 2, None], bytearray(b"\xff\x00"), None), (2, [], bytearray(b"a"), "2"), (None, None, None, "1")], "k int, xs array<int>, raw binary, s string")
    two = spark.createDataFrame([(1, [bytearray(b"\xff\x00")], None), (1, [bytearray(b"a"), bytearray(b"b")], None)], "y int, blobs array<binary>, z string")
    return lambda: Catalog({"one": one, "two": two}, nested="explode")


@pytest.mark.parametrize("nulls", ["equal", "ignore"])
def test_arrays_bytes_and_nulls_by_all_methods(spark, mixed, nulls):
    want = included(mixed(), nulls)
    ids = {a.column: a.id for a in mixed().attributes}
    assert (ids["y"], ids["xs"]) in want and (ids["raw"], ids["blobs"]) in included(mixed(), "ignore")
    for method in ("bitset", "inverted", "pairwise"):
        assert {tuple(r) for r in unary_pairs(mixed(), method, nulls).select("dep", "ref").collect()} == want, method
    for kind in dedupe.KINDS:
        assert {tuple(r) for r in unary_pairs(mixed(), "merge", nulls, kind=kind, chunk_bytes=200).select("dep", "ref").collect()} == want, kind
    for engine in ("sql", "vector", "batch"):
        got = discover(mixed(), "sketch", nulls=nulls, engine=engine)
        assert {(ids[r["dep_cols"][0]], ids[r["ref_cols"][0]]) for r in got.collect()} == want, engine


def test_array_elements_stay_out_of_wider_levels(spark, mixed):
    for options in ({}, {"method": "sketch"}, {"method": "sketch", "verify": True}):
        got = discover(mixed(), max_arity=None, **options).collect()
        assert all(r["arity"] == 1 or not {"xs", "blobs"} & {*r["dep_cols"], *r["ref_cols"]} for r in got)
        assert {(r["dep_cols"][0], r["ref_cols"][0]) for r in got if r["arity"] == 1} >= {("y", "xs")}


def test_merge_is_a_stream_of_small_batches(spark, small):
    """Values that go on over batches, and more attributes than a word holds."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        got = {tuple(r) for r in unary_pairs(W.wide(spark, small, 70), "merge").collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert got == {(j, k) for j in range(70) for k in range(70) if j < k}


@pytest.mark.parametrize("nulls", ["equal", "ignore"])
def test_looked_up_rows_rule_out_only_what_is_false(spark, small, monkeypatch, nulls):
    catalog = W.sparse(spark, small)
    first = lattice.written(lattice.as_level(unary_pairs(catalog, nulls=nulls), catalog), "level")
    level = [(r["dep_table"], r["ref_table"], tuple(r["dep"]), tuple(r["ref"])) for r in lattice.next_level(first, 1).collect()]
    combos = sorted({c for row in level for c in row[2:]})
    hashed = attr_values.hashed_columns(catalog, nulls)
    held = {(combos[r["dep"]], combos[r["ref"]]) for r in exact.bitset(attr_values.unpivot_combos(hashed, catalog, combos), len(combos)).collect()}
    pairs = [row[2:] for row in level]
    bad = lattice._refuted(hashed, catalog, pairs)
    assert bad and bad <= set(pairs) and not bad & held
    monkeypatch.setattr(lattice, "PROBE_ROWS", 1)  # what a single row leaves open is decided by the masks
    got = lattice.exact_check(catalog, nulls)(spark.createDataFrame(level, lattice.LEVEL), combos)
    assert {(tuple(r["dep"]), tuple(r["ref"])) for r in got.collect()} == held & set(pairs)


def test_a_data_set_inside_another_takes_its_levels_from_there(spark, small, monkeypatch):
    whole = W.core(spark, small).select(exclude=r"^(lineitem|part)\.")
    some = Catalog({t: whole.tables[t] for t in ("nation", "region", "supplier")})
    want, asked = {"whole": find.levels(whole), "some": find.levels(some)}, []
    plain = find.levels
    monkeypatch.setattr(find, "levels", lambda c, *a: asked.append(len(c.tables)) or plain(c, *a))
    flat = lambda x: ([{k: v for k, v in c.items() if isinstance(v, int)} for c in x[0]], x[1])
    got = find.levels_of({"some": some, "whole": whole})
    assert asked == [5] and {n: flat(x) for n, x in got.items()} == {n: flat(x) for n, x in want.items()}
    got = find.levels_of({"some": some, "whole": whole}, max_candidates=max((c["candidates"] for c in want["some"][0][1:]), default=0))  # only the larger one is stopped
    assert asked[1:] == [5, 3] and [got[n][1] for n in ("whole", "some")] == [True, False] and flat(got["some"]) == flat(want["some"])
    assert find.table_sizes({"some": some, "whole": whole})["some"][0][0] == 25


@pytest.mark.parametrize("nulls", ["equal", "ignore"])
def test_sets_of_stored_numbers_give_the_same_text(spark, nulls):
    df = spark.sql("""
        select * from values (1, 1.5D, date'2020-02-29', 'v', true, 1.50BD, timestamp'2020-01-01 00:00:01', float(0.1), array(1, null)), (-7, -0.0D, date'0001-01-01', repeat('é', 65), false, 0.00BD, null, float(1e10), array(3)),
        (2147483647, double('NaN'), date'9999-12-31', '', null, -2.25BD, timestamp'1969-12-31 23:59:59.5', float('Infinity'), null), (null, null, null, null, null, null, null, null, null),
        (0, 1e21D, date'1582-10-15', 'n', true, null, null, null, null), (1, 0.0D, null, 'x', true, 1.50BD, null, null, null), (2, double('-Infinity'), null, '1', true, 1.50BD, null, null, null), (3, 4.9E-324D, null, null, true, 1.50BD, null, null, null)
        as t(i, d, day, s, b, m, ts, f, a)""")
    catalog = Catalog({"t": df.repartition(2), "none": df.limit(0)}, nested="explode")
    assert [set(k.values()) >= {"integer", "date", "double", "text"} for _, k in dedupe.raw_tables(catalog)][:2] == [True, True]
    want = sorted(map(tuple, dedupe.as_set(catalog, nulls).collect()))
    for limit in (1, 64 << 20):
        assert sorted(map(tuple, dedupe.as_set_single(catalog, nulls, limit).collect())) == want


def test_values_are_merged_once(spark, small):
    pairs = exact.merge_inds(dedupe.as_set(W.core(spark, small)), 37)
    assert "MapInArrow" not in pairs._jdf.queryExecution().toString() and pairs.count() > 0


def test_no_candidate_is_too_many(spark):
    """A million candidates of three columns at a level, more combinations than masks are for: all counted, none refused."""
    n = 102
    refs = [f"r{k}" for k in range(n)]
    tables = {"t": (["a", "b", "c"], [("1", "1", "1")]), "u": (refs, [("1",) * n, tuple(f"x{k}" for k in range(n))])}
    counts, stopped = find.levels(build(spark, tables))
    assert not stopped and [(c["arity"], c["candidates"], c["valid"]) for c in counts[1:]] == [(2, 3 * n * (n - 1), 3 * n * (n - 1)), (3, n * (n - 1) * (n - 2), n * (n - 1) * (n - 2))]


@pytest.mark.parametrize("nulls", ["equal", "ignore"])
@pytest.mark.parametrize("at_once", [5_000, 200_000_000])
def test_combinations_as_rows_agree_with_masks(spark, small, monkeypatch, nulls, at_once):
    monkeypatch.setattr(lattice, "PROBE_PAIRS", 1)
    monkeypatch.setattr(lattice, "PAIRS_AT_ONCE", at_once)  # several jobs, or one
    catalog = W.sparse(spark, small)
    first = lattice.written(lattice.as_level(unary_pairs(catalog, nulls=nulls), catalog), "level")
    level = lattice.written(lattice.next_level(first, 1), "level")
    want = lattice.exact_check(catalog, nulls)(level, lattice.combos_of(level)).collect()
    got = lattice.exact_check(catalog, nulls)(level, lattice.combos_of(level, 0)).collect()
    assert want and len(want) < level.count() and sorted(map(tuple, got)) == sorted(map(tuple, want))


def test_empty_tables_have_all_levels(spark):
    """Nothing rules anything out where there are no rows: each list of columns is in each other one, up to the widest."""
    wide, narrow = [f"a{k}" for k in range(7)], [f"b{k}" for k in range(5)]
    counts, stopped = find.levels(build(spark, {"t": (wide, []), "u": (narrow, [])}))
    ways = lambda n, m, k: math.comb(n, k) * math.perm(m, k) if m >= k else 0
    want = [sum(ways(n, m, k) for n, m in ((7, 5), (5, 7), (7, 7 - k), (5, 5 - k))) for k in range(1, 6)]
    assert not stopped and [c["valid"] for c in counts] == want and [c["candidates"] for c in counts[1:]] == want[1:]


def test_profile_counts_all_levels(spark):
    """A level with more than a hundred thousand candidates is counted like the others."""
    n = 50
    refs = [f"r{k}" for k in range(n)]
    tables = {"t": (["a", "b", "c"], [("1", "1", "1")]), "u": (refs, [("1",) * n, tuple(f"x{k}" for k in range(n))])}
    row = find.profile({"one": build(spark, tables)}).first()
    assert (row["unary_inds"], row["max_arity"]) == (6 + 3 * n, 3)
    assert row["nary_inds"] == 6 + 3 * n + 3 * n * (n - 1) + n * (n - 1) * (n - 2)
