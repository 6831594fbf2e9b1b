"""One entry for all discovery methods."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark import inheritable_thread_target
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .catalog import Catalog
from .functions import quoted
from .operators import attr_values, candidates, dedupe, derived, exact, lattice, sketch
from .plans import written

METHODS = ("bitset", "merge", "inverted", "pairwise", "sketch")


def _names(catalog: Catalog, ids: str) -> Column:
    names = F.array(*(F.lit(a.column) for a in catalog.attributes))
    return F.transform(ids, lambda i: F.element_at(names, i + 1))


def result(level: DataFrame, catalog: Catalog) -> DataFrame:
    """(dep_table, dep_cols, ref_table, ref_cols, arity) of a level or of several."""
    return level.select("dep_table", _names(catalog, "dep").alias("dep_cols"), "ref_table", _names(catalog, "ref").alias("ref_cols"), F.size("dep").alias("arity"))


def flatten(inds: DataFrame) -> DataFrame:
    """Column lists as comma-separated text."""
    return inds.withColumns({c: F.concat_ws(",", c) for c in ("dep_cols", "ref_cols")})


def _tables(catalog: Catalog, nulls: str) -> list[str] | None:
    """The table of each attribute, where a dependency's projections hold as it does: not if tuples with a NULL are left out."""
    return [a.table for a in catalog.attributes] if nulls == "equal" else None


def unary_pairs(catalog: Catalog, method: str = "bitset", nulls: str = "equal", typed: bool = False, prune_max: bool = False, kind: str = "set", chunk_bytes: int = 64 << 20) -> DataFrame:
    """(dep, ref) of the exact unary dependencies."""
    n = len(catalog.attributes)
    cand = None
    if typed or prune_max or method == "pairwise":
        cand = candidates.unary(catalog, typed)
        if prune_max:
            cand = candidates.prune(cand, written(attr_values.attr_stats(catalog), "stats"))
        cand = written(cand, "candidates")
    if method == "bitset":
        pairs = exact.bitset(attr_values.unpivot_all(catalog, nulls), n)
    elif method == "inverted":
        pairs = exact.inverted(attr_values.unpivot_all(catalog, nulls), n)
    elif method == "merge":
        values = dedupe.distinct_values(catalog, kind, chunk_bytes, nulls)
        first: dict[int, set[int]] | None = None
        if cand is not None:
            first = {a: set() for a in range(n)}
            for d, r in cand.collect():  # of the size of the schema squared
                first[d].add(r)
        return exact.merge_inds(values, n, first)
    elif method == "pairwise":
        return exact.pairwise(written(attr_values.unpivot_all(catalog, nulls).distinct(), "values"), cand)
    else:
        raise ValueError(f"method={method!r}")
    return pairs.join(cand, ["dep", "ref"], "left_semi") if cand is not None else pairs


def discover(
    catalog: Catalog, method: str = "bitset", max_arity: int | None = 1, nulls: str = "equal", typed: bool = False, prune_max: bool = False,
    verify: bool = False, kind: str = "set", chunk_bytes: int = 64 << 20, sample_n: int | None = 500, hll_error: float = 0.001, lgk: int | None = None,
    members: str = "bits", engine: str = "sql", fn: str = "xx", max_candidates: int = 1_000_000, view: str | None = None,
) -> DataFrame:
    """All inclusion dependencies up to ``max_arity`` columns (None: no limit), by one of ``METHODS``.

    ``nulls``: NULL is a value of its own (``equal``) or left out (``ignore``). ``typed`` compares columns of one type class
    only. ``prune_max`` drops candidates by their largest values. ``kind`` and ``chunk_bytes`` choose the merge method's
    preprocessing; ``sample_n``, ``hll_error`` or ``lgk``, ``members``, ``engine`` and ``fn`` belong to the sketch method, whose
    answer may hold false dependencies unless ``verify`` checks the survivors exactly. ``view`` registers the result.
    """
    if method == "sketch":
        level, _ = sketch.approx_inds(catalog, sample_n, hll_error, max_arity, nulls, typed, members, engine, fn, lgk, max_candidates)
        if verify:
            level = written(level, "survivors")
            combos = lattice.combos_of(level)
            level = lattice.exact_check(catalog, nulls)(level, combos) if combos else level
    else:
        first = lattice.as_level(unary_pairs(catalog, method, nulls, typed, prune_max, kind, chunk_bytes), catalog)
        level, _ = (first, None) if max_arity == 1 else lattice.climb(first, lattice.exact_check(catalog, nulls), max_arity, max_candidates, catalog.element_ids, _tables(catalog, nulls), lattice.MASK_COMBOS)
    out = result(level, catalog)
    if view:
        out.createOrReplaceTempView(view)
    return out


def levels(catalog: Catalog, max_arity: int | None = None, max_candidates: int | None = None, nulls: str = "equal") -> tuple[list[dict], bool]:
    """Candidates and valid dependencies of each level, exactly, and whether a level had more candidates than allowed (None: any number is)."""
    n = len(catalog.attributes)
    first = lattice.as_level(unary_pairs(catalog, nulls=nulls), catalog)
    try:
        counts, stopped = lattice.climb(first, lattice.exact_check(catalog, nulls), max_arity, max_candidates, catalog.element_ids, _tables(catalog, nulls), lattice.MASK_COMBOS)[1], False
    except lattice.TooManyCandidates as e:
        counts, stopped = e.counts, True
    counts[0]["candidates"] = n * (n - 1)
    return counts, stopped


def levels_of(catalogs: dict[str, Catalog], max_arity: dict[str, int] | None = None, max_candidates: int | None = None) -> dict[str, tuple[list[dict], bool]]:
    """``levels`` of several data sets side by side: the small jobs of one run while others compute.

    A data set whose tables all are tables of another one takes its levels from there, if that one is bounded alike and wasn't stopped.
    """
    bound = lambda name: (max_arity or {}).get(name)
    same = lambda a, b: all(t in b.tables and a.tables[t].sameSemantics(b.tables[t]) for t in a.tables) and a.nested == b.nested
    order = sorted(catalogs, key=lambda name: -len(catalogs[name].tables))
    inside = {}
    for k, name in enumerate(order):
        larger = [m for m in order[:k] if m not in inside and bound(m) == bound(name) and same(catalogs[name], catalogs[m])]
        inside |= {name: larger[0]} if larger else {}
    spark = next(iter(catalogs.values())).spark

    def run(names: list[str]) -> dict[str, tuple[list[dict], bool]]:
        with ThreadPoolExecutor(max(1, len(names))) as pool:
            jobs = {n: pool.submit(inheritable_thread_target(spark)(lambda n=n: levels(catalogs[n], bound(n), max_candidates))) for n in names}
            return {n: j.result() for n, j in jobs.items()}

    got = run([n for n in order if n not in inside])
    rest = [n for n, m in inside.items() if got[m][1]]
    for name, larger in inside.items():
        if name not in rest:
            counts, n = lattice.within(got[larger][0], catalogs[name].tables), len(catalogs[name].attributes)
            counts[0]["candidates"] = n * (n - 1)
            got[name] = counts, False
    return got | run(rest)


def table_sizes(catalogs: dict[str, Catalog]) -> dict[str, list[tuple[int, int]]]:
    """(rows, characters of all values as text) of each data set's tables; a table that several have is read once."""
    distinct: list[DataFrame] = []
    place: dict[str, list[int]] = {}
    plans = []
    for name, c in catalogs.items():
        for t, df in c.tables.items():
            at = next((k for k, other in enumerate(distinct) if other.sameSemantics(df)), None)
            if at is None:
                at = len(distinct)
                distinct.append(df)
                chars = [F.coalesce(F.sum(F.length(F.col(quoted(a.column)).cast("string"))), F.lit(0)) for a in attr_values.plain_attributes(c, t)]
                plans.append(df.agg(F.count(F.lit(1)).alias("rows"), reduce(Column.__add__, chars, F.lit(0).cast("long")).alias("chars")).withColumn("place", F.lit(at)))
            place.setdefault(name, []).append(at)
    sizes = {r["place"]: (r["rows"], r["chars"]) for r in reduce(DataFrame.unionByName, plans).collect()}
    return {name: [sizes[k] for k in mine] for name, mine in place.items()}


def profile(catalogs: dict[str, Catalog], max_arity: dict[str, int] | None = None, max_candidates: int | None = None) -> DataFrame:
    """(dataset, tables, attributes, rows, text_chars, unary_inds, nary_inds, max_arity): one row a data set.

    ``text_chars`` is the size of all values as text. ``nary_inds`` and ``max_arity`` are NULL where a level has more candidates than
    allowed (None: any number is), or where ``max_arity`` bounds the data set to unary ones.
    """
    found, sizes, out = levels_of(catalogs, max_arity, max_candidates), table_sizes(catalogs), []
    for name, c in catalogs.items():
        counts, stopped = found[name]
        known = not stopped and (max_arity or {}).get(name) is None
        widest = max((x["arity"] for x in counts if x.get("valid")), default=None)
        out.append((name, len(c.tables), len(c.attributes), sum(r for r, _ in sizes[name]), sum(n for _, n in sizes[name]), counts[0]["valid"], sum(x["valid"] for x in counts) if known else None, widest if known else None))
    return next(iter(catalogs.values())).spark.createDataFrame(out, "dataset string, tables long, attributes long, rows long, text_chars long, unary_inds long, nary_inds long, max_arity int")


__all__ = ["METHODS", "Catalog", "derived", "discover", "flatten", "levels", "levels_of", "profile", "result", "unary_pairs"]
