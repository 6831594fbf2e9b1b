"""Level-wise candidates of several columns, and exact discovery on them.

A dependency is a row (dep_table, ref_table, dep array<int>, ref array<int>): positions correspond, the dependent side is in
ascending order of attributes, no attribute repeats inside a side or occurs on both, each side is of one table.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Collection, Sequence
from functools import reduce
from itertools import permutations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..catalog import Catalog
from ..functions import rotate
from ..plans import written
from .attr_values import hashed_columns, unpivot_all, unpivot_combos
from .exact import bitset

LEVEL = "dep_table string, ref_table string, dep array<int>, ref array<int>"
LOCAL_ROWS = 10_000  # dependencies of a level, and pairs of them, up to which the next one's candidates are formed on the driver, without a job

PROBE_ROWS = 300  # rows of a dependent table whose tuples are looked up before a level's full check
PROBE_CELLS = 100_000  # tuples that are looked up at most, over all combinations

MASK_COMBOS = 1024  # combinations of a level up to which its check has masks, a word for 64 of them; more than that are rows
PROBE_PAIRS = 2_000_000  # tuples that are looked up first, over all candidates of such a level; those of one row at least
PAIRS_AT_ONCE = 200_000_000  # tuples that are looked up in one job, over candidates


class TooManyCandidates(RuntimeError):
    """A level has more candidates than allowed; ``counts`` has the levels so far, that one too."""

    counts: list[dict]


def as_level(pairs: DataFrame, catalog: Catalog) -> DataFrame:
    """Unary (dep, ref) pairs as a level."""
    one = catalog.dictionary(catalog.spark)
    dep, ref = one.select(F.col("attr").alias("dep"), F.col("table_name").alias("dep_table")), one.select(F.col("attr").alias("ref"), F.col("table_name").alias("ref_table"))
    both = pairs.join(F.broadcast(dep), "dep").join(F.broadcast(ref), "ref")
    return both.select("dep_table", "ref_table", F.array(F.col("dep").cast("int")).alias("dep"), F.array(F.col("ref").cast("int")).alias("ref"))


def next_level(valid: DataFrame, arity: int) -> DataFrame:
    """Candidates of ``arity`` + 1 columns from the valid dependencies of ``arity``.

    Two dependencies between the same tables that agree in all but their last pair are joined; a candidate stays if all its
    projections on ``arity`` pairs are valid.
    """
    head = lambda c: F.slice(c, 1, arity - 1)
    left = valid.select("dep_table", "ref_table", head("dep").alias("d"), head("ref").alias("r"), F.element_at("dep", -1).alias("dl"), F.element_at("ref", -1).alias("rl"))
    right = left.withColumnRenamed("dl", "dm").withColumnRenamed("rl", "rm")
    joined = left.join(right, ["dep_table", "ref_table", "d", "r"]).filter("dl < dm and rl <> rm")
    raw = joined.select("dep_table", "ref_table", F.concat("d", F.array("dl", "dm")).alias("dep"), F.concat("r", F.array("rl", "rm")).alias("ref"))
    raw = raw.filter((F.size(F.array_distinct("ref")) == arity + 1) & (F.size(F.array_intersect("dep", "ref")) == 0))
    drop = lambda c, k: F.filter(c, lambda x, i: i != k)
    parts = raw.select("*", F.explode(F.array(*(F.struct(drop("dep", k).alias("pd"), drop("ref", k).alias("pr")) for k in range(arity + 1)))).alias("p"))
    known = valid.select("dep_table", "ref_table", F.col("dep").alias("pd"), F.col("ref").alias("pr"))
    held = parts.select("dep_table", "ref_table", "dep", "ref", "p.pd", "p.pr").join(known, ["dep_table", "ref_table", "pd", "pr"], "left_semi")
    return held.groupBy("dep_table", "ref_table", "dep", "ref").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") == arity + 1).drop("n")


def _plain(x: str | Sequence[int]) -> str | tuple[int, ...]:
    return x if isinstance(x, str) else tuple(x)


def next_rows(valid: list[tuple], arity: int) -> list[tuple] | None:
    """``next_level`` of rows on the driver; None if it has more than ``LOCAL_ROWS`` pairs to join."""
    known, heads = set(valid), {}
    for t, u, dep, ref in valid:
        heads.setdefault((t, u, dep[:-1], ref[:-1]), []).append((dep[-1], ref[-1]))
    if sum(len(x) ** 2 for x in heads.values()) > 2 * LOCAL_ROWS:
        return None
    out = []
    for (t, u, d, r), last in heads.items():
        for (dl, rl), (dm, rm) in permutations(last, 2):
            dep, ref = (*d, dl, dm), (*r, rl, rm)
            if dl < dm and rl != rm and len(set(ref)) == arity + 1 and not set(dep) & set(ref) and all((t, u, dep[:k] + dep[k + 1 :], ref[:k] + ref[k + 1 :]) in known for k in range(arity + 1)):
                out.append((t, u, dep, ref))
    return sorted(out)


def combos_of(candidates: DataFrame, most: int | None = None) -> list[tuple[int, ...]] | None:
    """The distinct column combinations of a level: as many as the lattice has, not as the data. None if they are more than ``most``."""
    sides = candidates.select("dep").union(candidates.select("ref")).distinct()
    rows = (sides if most is None else sides.limit(most + 1)).collect()
    return None if most is not None and len(rows) > most else sorted(tuple(r[0]) for r in rows)


def with_combo_ids(candidates: DataFrame, combos: list[tuple[int, ...]]) -> DataFrame:
    names = candidates.sparkSession.createDataFrame([(list(c), k) for k, c in enumerate(combos)], "combo array<int>, id int")
    dep = F.broadcast(names.select(F.col("combo").alias("dep"), F.col("id").alias("d")))
    ref = F.broadcast(names.select(F.col("combo").alias("ref"), F.col("id").alias("r")))
    return candidates.join(dep, "dep").join(ref, "ref")


Pairs = tuple[tuple[int, int], ...]  # of a dependency: (dep, ref) by position


def guesses(valid: list[tuple[Sequence[int], Sequence[int]]], table: Sequence[str]) -> list[Pairs]:
    """Wide dependencies that the valid ones of a level don't rule out: one at most between two tables, of two columns more at least.

    From unary ones the largest matching of dependent to referenced columns; from wider ones a set of pairs that grows, starting with
    those that occur most, while all two of them occur together. ``table`` is the table of each attribute.
    """
    groups: dict[tuple[str, str], list[Pairs]] = {}
    for dep, ref in valid:
        if table[dep[0]] != table[ref[0]]:
            groups.setdefault((table[dep[0]], table[ref[0]]), []).append(tuple(zip(dep, ref, strict=True)))
    out = []
    for _, rows in sorted(groups.items()):
        arity = len(rows[0])
        if arity == 1:
            refs: dict[int, list[int]] = {}
            for ((d, r),) in sorted(rows):
                refs.setdefault(d, []).append(r)
            taken: dict[int, int] = {}  # ref to dep

            def place(d: int, tried: set[int], refs: dict[int, list[int]] = refs, taken: dict[int, int] = taken) -> bool:
                for r in refs[d]:
                    if r not in tried:
                        tried.add(r)
                        if r not in taken or place(taken[r], tried):
                            taken[r] = d
                            return True
                return False

            for d in refs:
                place(d, set())
            got = sorted((d, r) for r, d in taken.items())
        else:
            near: dict[tuple[int, int], set[tuple[int, int]]] = {}
            seen = Counter(p for row in rows for p in row)
            for row in rows:
                for p in row:
                    near.setdefault(p, set()).update(row)
            got = []
            for p in sorted(seen, key=lambda p: (-seen[p], p)):
                if all(p in near[q] and p[0] != q[0] and p[1] != q[1] for q in got):
                    got.append(p)
            got.sort()
        if len(got) >= max(arity + 2, 4):  # fewer would spare hardly any check
            out.append(tuple(got))
    return out


def _inside(wide: Sequence[Pairs], n: int) -> Column:
    """Whether a candidate of attributes below ``n`` is a projection of one of the ``wide`` dependencies."""
    pairs = F.zip_with("dep", "ref", lambda d, r: d.cast("long") * n + r)
    return reduce(Column.__or__, [F.size(F.array_except(pairs, F.array(*(F.lit(d * n + r).cast("long") for d, r in w)))) == 0 for w in wide], F.lit(False))


def _between(level: DataFrame) -> Counter:
    """The number of a level's rows by (dep_table, ref_table)."""
    return Counter({(r[0], r[1]): r[2] for r in level.groupBy("dep_table", "ref_table").agg(F.count(F.lit(1)).alias("n")).collect()})


def within(counts: list[dict], tables: Collection[str]) -> list[dict]:
    """The levels of ``climb`` on some of its tables alone: candidates and what holds between two tables depend on no other table."""
    out: list[dict] = []
    for c in counts:
        some = {f: Counter({p: n for p, n in c[f].items() if p[0] in tables and p[1] in tables}) for f in ("candidates_between", "valid_between") if f in c}
        one = {"arity": c["arity"]} | {f.removesuffix("_between"): sum(x.values()) for f, x in some.items()} | some
        if out and not (out[-1]["valid"] and one["candidates"]):
            break
        out.append(one)
    return out


def climb(
    unary: DataFrame, check: Callable[[DataFrame, list[tuple[int, ...]] | None], DataFrame], max_arity: int | None, max_candidates: int | None = None, alone: Sequence[int] = (),
    tables: Sequence[str] | None = None, most_combos: int | None = None,
) -> tuple[DataFrame, list[dict[str, int]]]:
    """All levels from the valid unary level on; also candidates and survivors of each level. Attributes in ``alone`` stay unary.

    ``tables`` has the table of each attribute and is for a ``check`` that is exact and takes NULL for a value: then all projections of a valid
    dependency are valid. Wide dependencies that a level leaves possible are checked ahead, and the candidates inside one that holds need no check of their own.
    ``max_candidates`` None is no limit. ``check`` gets None in place of a level's combinations if they are more than ``most_combos``.
    """
    spark = unary.sparkSession
    valid = written(unary, "level")
    between = _between(valid)
    every, counts, arity = valid, [{"arity": 1, "valid": sum(between.values()), "valid_between": between}], 1
    asked: set[Pairs] = set()
    wide: list[Pairs] = []
    while counts[-1]["valid"] and (max_arity is None or arity < max_arity):
        base = valid.filter(~F.arrays_overlap(F.concat("dep", "ref"), F.array(*map(F.lit, alone)))) if alone and arity == 1 else valid
        rows = [tuple(map(_plain, r)) for r in base.collect()] if counts[-1]["valid"] <= LOCAL_ROWS else None
        local = next_rows(rows, arity) if rows is not None else None
        candidates = spark.createDataFrame(local, LEVEL) if local is not None else written(next_level(base, arity), "level")
        possible = Counter(r[:2] for r in local) if local is not None else _between(candidates)
        n = sum(possible.values())
        if max_candidates is not None and n > max_candidates:
            stop = TooManyCandidates(f"{n} candidates of {arity + 1} columns; at most {max_candidates} are allowed")
            stop.counts = [*counts, {"arity": arity + 1, "candidates": n}]
            raise stop
        if not n:
            break
        if tables is not None and rows is not None and max_arity != arity + 1:
            fresh = [g for g in guesses([r[2:] for r in rows], tables) if g not in asked and not any(set(g) <= set(w) for w in wide)]
            if fresh:
                asked.update(fresh)
                some = [(tables[g[0][0]], tables[g[0][1]], tuple(d for d, _ in g), tuple(r for _, r in g)) for g in fresh]
                true = check(spark.createDataFrame(some, LEVEL), sorted({c for row in some for c in row[2:]})).collect()
                wide += [tuple(zip(r["dep"], r["ref"], strict=True)) for r in true]
        if local is not None:
            sure = [row for row in local if any(set(zip(*row[2:], strict=True)) <= set(w) for w in wide)]
            if len(sure) == n:
                valid, between = candidates, possible
            else:
                tested = sorted(set(local) - set(sure))
                true = check(spark.createDataFrame(tested, LEVEL), sorted({c for row in tested for c in row[2:]})).collect()
                held = sure + [tuple(map(_plain, r)) for r in true]
                valid, between = spark.createDataFrame(held, LEVEL), Counter(r[:2] for r in held)
        else:
            tested = written(candidates.filter(~_inside(wide, len(tables))), "level") if wide else candidates
            valid = check(tested, combos_of(tested, most_combos)) if not wide or not tested.isEmpty() else tested
            valid = written(valid.unionByName(candidates.filter(_inside(wide, len(tables)))) if wide else valid, "level")
            between = _between(valid)
        arity += 1
        counts.append({"arity": arity, "candidates": n, "valid": sum(between.values()), "candidates_between": possible, "valid_between": between})
        every = every.unionByName(valid)
    return every, counts


def _refuted(hashed: dict[str, DataFrame], catalog: Catalog, pairs: list[tuple[tuple[int, ...], tuple[int, ...]]]) -> set[tuple[tuple[int, ...], tuple[int, ...]]]:
    """Those of ``pairs`` of combinations (dep, ref) that some rows rule out: one of their dependent tuples is nowhere in the referenced table.

    All rows of the referenced tables are looked through, for the tuples of a few rows of the dependent ones. So what it rules out doesn't hold; of the rest nothing is known.
    """
    by_id = {a.id: a.table for a in catalog.attributes}
    deps, refs = sorted({d for d, _ in pairs}), sorted({r for _, r in pairs})
    n = max(1, min(PROBE_ROWS, PROBE_CELLS // len(deps)))
    probes = {}
    for t in sorted({by_id[d[0]] for d in deps}):
        rows = hashed[t].orderBy(F.xxhash64(*hashed[t].columns)).limit(n)
        probes[t] = catalog.spark.createDataFrame(rows.collect(), rows.schema)
    asked: dict[tuple[int, int], set[int]] = {}  # the dependents that have a tuple
    for k, v in unpivot_combos(probes, catalog, deps).distinct().collect():
        asked.setdefault(tuple(v), set()).add(k)
    if not asked:
        return set()
    keys = catalog.spark.createDataFrame([(g,) for g in sorted({g for g, _ in asked})], "key long")
    cells = unpivot_combos(hashed, catalog, refs).join(F.broadcast(keys), F.col("v.g") == F.col("key"), "left_semi")
    found: dict[tuple[int, int], set[int]] = {}
    for k, v in cells.distinct().collect():
        found.setdefault(tuple(v), set()).add(k)
    of: dict[int, list[int]] = {}
    place = {r: k for k, r in enumerate(refs)}, {d: k for k, d in enumerate(deps)}
    for d, r in pairs:
        of.setdefault(place[1][d], []).append(place[0][r])
    return {(deps[d], refs[r]) for v, ds in asked.items() for d in ds for r in of[d] if r not in found.get(v, ())}


def _tuples(hashed: dict[str, DataFrame], catalog: Catalog, combos: DataFrame) -> DataFrame:
    """(id, g, h): the tuples of ``unpivot_combos`` for combinations (id, combo) that are rows, so that a plan doesn't grow with them."""
    parts = []
    for name, df in hashed.items():
        ids = [a.id for a in catalog.of(name)]
        null = F.lit(None).cast("long")
        arrays = [F.array(*(F.col(f"{n}{a}") if f"{n}{a}" in df.columns else null for a in ids)).alias(n) for n in "gh"]
        at = lambda x, a, first=ids[0]: F.element_at(x, a - F.lit(first - 1))
        fold = lambda x, at=at: F.aggregate(F.slice("combo", 2, F.size("combo") - 1), at(x, F.element_at("combo", 1)), lambda acc, a: rotate(acc).bitwiseXOR(at(x, a))).alias(x)
        mine = combos.filter(F.element_at("combo", 1).between(ids[0], ids[-1]))
        parts.append(df.select(*arrays).crossJoin(mine).select("id", fold("g"), fold("h")))
    return reduce(DataFrame.unionByName, parts).filter("g is not null").distinct()


def _by_rows(hashed: dict[str, DataFrame], catalog: Catalog, candidates: DataFrame) -> DataFrame:
    """Those of ``candidates`` that hold, however many they and their combinations are: each dependent tuple is looked up in the referenced combination.

    Tuples of some rows come first. What they leave open is looked up for all rows, in as many jobs as bound what one of them writes.
    """
    sides = candidates.select(F.col("dep").alias("combo")).union(candidates.select("ref")).distinct()
    combos = written(sides.withColumn("id", F.monotonically_increasing_id()), "combos")
    dep, ref = (combos.select(F.col("combo").alias(side), F.col("id").alias(number)) for side, number in (("dep", "d"), ("ref", "r")))
    level = written(candidates.join(dep, "dep").join(ref, "ref"), "level")

    def stay(level: DataFrame, few: dict[str, DataFrame], every: dict[str, DataFrame]) -> DataFrame:
        """Without candidates of which a tuple in ``few`` is nowhere in ``every``."""
        asked = _tuples(few, catalog, combos.join(level.select(F.col("d").alias("id")), "id", "left_semi")).withColumnRenamed("id", "d")
        held = _tuples(every, catalog, combos.join(level.select(F.col("r").alias("id")), "id", "left_semi")).withColumnRenamed("id", "r")
        lost = level.select("d", "r").join(asked, "d").join(held, ["r", "g", "h"], "left_anti")
        return level.join(lost.select("d", "r").distinct(), ["d", "r"], "left_anti")

    used = {r[0] for r in combos.select(F.explode("combo")).distinct().collect()}
    rows = {t: df.select(*(c for c in df.columns if int(c[1:]) in used)) for t, df in hashed.items()}
    rows = {t: written(df.distinct(), "distinct") for t, df in rows.items() if df.columns}
    n = max(1, min(PROBE_ROWS, PROBE_PAIRS // max(1, level.count())))
    some = {t: written(df.orderBy(F.xxhash64(*df.columns)).limit(n), "probes") for t, df in rows.items()}
    left = written(stay(level, some, rows), "level")
    many = {t: df.count() for t, df in rows.items()}
    jobs = -(-sum(k * many[t] for t, k in left.groupBy("dep_table").count().collect()) // PAIRS_AT_ONCE)
    parts = [left.filter(F.pmod(F.xxhash64("d"), F.lit(jobs)) == k) for k in range(jobs)] if jobs > 1 else [left]
    true = [written(stay(part, rows, rows), "level") for part in parts]
    return reduce(DataFrame.unionByName, true)


def exact_check(catalog: Catalog, nulls: str = "equal") -> Callable[[DataFrame, list[tuple[int, ...]] | None], DataFrame]:
    """Exact validation of a level: one scan of each table's hashes, tuples as values, and value masks over combinations.

    Candidates of several columns that the tuples of some rows already rule out take no part in the masks, which only the rest and their combinations need.
    A level with more combinations than ``MASK_COMBOS``, or with None for them, has no masks; its combinations, all of several columns if None, are rows.
    """
    hashed: dict[str, DataFrame] = {}
    known: set[int] = set()  # attributes that are hashed

    def check(candidates: DataFrame, combos: list[tuple[int, ...]] | None) -> DataFrame:
        left = candidates.filter(F.size("dep") > 1)
        many = None if combos is None else [c for c in combos if len(c) > 1]
        out = []
        if many is not None and len(many) < len(combos):
            unary = as_level(bitset(unpivot_all(catalog, nulls), len(catalog.attributes)), catalog)
            out.append(candidates.filter(F.size("dep") == 1).join(unary, ["dep", "ref"], "left_semi"))
        if many is None or many:
            sides = [r[0] for r in left.select(F.explode(F.array("dep", "ref"))).select(F.explode("col")).distinct().collect()] if many is None else [a for c in many for a in c]
            if fresh := set(sides) - known:
                again = {catalog.attributes[a].table for a in fresh}
                known.update(fresh)
                hashed.update(hashed_columns(catalog, nulls, {a for a in known if catalog.attributes[a].table in again}))
        if many is None or len(many) > MASK_COMBOS:
            out.append(_by_rows(hashed, catalog, left.select("dep_table", "ref_table", "dep", "ref")))
        elif many:
            rows = left.select("dep_table", "ref_table", "dep", "ref").limit(LOCAL_ROWS + 1).collect()
            if len(rows) <= LOCAL_ROWS:
                level = {(row[2], row[3]): row for row in (tuple(map(_plain, r)) for r in rows)}
                bad = _refuted(hashed, catalog, list(level)) if level else set()
                left = catalog.spark.createDataFrame([row for pair, row in level.items() if pair not in bad], LEVEL)
                many = sorted({c for pair in level.keys() - bad for c in pair})
            if many:
                true = bitset(unpivot_combos({t: hashed[t] for t in hashed if any(catalog.attributes[c[0]].table == t for c in many)}, catalog, many), len(many)).withColumnsRenamed({"dep": "d", "ref": "r"})
                left = with_combo_ids(left, many).join(true, ["d", "r"], "left_semi")
            out.append(left)
        return reduce(DataFrame.unionByName, [df.select("dep_table", "ref_table", "dep", "ref") for df in out])

    return check
