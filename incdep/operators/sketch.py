"""The approximate method: hashed columns, a covering sample, a small inverted index and HyperLogLog registers.

A combination's hashes that are keys of the index are settled there, exactly up to hash collisions; all other hashes go to
the combination's registers. A candidate survives if no index key has its dependent without its referenced side and no
register of the dependent exceeds the referenced side's. Neither test rejects a true dependency.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import Catalog
from ..functions import bucket, fingerprint_sql, folded, has_bit, quoted, rho, token_sql, word_masks
from ..plans import written
from .attr_values import plain_attributes
from .candidates import unary
from .exact import bitset
from .lattice import LEVEL, LOCAL_ROWS, as_level, climb, with_combo_ids

ENGINES = ("sql", "vector", "batch", "htab", "row")
BROADCAST_KEYS = 4_000_000
FILLED = "hit boolean, combo int, k long, rho int"
ARRAYS = "combo int, part int, data binary"
ARRAYS_AT_ONCE = 32  # combinations whose registers a task holds at a time: 64 MB of them at lgk 21
PART_LGK = 12  # registers of a combination that are kept and compared together


def lgk_for(error: float) -> int:
    """Smallest power of two of registers whose standard error, 1.04 / sqrt(m), is at most ``error``; from 4 to 21."""
    return min(21, max(4, math.ceil(2 * math.log2(1.04 / error))))


def hash_tables(catalog: Catalog, fn: str = "xx", nulls: str = "equal", keep: bool = False) -> dict[str, DataFrame]:
    """Per table a row of hashes h<attr>, one a column, in row order; ``keep`` writes them, so that levels don't scan the originals again.

    An exploded array is a table of its own, a row an element.
    """
    hashed = lambda x, a: f"{fingerprint_sql(token_sql(x, nulls, compact=False), fn)} as h{a}"
    out = {}
    for name, df in catalog.tables.items():
        if plain := plain_attributes(catalog, name):
            out[name] = df.selectExpr(*(hashed(quoted(a.column), a.id) for a in plain))
    for a in catalog.attributes:
        if a.id in catalog.element_ids:
            out[f"{a.table}[{a.column}]"] = catalog.tables[a.table].selectExpr(f"explode({quoted(a.column)}) as e").selectExpr(hashed("e", a.id))
    return {name: written(df, "hashed") if keep else df for name, df in out.items()}


def _fold(columns: list[np.ndarray], width: int = 64) -> np.ndarray:
    """The combined hash on 64-bit unsigned vectors."""
    acc = columns[0].copy()
    low = np.uint64((1 << (width - 1)) - 1)
    for h in columns[1:]:
        acc = ((acc & low) << np.uint64(1)) | (acc >> np.uint64(width - 1))
        acc ^= h
    return acc


def sample_rows(hashed: DataFrame, n: int = 500, width: int = 64) -> DataFrame:
    """Rows such that each column shows all its distinct hashes, or its ``n`` smallest ones; NULL is no hash.

    Each kept hash has one witness, the row of smallest combined hash. Tasks keep at most n rows a column; what they keep is
    ranked again by (column, hash), so neither the order nor the number of tasks matters.
    """
    cols = hashed.columns

    def bottom(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept, none = np.empty((0, len(cols)), np.int64), np.empty((0, len(cols)), bool)
        for b in batches:
            if not b.num_rows:
                continue
            x = np.concatenate([kept, np.stack([c.fill_null(0).to_numpy() for c in b.columns], axis=1)])
            null = np.concatenate([none, np.stack([c.is_null().to_numpy(zero_copy_only=False) for c in b.columns], axis=1)])
            row = _fold([np.ascontiguousarray(x[:, c]).view(np.uint64) for c in range(len(cols))], width).view(np.int64)
            take = np.zeros(len(x), bool)
            for c in range(len(cols)):
                some = np.flatnonzero(~null[:, c])
                if len(some) > 4 * n + 100:  # all that can be among the n smallest distinct ones, and the rows they occur in
                    least = np.unique(x[some, c])[:n]
                    some = some[x[some, c] <= least[-1]]
                order = some[np.lexsort((row[some], x[some, c]))]
                v = x[order, c]
                take[order[np.concatenate([[True], v[1:] != v[:-1]])][:n] if len(v) else order] = True
            kept, none = x[take], null[take]
        if len(kept):
            yield pa.RecordBatch.from_arrays([pa.array(kept[:, c], mask=none[:, c]) for c in range(len(cols))], names=cols)

    local = hashed.mapInArrow(bottom, ", ".join(f"{c} long" for c in cols))
    turned = f"(shiftleft(acc & {(1 << (width - 1)) - 1}L, 1) | shiftrightunsigned(acc, {width - 1}))"  # few rows: a loop over their values, not an expression that doubles with each
    row = F.struct(F.expr(f"aggregate(array({', '.join(f'coalesce({c}, 0L)' for c in cols)}), 0L, (acc, x) -> {turned} ^ x)").alias("order"), *cols)
    cells = local.select(row.alias("row"), F.explode(F.array(*(F.struct(F.lit(k).alias("c"), F.col(c).alias("h")) for k, c in enumerate(cols)))).alias("x")).select("x.c", "x.h", "row").filter("h is not null")
    best = cells.groupBy("c", "h").agg(F.min("row").alias("row")).withColumn("at", F.row_number().over(Window.partitionBy("c").orderBy("h"))).filter(F.col("at") <= n)
    return best.select("row.*").select(*cols).distinct()


def combo_folds(name: str, combos: list[tuple[int, ...]], catalog: Catalog) -> list[tuple[int, list[str]]]:
    """(combination, hash columns) of the combinations of a hashed table."""
    mine = {a.id for a in (plain_attributes(catalog, name) if name in catalog.tables else catalog.attributes) if name in (a.table, f"{a.table}[{a.column}]")}
    return [(k, [f"h{a}" for a in c]) for k, c in enumerate(combos) if mine.issuperset(c)]


def index_keys(samples: dict[str, DataFrame], combos: list[tuple[int, ...]], catalog: Catalog, width: int = 64) -> DataFrame:
    """(h): the combined hashes of the sampled rows, the keys of the inverted index."""
    parts = []
    for name, sample in samples.items():
        if mine := combo_folds(name, combos, catalog):
            wide, names = folded(sample, [cols for _, cols in mine], width)
            parts.append(wide.select(F.explode(F.array(*names)).alias("h")).filter("h is not null"))
    return reduce(DataFrame.unionByName, parts).distinct()


def _sql_fill(hashed: DataFrame, mine: list[tuple[int, list[str]]], keys: DataFrame | None, small: bool, lgk: int, width: int) -> DataFrame:
    wide, names = folded(hashed, [cols for _, cols in mine], width)
    cells = ", ".join(f"named_struct('combo', {k}, 'h', {name})" for (k, _), name in zip(mine, names, strict=True))
    rows = wide.selectExpr(f"explode(array({cells})) as c").select("c.combo", "c.h").filter("h is not null")
    if keys is not None:
        k = keys.select("h", F.lit(True).alias("hit"))
        rows = rows.join(F.broadcast(k) if small else k, "h", "left")
    else:
        rows = rows.withColumn("hit", F.lit(None).cast("boolean"))
    hit = F.coalesce("hit", F.lit(False))
    return rows.select(hit.alias("hit"), "combo", F.when(hit, F.col("h")).otherwise(bucket(F.col("h"), lgk).cast("long")).alias("k"), F.when(hit, F.lit(0)).otherwise(rho(F.col("h"), lgk, width)).alias("rho"))


def _python_fill(hashed: DataFrame, mine: list[tuple[int, list[str]]], keys: np.ndarray, engine: str, lgk: int, width: int) -> DataFrame:
    """Fill outside the JVM; ``keys`` is sorted and went through the broadcast guard."""
    full, low = (1 << width) - 1, (1 << lgk) - 1
    names = hashed.columns

    def emit(hit: list, combo: list, k: list, r: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(hit, pa.bool_()), pa.array(combo, pa.int32()), pa.array(k, pa.int64()), pa.array(r, pa.int32())], names=["hit", "combo", "k", "rho"])

    def signed(h: int) -> int:
        return h - (1 << 64) if h >> 63 else h

    def one(values: list[int]) -> int:
        acc = values[0] & full
        for v in values[1:]:
            acc = ((acc << 1) & full | acc >> (width - 1)) ^ (v & full)
        return acc

    def position(h: int) -> int:
        x = h >> lgk
        return (x & -x).bit_length() if x else width - lgk + 1

    def scalar(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        text = engine == "row"
        known = {str(x) for x in keys.tolist()} if text else set(keys.tolist())
        hits: set = set()
        regs: dict = {}

        def put(c: int, h: int) -> None:
            s = signed(h)
            if (str(s) if text else s) in known:
                hits.add((s, c))
            elif (p := position(h)) > regs.get((c, h & low), 0):
                regs[c, h & low] = p

        for b in batches:
            if engine == "batch":
                data = {n: c.to_pylist() for n, c in zip(names, b.columns, strict=True)}
                for c, cols in mine:
                    for values in zip(*(data[n] for n in cols), strict=True):
                        if None not in values:
                            put(c, one(list(values)))
            else:
                for row in b.to_pylist():
                    for c, cols in mine:
                        values = [row[n] for n in cols]
                        if None not in values:
                            put(c, one(values))
        rows = [(True, c, s, 0) for s, c in hits] + [(False, c, k, p) for (c, k), p in regs.items()]
        for at in range(0, len(rows), 50_000):
            yield emit(*map(list, zip(*rows[at : at + 50_000], strict=True)))

    def vector(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if any(c.null_count for c in b.columns):
                null = {n: np.asarray(c.is_null()) for n, c in zip(names, b.columns, strict=True)}
                data = {n: c.fill_null(0).to_numpy().view(np.uint64) for n, c in zip(names, b.columns, strict=True)}
            else:
                null, data = {}, {n: c.to_numpy().view(np.uint64) for n, c in zip(names, b.columns, strict=True)}
            for c, cols in mine:
                h = _fold([data[n] for n in cols], width)
                if null:
                    h = h[~np.any([null[n] for n in cols], axis=0)]
                s = h.view(np.int64)
                at = np.searchsorted(keys, s)
                hit = keys[np.minimum(at, len(keys) - 1)] == s if len(keys) else np.zeros(len(s), bool)
                k = np.unique(s[hit])
                x = h[~hit] >> np.uint64(lgk)
                lowest = x & (~x + np.uint64(1))
                p = np.where(x == 0, width - lgk + 1, np.frexp(lowest.astype(np.float64))[1])
                where = (h[~hit] & np.uint64(low)).astype(np.int64)
                order = np.lexsort((-p, where))
                first = order[np.concatenate([[True], where[order][1:] != where[order][:-1]])] if len(order) else order
                yield emit([True] * len(k) + [False] * len(first), [c] * (len(k) + len(first)), np.concatenate([k, where[first]]), np.concatenate([np.zeros(len(k), int), p[first]]))

    return hashed.mapInArrow(vector if engine == "vector" else scalar, FILLED)


def fill(hashed: dict[str, DataFrame], combos: list[tuple[int, ...]], keys: DataFrame | None, catalog: Catalog, lgk: int = 21, engine: str = "sql", width: int = 64) -> DataFrame:
    """(hit, combo, k, rho): index entries (k is the hash) and registers (k is the register) of a level, in one scan of each table and one shuffle.

    Hits and misses share one aggregation with map-side combine, so a frequent value costs a row a task.
    ``keys`` is broadcast up to ``BROADCAST_KEYS`` and joined by a shuffle beyond (the Python engines refuse then).
    """
    small, local = True, np.empty(0, np.int64)
    if keys is not None:
        small = keys.count() <= BROADCAST_KEYS
        if engine != "sql":
            if not small:
                raise ValueError(f"engine={engine!r} needs at most {BROADCAST_KEYS} index keys")
            local = np.sort(np.asarray([r[0] for r in keys.collect()], dtype=np.int64))
    parts = []
    for name, df in hashed.items():
        if mine := combo_folds(name, combos, catalog):
            df = df.select(*sorted({c for _, cols in mine for c in cols}))
            parts.append(_sql_fill(df, mine, keys, small, lgk, width) if engine == "sql" else _python_fill(df, mine, local, engine, lgk, width))
    return reduce(DataFrame.unionByName, parts).groupBy("hit", "combo", "k").agg(F.max("rho").alias("rho"))


def lookups(hashed: dict[str, DataFrame], combos: list[tuple[int, ...]], catalog: Catalog) -> DataFrame:
    """(table_name, combos, row_count, lookups) of a level: how often the index is asked, counted on the cells that ask it."""
    parts = []
    for name, df in hashed.items():
        if mine := combo_folds(name, combos, catalog):
            wide, names = folded(df, [cols for _, cols in mine])
            asked = F.size(F.array_compact(F.array(*names)))
            parts.append(wide.agg(F.count(F.lit(1)).alias("row_count"), F.sum(asked.cast("long")).alias("lookups")).select(F.lit(name).alias("table_name"), F.lit(len(mine)).cast("long").alias("combos"), "row_count", "lookups"))
    return reduce(DataFrame.unionByName, parts)


def fill_index(hashed: dict[str, DataFrame], combos: list[tuple[int, ...]], keys: DataFrame, catalog: Catalog, members: str = "bits", width: int = 64) -> DataFrame:
    """The inverted index straight from the probed rows, as ``index_members`` gives it.

    Every hit of every row goes into its key's members: a set that grows by insertion (``set``), or words that are ORed (``bits``). So the
    two differ where values repeat, as a locked set and a bit vector do; both are combined by task before anything is shuffled.
    """
    small = keys.count() <= BROADCAST_KEYS
    parts = [_sql_fill(df, mine, keys, small, 4, width) for name, df in hashed.items() if (mine := combo_folds(name, combos, catalog))]
    return index_members(reduce(DataFrame.unionByName, parts), len(combos), members)


def index_members(filled: DataFrame, n: int, members: str = "bits") -> DataFrame:
    """The inverted index: (h, members) with a sorted set (``set``), or (h, w0..) with one bit a combination (``bits``)."""
    hits = filled.filter("hit").select(F.col("k").alias("h"), "combo")
    if members == "set":
        return hits.groupBy("h").agg(F.array_sort(F.collect_set("combo")).alias("members"))
    return hits.groupBy("h").agg(*word_masks(F.col("combo"), n))


def registers(filled: DataFrame) -> DataFrame:
    """(combo, bucket, rho)."""
    return filled.filter("not hit").select("combo", F.col("k").cast("int").alias("bucket"), "rho")


def estimate(regs: DataFrame, lgk: int) -> DataFrame:
    """(combo, estimate): harmonic mean of registers, linear counting while many are empty."""
    m = float(1 << lgk)
    alpha = {4: 0.673, 5: 0.697, 6: 0.709}.get(lgk, 0.7213 / (1 + 1.079 / m))
    got = regs.groupBy("combo").agg(F.count(F.lit(1)).alias("full"), F.sum(F.pow(F.lit(2.0), -F.col("rho"))).alias("s"))
    empty = F.lit(m) - F.col("full")
    raw = F.lit(alpha * m * m) / (F.col("s") + empty)
    return got.select("combo", F.when((raw <= 2.5 * m) & (empty > 0), m * F.log(m / empty)).otherwise(raw).alias("estimate"))


def dominated(regs: DataFrame, n: int) -> DataFrame:
    """(d, r): no register of combination ``d`` exceeds that of ``r``; d and r may be equal.

    Register by register, the combinations that reach a value are one mask: an OR over the register's entries from the largest
    value down. A combination keeps those that are in the masks of all its registers. So entries meet in one shuffle by register,
    whatever the number of candidates, and no pair of combinations is formed before the end.
    """
    words = range(max(1, -(-n // 64)))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("combo") % 64).cast("int"))
    down = Window.partitionBy("bucket").orderBy(F.desc("rho")).rangeBetween(Window.unboundedPreceding, Window.currentRow)
    reach = regs.select("combo", "bucket", "rho", *(F.when(F.floor(F.col("combo") / 64) == w, bit).otherwise(F.lit(0).cast("long")).alias(f"b{w}") for w in words))
    reach = reach.select("combo", *(F.bit_or(f"b{w}").over(down).alias(f"w{w}") for w in words))
    meet = reach.groupBy("combo").agg(*(F.bit_and(f"w{w}").alias(f"w{w}") for w in words))
    every = regs.sparkSession.range(n, numPartitions=1).select(F.col("id").cast("int").alias("d"))
    meet = every.join(F.broadcast(meet.withColumnRenamed("combo", "d")), "d", "left").withColumns({f"w{w}": F.coalesce(f"w{w}", F.lit(-1).cast("long")) for w in words})
    ref = F.filter(F.sequence(F.lit(0), F.lit(n - 1)), lambda x: has_bit([f"w{w}" for w in words], x))
    return meet.select("d", F.explode(ref).alias("r"))


def check(candidates: DataFrame, filled: DataFrame, n: int, members: str = "bits") -> DataFrame:
    """``candidates(d, r, ...)`` that neither structure rejects, with ``decided_by``: which had something to say of the dependent side."""
    hits = filled.filter("hit").select(F.col("combo").alias("attr"), F.col("k").alias("v"))
    if members == "set":
        sets = hits.groupBy("v").agg(F.collect_set("attr").alias("m")).select("m").distinct()
        bad = sets.select(F.explode("m").alias("d"), "m").join(candidates.select("d", "r"), "d").filter(~F.array_contains("m", F.col("r"))).select("d", "r").distinct()
        left = candidates.join(bad, ["d", "r"], "left_anti")
    else:
        left = candidates.join(bitset(hits, n).withColumnsRenamed({"dep": "d", "ref": "r"}), ["d", "r"], "left_semi")
    left = left.join(dominated(registers(filled), n), ["d", "r"], "left_semi")
    has = filled.groupBy(F.col("combo").alias("d")).agg(F.bool_or("hit").alias("i"), F.bool_or(~F.col("hit")).alias("s"))
    by = F.when(F.col("i") & F.col("s"), "both").when(F.col("i"), "index").when(F.col("s"), "sketch").otherwise("empty")
    return left.join(F.broadcast(has), "d", "left").withColumn("decided_by", by).drop("i", "s")


def fill_arrays(hashed: dict[str, DataFrame], combos: list[tuple[int, ...]], keys: np.ndarray, catalog: Catalog, lgk: int, width: int = 64) -> DataFrame:
    """(combo, part, data): the level of ``fill`` as arrays, a row a task, a combination and a part of its registers (a byte each); part -1 has the index entries' hashes.

    A task holds an array of all registers of a combination and raises them in place, so what leaves it grows with registers and not with rows.
    ``keys`` is sorted.
    """
    size, low = 1 << min(lgk, PART_LGK), np.uint64((1 << lgk) - 1)
    may = np.zeros(1 << lgk, bool)  # registers that an index key would go to: few rows are looked up among the keys
    may[(keys.view(np.uint64) & low).astype(np.int64)] = True

    def filler(names: list[str], mine: list[tuple[int, list[str]]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            regs = {c: np.zeros(1 << lgk, np.uint8) for c, _ in mine}
            hits = {c: np.empty(0, np.int64) for c, _ in mine}
            for b in batches:
                null = {n: x.is_null().to_numpy(zero_copy_only=False) for n, x in zip(names, b.columns, strict=True) if x.null_count}
                data = {n: x.fill_null(0).to_numpy().view(np.uint64) for n, x in zip(names, b.columns, strict=True)}
                folds: dict[tuple[str, ...], np.ndarray] = {(n,): x for n, x in data.items()}
                for c, cols in mine:
                    for j in range(2, len(cols) + 1):  # from the fold of its prefix, which combinations share
                        if (prefix := tuple(cols[:j])) not in folds:
                            folds[prefix] = _fold([folds[prefix[:-1]], data[cols[j - 1]]], width)
                    h = folds[tuple(cols)]
                    if some := [null[n] for n in cols if n in null]:
                        h = h[~np.any(some, axis=0)]
                    where = (h & low).astype(np.int64)
                    if len(keys) and len(ask := np.flatnonzero(may[where])):
                        s = h[ask].view(np.int64)
                        hit = keys[np.minimum(np.searchsorted(keys, s), len(keys) - 1)] == s
                        hits[c] = np.union1d(hits[c], s[hit])
                        miss = np.ones(len(h), bool)
                        miss[ask[hit]] = False
                        h, where = h[miss], where[miss]
                    x = h >> np.uint64(lgk)
                    p = np.where(x == 0, width - lgk + 1, np.bitwise_count(x ^ (x - np.uint64(1)))).astype(np.uint8)
                    np.maximum.at(regs[c], where, p)
            for c, _ in mine:
                rows = [(-1, hits[c].tobytes())] if len(hits[c]) else []
                rows += [(k, part.tobytes()) for k, part in enumerate(regs[c].reshape(-1, size)) if part.any()]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array([c] * len(rows), pa.int32()), pa.array([k for k, _ in rows], pa.int32()), pa.array([x for _, x in rows], pa.binary())], names=["combo", "part", "data"])

        return run

    parts = []
    for name, df in hashed.items():
        every = combo_folds(name, combos, catalog)
        for at in range(0, len(every), ARRAYS_AT_ONCE):
            mine = every[at : at + ARRAYS_AT_ONCE]
            names = sorted({x for _, cols in mine for x in cols})
            parts.append(df.select(*names).mapInArrow(filler(names, mine), ARRAYS))
    return reduce(DataFrame.unionByName, parts)


def refuted(arrays: DataFrame, pairs: list[tuple[int, int]]) -> DataFrame:
    """(d, r): those of ``pairs`` that the index entries or the registers of ``fill_arrays`` reject; tasks meet by part, and a pair may come from several."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        live, bad, now = set(pairs), [], None

        def settle() -> None:
            for d, r in sorted(live) if held else ():
                if d not in held:
                    continue
                lost = r not in held or (len(np.setdiff1d(held[d], held[r], assume_unique=True)) if now == -1 else (held[d] > held[r]).any())
                if lost:
                    live.discard((d, r))
                    bad.append((d, r))

        for b in batches:
            for c, part, data in zip(*(x.to_pylist() for x in b.columns), strict=True):
                if part != now:
                    settle()
                    held, now = {}, part
                one = np.frombuffer(data, np.int64 if part == -1 else np.uint8)
                held[c] = one if c not in held else np.union1d(held[c], one) if part == -1 else np.maximum(held[c], one)
        settle()
        if bad:
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int32()) for x in zip(*bad, strict=True)], names=["d", "r"])

    return arrays.repartition("part").sortWithinPartitions("part", "combo").mapInArrow(run, "d int, r int")


def level_check(catalog: Catalog, hashed: dict[str, DataFrame], samples: dict[str, DataFrame] | None, lgk: int, engine: str, members: str, width: int, arrays: bool = False) -> Callable[[DataFrame, list[tuple[int, ...]]], DataFrame]:
    """Validation of one lattice level; ``samples`` None is no index at all.

    Tuples hardly repeat, so the entries of a level of several columns are nearly as many as rows times combinations. With ``arrays`` registers are arrays instead, if
    engine and members are left to their defaults and the level has no more than ``LOCAL_ROWS`` candidates and ``BROADCAST_KEYS`` index keys.
    """

    def run(candidates: DataFrame, combos: list[tuple[int, ...]]) -> DataFrame:
        keys = index_keys(samples, combos, catalog, width) if samples is not None else None
        if arrays and engine == "sql" and members == "bits":
            rows = candidates.select("dep_table", "ref_table", "dep", "ref").limit(LOCAL_ROWS + 1).collect()
            local = np.empty(0, np.int64) if keys is None else np.sort(keys.limit(BROADCAST_KEYS + 1).toArrow()["h"].to_numpy())
            if len(rows) <= LOCAL_ROWS and len(local) <= BROADCAST_KEYS:
                number = {c: k for k, c in enumerate(combos)}
                of = {(number[tuple(r["dep"])], number[tuple(r["ref"])]): tuple(r) for r in rows}
                bad = {tuple(x) for x in refuted(fill_arrays(hashed, combos, local, catalog, lgk, width), list(of)).collect()}
                return candidates.sparkSession.createDataFrame([r for pair, r in of.items() if pair not in bad], LEVEL)
        keys = written(keys, "keys") if keys is not None else None
        filled = written(fill(hashed, combos, keys, catalog, lgk, engine, width), "filled")
        return check(with_combo_ids(candidates, combos), filled, len(combos), members).select("dep_table", "ref_table", "dep", "ref")

    return run


def approx_inds(
    catalog: Catalog, sample_n: int | None = 500, hll_error: float | None = 0.001, max_arity: int | None = 1, nulls: str = "equal", typed: bool = False,
    members: str = "bits", engine: str = "sql", fn: str = "xx", lgk: int | None = None, max_candidates: int = 1_000_000,
) -> tuple[DataFrame, list[dict[str, int]]]:
    """All levels of dependencies that the sketch method accepts.

    ``sample_n`` 0 leaves out the index; None takes all rows into it (an exact index on hashes). ``lgk`` overrides ``hll_error``.
    """
    width = 60 if fn == "md5" else 64
    hashed = hash_tables(catalog, fn, nulls, keep=True)
    samples = None if sample_n == 0 else {k: v if sample_n is None else written(sample_rows(v, sample_n, width), "sample") for k, v in hashed.items()}
    run = level_check(catalog, hashed, samples, lgk or lgk_for(hll_error), engine, members, width, max_arity != 1)
    first = as_level(unary(catalog, typed), catalog)
    return climb(run(first, [(a.id,) for a in catalog.attributes]), run, max_arity, max_candidates, catalog.element_ids)
