"""MinHash near-duplicates with set-sketch registers.

A document's sketch has m registers: for register j the least of one exponential variable for each shingle, on an
exponentially spaced integer scale, floor(1 - log_b(min)), truncated to [0, q+1]. Registers of a union are the larger
ones of each register, so sketches merge; for b close to 1 two sketches agree in a register with a probability close to
the Jaccard similarity. Registers are banded; documents that share a band are candidates, a maximum-likelihood estimate
of the similarity from registers larger, smaller and equal drops those clearly below the threshold, and the rest is
verified on the full sets.

The number of bands follows from the threshold so that a pair just at it is missed with a probability below ``miss``; the
estimate has a margin of five standard deviations. Sets are of 64-bit shingle numbers that rest on a keyed cryptographic digest of
each word, so full sets stand for the texts' own shingles.

Groups of copies: documents with equal sets are one node. In a band bucket all members are first compared with the
smallest one only; then, once components are known, members of different components are compared, each pair in the
first band that it shares; the members of a bucket's largest component meet only the others. Buckets of up to ``SMALL`` members give out pairs, a few a member; larger ones are compared
in square blocks of bounded size: first by sketches, giving out the members that have a likely link, then these by
their full sets, giving out a spanning forest of the links verified. So a bucket of thousands of copies costs a few rows
each, and no link between components is lost.

Defined cases: null and empty texts and those of white space have an empty set and link with nothing; a null id
links with nothing (its row has a null component and is kept); rows that repeat an id are one node. An empty table
gives no rows. Extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bpe
from .common import components, discard, may_match, release, without, written
from .embedding_dups import forest
from .shingles import forget, in_chunks, mix

BASE, RATE, TOP = 1.001, 20.0, 65534  # b, a and q of the registers, for 16 bits each
ROWS = 5  # registers in a band
SMALL = 8  # members of a bucket whose pairs may be given out
BLOCK = 1024  # about how many members of a larger one a comparison holds on each side
ITEMS = 1 << 20  # and about how many shingles these have


def bands_for(threshold: float, miss: float = 1e-6, rows: int = ROWS) -> int:
    """Bands needed so that a pair of similarity ``threshold`` shares none with a probability below ``miss``."""
    return math.ceil(math.log(miss) / math.log1p(-(threshold**rows)))


def _functions(m: int) -> tuple[np.ndarray, np.ndarray]:
    seeds = mix(np.arange(1, 2 * m + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    return seeds[:m] | np.uint64(1), seeds[m:]


def registers(sets: list[np.ndarray], m: int) -> np.ndarray:
    """Registers of each set, a row each; an empty set has zeros."""
    out = np.zeros((len(sets), m), "<u2")
    full = [k for k, s in enumerate(sets) if len(s)]
    if not full:
        return out
    times, flips = _functions(m)
    least = np.empty((len(full), m), np.uint64)
    group: list[int] = []
    held = 0

    def sketch(ks: list[int]) -> None:
        h = np.concatenate([sets[full[k]] for k in ks])
        starts = np.cumsum([0, *(len(sets[full[k]]) for k in ks[:-1])])
        buf = np.empty_like(h)
        for j in range(m):
            np.bitwise_xor(h, flips[j], out=buf)
            np.multiply(buf, times[j], out=buf)
            least[ks[0] : ks[-1] + 1, j] = np.minimum.reduceat(buf, starts)

    for k, at in enumerate(full):
        group.append(k)
        held += len(sets[at])
        if held >= 50_000:
            sketch(group)
            group, held = [], 0
    if group:
        sketch(group)
    x = -np.log1p(-(least.astype("f8") + 0.5) / 2.0**64) / RATE
    out[full] = np.clip(np.floor(1 - np.log(x) / math.log(BASE)), 0, TOP + 1)
    return out


def band_keys(regs: np.ndarray, rows: int = ROWS) -> np.ndarray:
    """64-bit keys of the bands, a row for each sketch; the band's number is part of its key."""
    parts = regs.astype(np.uint64).reshape(len(regs), -1, rows)
    key = np.broadcast_to(np.arange(1, parts.shape[1] + 1, dtype=np.uint64), parts.shape[:2])
    for j in range(rows):
        key = mix(key * np.uint64(0x9E3779B97F4A7C15) + parts[:, :, j])
    return key.view("i8")


def similarity(n1: np.ndarray, n2: np.ndarray, more: np.ndarray, less: np.ndarray, m: int) -> np.ndarray:
    """Maximum-likelihood Jaccard similarity from set sizes and the counts of larger and smaller registers, on a grid of 201."""
    grid = np.linspace(0, 1, 201)[None, :]
    u = (n1 / (n1 + n2))[:, None]
    v = 1 - u
    top = np.minimum(u / v, v / u)
    j = grid * top
    p = lambda x: -np.log1p(-np.clip(x, 1e-12, 1) * (BASE - 1) / BASE) / math.log(BASE)
    up, down = p(u - v * j), p(v - u * j)
    score = more[:, None] * np.log(up) + less[:, None] * np.log(down) + (m - more - less)[:, None] * np.log(np.clip(1 - up - down, 1e-12, 1))
    return j[np.arange(len(j)), score.argmax(1)]


def sketches(docs: DataFrame, k: int, m: int) -> DataFrame:
    """(doc_id, n, fp, regs): size of the set, a 128-bit fingerprint of it, and its registers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe.forget()
        for batch in batches:
            at = 0
            texts = (t for s in range(0, batch.num_rows, 256) for t in batch.column(1).slice(s, 256).to_pylist())
            for sets in in_chunks(texts, k):
                fps = [blake2b(s, digest_size=16).digest() for s in sets]  # of the sorted set
                regs = registers(sets, m)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(sets)), pa.array([len(s) for s in sets], pa.int64()), pa.array(fps, pa.binary()), pa.array([r.tobytes() for r in regs], pa.binary())], names=["doc_id", "n", "fp", "regs"])
                at += len(sets)
        forget()

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n long, fp binary, regs binary")


def full_sets(docs: DataFrame, k: int) -> DataFrame:
    """(doc_id, items): the whole shingle set of each document, in ascending order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe.forget()
        for batch in batches:
            at = 0
            texts = (t for s in range(0, batch.num_rows, 256) for t in batch.column(1).slice(s, 256).to_pylist())
            for sets in in_chunks(texts, k):
                ends = np.cumsum([0, *map(len, sets)]).astype("i4")
                items = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([np.sort(x.view("i8")) for x in sets])))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(sets)), items], names=["doc_id", "items"])
                at += len(sets)
        forget()

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, items array<long>")


def _likely(pairs: DataFrame, reps: DataFrame, percent: int, m: int) -> DataFrame:
    """``pairs(a, b)`` whose sizes allow the threshold and whose estimated similarity is within the margin of it."""
    one = reps.select(F.col("rep").alias("a"), F.col("n").alias("n1"), F.col("regs").alias("r1"))
    two = reps.select(F.col("rep").alias("b"), F.col("n").alias("n2"), F.col("regs").alias("r2"))
    sized = pairs.join(one, "a").join(two, "b").filter(100 * F.least("n1", "n2") >= percent * F.greatest("n1", "n2"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 2000):
                b = whole.slice(at, 2000)
                r1, r2 = (np.frombuffer(b"".join(b.column(c).to_pylist()), "<u2").reshape(-1, m) for c in ("r1", "r2"))
                n1, n2 = (b.column(c).to_numpy().astype("f8") for c in ("n1", "n2"))
                ok = similarity(n1, n2, (r1 > r2).sum(1), (r1 < r2).sum(1), m) >= _least(percent, m)
                yield pa.RecordBatch.from_arrays([c.filter(pa.array(ok)) for c in (b.column("a"), b.column("b"))], names=["a", "b"])

    return sized.select("a", "b", "n1", "n2", "r1", "r2").mapInArrow(run, "a long, b long")


def _least(percent: int, m: int) -> float:
    t = percent / 100
    return t - 5 * math.sqrt(t * (1 - t) / m)


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """``pairs(a, b)`` whose full sets reach the threshold, in whole numbers."""
    one = sets.select(F.col("doc_id").alias("a"), F.col("items").alias("s1"))
    two = sets.select(F.col("doc_id").alias("b"), F.col("items").alias("s2"))
    both = pairs.join(one, "a").join(two, "b").withColumn("_i", F.size(F.array_intersect("s1", "s2")))
    return both.filter(100 * F.col("_i") >= percent * (F.size("s1") + F.size("s2") - F.col("_i"))).select("a", "b")


def _spread(members: DataFrame) -> DataFrame:
    """``members(band, no, major, many, items, rep, comp, n)`` dealt to blocks (i, j) of their bucket's sides, ``_at`` being a member's side.

    ``major`` marks the members of the bucket's largest component, of which no two are compared; ``many`` and ``items`` count
    each kind's members and shingles. Sides 0 to I - 1 hold the others, sides I to I + J - 1 the largest component: the
    others meet all sides, the largest component only theirs.
    """
    blocks = lambda k: F.greatest(F.ceil(F.col("many")[k] / BLOCK), F.ceil(F.col("items")[k] / ITEMS)).cast("int")
    at = members.withColumns({"_i": blocks(0), "_j": blocks(1)})
    side = lambda n: F.pmod(F.xxhash64("rep"), n).cast("int")
    at = at.withColumn("_at", F.when(F.col("major"), F.col("_i") + side(F.col("_j"))).otherwise(side(F.col("_i"))))
    meets = F.sequence(F.lit(0), F.when(F.col("major"), F.col("_i")).otherwise(F.col("_i") + F.col("_j")) - 1)
    pairs = F.transform(meets, lambda x: F.struct(F.least(x, F.col("_at")).alias("i"), F.greatest(x, F.col("_at")).alias("j")))
    return at.withColumn("_pair", F.explode(pairs)).select("band", F.col("_pair.i").alias("i"), F.col("_pair.j").alias("j"), "no", "_at", "rep", "comp", "n")


_KEPT = pa.schema([("band", pa.int64()), ("i", pa.int32()), ("j", pa.int32()), ("no", pa.int32()), ("_at", pa.int32()), ("rep", pa.int64()), ("comp", pa.int64()), ("n", pa.int64())])


def _across(spread: DataFrame, percent: int, m: int, give: str) -> DataFrame:
    """Likely links between different components inside the blocks of ``spread`` (with ``regs``).

    ``give``: the ``pairs`` (a, b); only the ``members`` that have one, as rows of ``spread``; or, with the full sets in
    ``items``, a ``forest`` (a, b) of the links that these verify.
    """
    least = _least(percent, m)

    def run(t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        i, j, no = (t.column(c)[0].as_py() for c in ("i", "j", "no"))
        at, rep, comp, n = (t.column(c).to_numpy() for c in ("_at", "rep", "comp", "n"))
        regs = np.frombuffer(b"".join(t.column("regs").to_pylist()), "<u2").reshape(-1, m)
        if give == "forest":
            flat, off = t.column("items").combine_chunks().flatten().to_numpy(), np.concatenate([[0], np.cumsum(n)])
        left, right = np.flatnonzero(at == i), np.flatnonzero(at == j)
        out: list[np.ndarray] = []
        for x in left:
            ok = right[(comp[right] != comp[x]) & ((rep[right] > rep[x]) if i == j else True) & (100 * np.minimum(n[right], n[x]) >= percent * np.maximum(n[right], n[x]))]
            same = (regs[x] == regs[ok]).reshape(len(ok), -1, ROWS).all(2) if len(ok) else None
            ok = ok[same.argmax(1) == no] if len(ok) else ok  # each pair once, in the first band that it shares
            if len(ok):
                more, less = (regs[x] > regs[ok]).sum(1), (regs[x] < regs[ok]).sum(1)
                ok = ok[similarity(np.full(len(ok), float(n[x])), n[ok].astype("f8"), more, less, m) >= least]
            if give == "forest" and len(ok):
                own = flat[off[x] : off[x + 1]]
                both = np.asarray([(own[np.minimum(np.searchsorted(own, theirs), len(own) - 1)] == theirs).sum() for theirs in (flat[off[y] : off[y + 1]] for y in ok)])
                ok = ok[100 * both >= percent * (n[x] + n[ok] - both)]
            if len(ok):
                out.append(np.stack([np.full(len(ok), x), ok]))
        found = np.concatenate(out, axis=1) if out else np.empty((2, 0), int)
        if give == "members":
            return t.select(_KEPT.names).take(pa.array(np.unique(found))).cast(_KEPT)
        a, b = rep[found[0]], rep[found[1]]
        if give == "forest" and len(a):
            a, b = forest(a, b)
        return pa.table({"a": pa.array(np.minimum(a, b), pa.int64()), "b": pa.array(np.maximum(a, b), pa.int64())})

    if give == "members":
        return spread.groupBy("band", "i", "j").applyInArrow(run, "band long, i int, j int, no int, _at int, rep long, comp long, n long")
    return spread.groupBy("band", "i", "j").applyInArrow(run, "a long, b long").distinct()


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80, miss: float = 1e-6) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of ``docs(doc_id, text)``; links hold at ``percent`` % Jaccard similarity or more."""
    bands = bands_for(percent / 100, miss)
    m = bands * ROWS
    all_ = written(sketches(docs, k, m), "sketches")
    known = all_.filter("n > 0 and doc_id is not null")
    reps = written(known.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.first("n").alias("n"), F.first("regs").alias("regs")), "reps")
    ids = written(all_.select("doc_id", "n", "fp"), "ids")
    discard(all_)

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 2000):
                b = whole.slice(at, 2000)
                got = band_keys(np.frombuffer(b"".join(b.column(1).to_pylist()), "<u2").reshape(-1, m))
                rep, n = (np.repeat(b.column(c).to_numpy(), bands) for c in ("rep", "n"))
                yield pa.RecordBatch.from_arrays([pa.array(got.ravel()), pa.array(np.tile(np.arange(bands, dtype="i4"), len(got))), pa.array(rep), pa.array(n)], names=["band", "no", "rep", "n"])

    banded = reps.select("rep", "regs", "n").mapInArrow(keys, "band long, no int, rep long, n long")
    # a band of one member needs nothing more; the others are few
    shared = banded.groupBy("band").agg(F.min("rep").alias("hub"), F.count(F.lit(1)).alias("total")).filter("total > 1")
    shared = written(shared, "bands")
    members = written(may_match(banded, "band", shared.select("band")).filter("_may").drop("_may").join(shared, "band"), "members")
    discard(shared)
    some = written(members.select(F.col("rep").alias("doc_id")).distinct(), "candidates")
    # registers are needed further for candidates only
    named = some.withColumnRenamed("doc_id", "rep")
    sketch = written(may_match(reps.select("rep", "n", "regs"), "rep", named).filter("_may").drop("_may").join(named, "rep", "left_semi"), "registers")
    sames = written(reps.select("fp", "rep"), "same-sets")
    discard(reps)
    text = may_match(docs.select(F.col("doc_id").cast("long"), "text"), "doc_id", some).filter("_may").drop("_may").join(some, "doc_id", "left_semi")
    sets = written(full_sets(text, k), "sets")
    star = written(_likely(members.filter("hub <> rep").select(F.col("hub").alias("a"), F.col("rep").alias("b")).distinct(), sketch, percent, m), "stars")
    links = written(_verified(star, sets, percent), "links")
    label = written(components(links), "labels")
    marked = members.join(label.withColumnRenamed("node", "rep"), "rep", "left").withColumn("comp", F.coalesce("component", "rep")).drop("component")
    sums = marked.groupBy("band", "comp").agg(F.count(F.lit(1)).alias("c"), F.sum("n").alias("s"))
    open_ = sums.groupBy("band").agg(F.max(F.struct("c", "s", "comp")).alias("_top"), F.sum("c").alias("_c"), F.sum("s").alias("_s")).filter("_c > _top.c")
    open_ = written(open_.select("band", F.col("_top.comp").alias("_most"), F.array(F.col("_c") - F.col("_top.c"), "_top.c").alias("many"), F.array(F.col("_s") - F.col("_top.s"), "_top.s").alias("items")), "open-bands")
    rest = marked.join(open_, "band").withColumn("major", F.col("comp") == F.col("_most"))
    rest = written(rest.select("band", "no", "total", "major", "many", "items", "rep", "comp", "n"), "open")
    regs = sketch.select("rep", "regs")
    pairs = written(_across(_spread(rest.filter(F.col("total") <= SMALL)).join(regs, "rep"), percent, m, "pairs").join(star, ["a", "b"], "left_anti"), "across")
    likely = written(_across(_spread(rest.filter(F.col("total") > SMALL)).join(regs, "rep"), percent, m, "members"), "across")
    within = likely.join(regs, "rep").join(sets.withColumnRenamed("doc_id", "rep"), "rep")
    first, links = links, written(links.unionByName(_verified(pairs, sets, percent)).unionByName(_across(within, percent, m, "forest")), "links")
    discard(first, label, sets, sketch)
    label = written(components(links), "labels")
    of_set = sames.join(label.withColumnRenamed("node", "rep"), "rep", "left").select("fp", F.coalesce("component", "rep").alias("component"))
    lone = ids.filter("n = 0 or doc_id is null").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    grouped = ids.filter("n > 0 and doc_id is not null").join(of_set, "fp").select("doc_id", F.col("n").alias("n_shingles"), F.col("component").alias("component_id"))
    out = written(grouped.unionByName(lone).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id"))), "near-dups")
    discard(ids, sames, members, some, star, open_, rest, pairs, likely, links, label)
    release(docs.sparkSession)
    return out


def drop_near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` without the documents that are not the smallest id of their component; all columns stay."""
    gone = written(near_duplicates(docs, k, percent).filter("not kept").select("doc_id").distinct(), "dropped")
    return without(docs, "doc_id", gone)
