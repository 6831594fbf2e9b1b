"""Embedding near-duplicates by PCA-ordered tiled comparison.

Vectors are scaled to length one and turned into the eigenvectors of their second moments, largest first, so leading
dimensions carry most of a product. Tiles of two blocks are compared on leading dimensions first; what the remaining ones can
add is at most the product of the two suffix norms, and a pair is dropped as soon as the cosine cannot reach the
threshold. Survivors get more dimensions, and at last the whole product. Rotated products only drop pairs, or take those
that are above the threshold by more than rounding can do (``SLACK``); all others are decided by the cosine of the vectors as given,
in double precision: their product over the product of their norms.

Equal vectors are one class, compared once with their number as weight. A tile doesn't give out its links: it counts
them for each vector and gives a spanning forest of them, at most one edge a vector, so dense groups cost a row a vector
and a tile.

Defined cases: vectors that are null, zero, or hold null or non-finite components link with nothing; so do vectors of
another dimension than the most frequent one's with those of it (each dimension is compared apart). A null id links with nothing.
Rows that repeat an id are counted as vectors of their own and share the id's component. An empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import components, written
from .vector_blocks import load, write_blocks

STEPS = (8, 16, 32)
SLACK = 1e-9
TILE = 512


def usable(vec: str = "embedding"):
    """True for vectors without null or non-finite components and with a component that isn't zero."""
    x = F.col(vec)
    fine = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    return F.coalesce(fine & F.exists(x, lambda v: v != 0), F.lit(False))


def second_moments(rows: DataFrame) -> np.ndarray:
    """Sum of x x' over unit vectors of ``rows(vec)``: partial sums by task, one small matrix from each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for b in batches:
            if b.num_rows:
                x = scaled(b.column(0).flatten().to_numpy(zero_copy_only=False).astype("f8").reshape(b.num_rows, -1))
                x /= np.linalg.norm(x, axis=1, keepdims=True)
                total = x.T @ x if total is None else total + x.T @ x
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array(range(total.size), pa.int32()), pa.array(total.ravel())], names=["k", "v"])

    cells = rows.mapInArrow(run, "k int, v double").groupBy("k").agg(F.sum("v").alias("v")).orderBy("k").collect()  # dimension squared
    return np.asarray([r["v"] for r in cells]).reshape(int(len(cells) ** 0.5), -1)


def _suffix(x: np.ndarray) -> list[np.ndarray]:
    """Norms of the components from each step on."""
    return [np.linalg.norm(x[:, s:], axis=1) for s in STEPS if s < x.shape[1]]


def scaled(x: np.ndarray) -> np.ndarray:
    """Rows times a power of two each, so that squares neither overflow nor vanish; no digit changes."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(axis=1, keepdims=True))[1])


def cosines(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Of each row of ``a`` with that of ``b``, the same whatever else is in them."""
    dot = lambda x, y: np.einsum("ij,ij->i", x, y)
    return dot(a, b) / (np.sqrt(dot(a, a)) * np.sqrt(dot(b, b)))


def tile_links(a: np.ndarray, b: np.ndarray, sa: list[np.ndarray], sb: list[np.ndarray], own: tuple[np.ndarray, np.ndarray], threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Row numbers (of ``a``, of ``b``) of the pairs whose cosine reaches the threshold; ``own`` has their vectors as given."""
    steps = [s for s in STEPS if s < a.shape[1]]
    stop = steps[0] if steps else a.shape[1]
    part = a[:, :stop] @ b[:, :stop].T
    r, c = np.nonzero(part + (np.outer(sa[0], sb[0]) if steps else 0) >= threshold - SLACK)
    if steps and len(r) > 0.1 * part.size:  # too many to gather: the whole tile at once
        steps, part = [], a @ b.T
        r, c = np.nonzero(part >= threshold - SLACK)
    got = part[r, c]
    for k, s in enumerate(steps):
        stop = steps[k + 1] if k + 1 < len(steps) else a.shape[1]
        got += np.einsum("ij,ij->i", a[r, s:stop], b[c, s:stop])
        ok = got + (sa[k + 1][r] * sb[k + 1][c] if k + 1 < len(steps) else 0) >= threshold - SLACK
        r, c, got = r[ok], c[ok], got[ok]
    ok = got > threshold + SLACK
    close = np.flatnonzero(~ok)
    for at in range(0, len(close), 20_000):
        some = close[at : at + 20_000]
        ok[some] = cosines(own[0][r[some]], own[1][c[some]]) >= threshold
    return r[ok], c[ok]


def forest(r: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest, as (node, root) edges, of the graph with edges (r, c)."""
    nodes, at = np.unique(np.concatenate([r, c]), return_inverse=True)
    a, b = at[: len(r)], at[len(r) :]
    root = np.arange(len(nodes))
    while True:
        low = np.minimum(root[a], root[b])
        before = root.copy()
        np.minimum.at(root, root[a], low)
        np.minimum.at(root, root[b], low)
        while (root != (up := root[root])).any():
            root = up
        if (root == before).all():
            break
    return nodes, nodes[root]


def links(blocks: DataFrame, threshold: float, strip: int = 8) -> DataFrame:
    """(kind, a, b): for kind 'n' a vector class and a number of links, for kind 'e' an edge of a forest.

    Work is a block against a strip of ``strip`` blocks; the list of all such pairs is made by a join of block names, not on the driver.
    """
    numbered = written(blocks.select("path", (F.row_number().over(Window.orderBy("path")) - 1).alias("i")), "tiles-numbered")  # a row a block
    n = blocks.sparkSession.conf.get("spark.sql.shuffle.partitions")
    strips = numbered.withColumn("g", F.floor(F.col("i") / strip)).groupBy("g").agg(F.array_sort(F.collect_list(F.struct(F.col("i").alias("j"), F.col("path").alias("other")))).alias("others"))
    last = F.floor((numbered.agg(F.count(F.lit(1))).first()[0] - 1) / F.lit(strip))
    each = numbered.withColumn("g", F.explode(F.sequence(F.floor(F.col("i") / strip), last)))
    work = each.join(strips, "g").select("path", "i", "others").repartition(4 * int(n), "path", "others")
    fields = pa.schema([("kind", pa.string()), ("a", pa.int64()), ("b", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for w in batch.to_pylist():
                left = load(w["path"])
                la, lsuf = left["vec"], _suffix(left["vec"])
                mine = np.zeros(len(la), "i8")
                for other in w["others"]:
                    if other["j"] < w["i"]:
                        continue
                    same = other["j"] == w["i"]
                    right = left if same else load(other["other"])
                    rb, rsuf = right["vec"], _suffix(right["vec"])
                    theirs = np.zeros(len(rb), "i8")
                    ends: list[tuple[np.ndarray, np.ndarray]] = []
                    for p in range(0, len(la), TILE):
                        for q in range(p if same else 0, len(rb), TILE):
                            r, c = tile_links(la[p : p + TILE], rb[q : q + TILE], [s[p : p + TILE] for s in lsuf], [s[q : q + TILE] for s in rsuf], (left["own"][p : p + TILE], right["own"][q : q + TILE]), threshold)
                            r, c = r + p, c + q
                            if same and p == q:
                                up = c > r
                                r, c = r[up], c[up]
                            if len(r):
                                mine += np.bincount(r, right["n"][c], len(la)).astype("i8")
                                theirs += np.bincount(c, left["n"][r], len(rb)).astype("i8")
                                ends.append(forest(left["id"][r], right["id"][c]))
                    if same:
                        mine += theirs
                    elif theirs.any():
                        at = np.flatnonzero(theirs)
                        yield pa.RecordBatch.from_arrays([pa.array(["n"] * len(at)), pa.array(right["id"][at]), pa.array(theirs[at])], schema=fields)
                    if ends:
                        a, b = forest(np.concatenate([e[0] for e in ends]), np.concatenate([e[1] for e in ends]))
                        yield pa.RecordBatch.from_arrays([pa.array(["e"] * len(a)), pa.array(a), pa.array(b)], schema=fields)
                at = np.flatnonzero(mine)
                if len(at):
                    yield pa.RecordBatch.from_arrays([pa.array(["n"] * len(at)), pa.array(left["id"][at]), pa.array(mine[at])], schema=fields)

    return work.mapInArrow(run, "kind string, a long, b long")


def near_duplicates(vectors: DataFrame, threshold: float = 0.9, rows_per_block: int = 2048) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of ``vectors(vec_id, embedding)``."""
    rows = vectors.select(F.col("vec_id").cast("long"), F.transform("embedding", lambda v: v.cast("double")).alias("vec"))
    rows = rows.withColumn("_ok", usable("vec") & F.col("vec_id").isNotNull())
    rows = rows.withColumn("fp", F.when(F.col("_ok"), F.struct(F.xxhash64("vec").alias("h"), F.xxhash64(F.lit(7), "vec").alias("g"))))
    rows = written(rows, "vectors")
    good = rows.filter("_ok")
    classes = written(good.groupBy("fp").agg(F.min("vec_id").alias("id"), F.count(F.lit(1)).alias("n"), F.first("vec").alias("vec")), "classes")
    found = None
    for dim in [r[0] for r in classes.select(F.size("vec").alias("d")).distinct().orderBy("d").collect()]:
        part = classes.filter(F.size("vec") == dim)
        turn = np.linalg.eigh(second_moments(part.select("vec")))[1][:, ::-1]

        def rotate(x: np.ndarray, turn: np.ndarray = turn) -> dict[str, np.ndarray]:
            x = scaled(x)
            return {"vec": (x / np.linalg.norm(x, axis=1, keepdims=True)) @ turn, "own": x}

        got = links(write_blocks(part.select("id", "n", "vec"), ["id", "n"], rows_per_block, "tiles", rotate), threshold)
        found = got if found is None else found.unionByName(got)
    lone = rows.filter("not _ok").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    if found is None:
        return lone.withColumn("kept", F.lit(True))
    found = written(found, "links")
    label = components(found.filter("kind = 'e'").select("a", "b"))
    count = found.filter("kind = 'n'").groupBy(F.col("a").alias("id")).agg(F.sum("b").alias("others"))
    of = classes.select("fp", "id", "n").join(count, "id", "left").join(label.withColumnRenamed("node", "id"), "id", "left")
    of = of.select("fp", (F.coalesce("others", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    out = good.join(of, "fp").select("vec_id", "n_links", "component_id").unionByName(lone)
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
