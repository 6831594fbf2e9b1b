"""Exact top-k by inner product: the threshold algorithm over sorted per-dimension lists.

Rows are dealt into blocks; a block keeps, for each dimension, its rows sorted by their component. For a query the lists
are read in step from their better end (the upper one where the query's component is positive, the lower one where it
is negative); rows seen for the first time get their whole score. After each step no unseen row can score more than the
sum over dimensions of the query's component times the list's value at that depth; the search stops as soon as that
bound is below the k-th best score found. Reading goes on while the bound equals it, so ties to the smaller id are
exact. The best k of all blocks are merged by a ranked window that keeps k rows a task and query.

Components are turned into whole numbers, floor(scale * x), below 2^53; scores are 64-bit integers and must fit them.

Defined cases: vectors that are null or hold null or non-finite components, and null ids, take no part; vectors of
different dimensions aren't compared; a query's own row is no candidate (rows that repeat its id aren't either); fewer
candidates than k give fewer ranks. Tables without queries or candidates give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import written
from .vector_blocks import load, write_blocks


class SortedLists:
    """One block's per-dimension lists."""

    def __init__(self, ids: np.ndarray, x: np.ndarray):
        order = np.argsort(ids, kind="stable")
        self.ids, self.x = ids[order], np.ascontiguousarray(x[order])  # whole numbers, as doubles
        self.most = np.abs(self.x).max(initial=0)
        self.up = np.argsort(self.x, axis=0, kind="stable").T.astype("i4")  # rows from the smallest component on, a list for each dimension
        self.value = np.take_along_axis(self.x.T, self.up.astype("i8"), axis=1)

    def scores(self, rows: np.ndarray, q: np.ndarray) -> np.ndarray:
        """Whole scores of rows: in doubles where these are exact, else in 64-bit integers."""
        if self.most * np.abs(q).sum() < 2.0**53:
            return self.x[rows] @ q if 4 * len(rows) < len(self.x) else (self.x @ q)[rows]
        return self.x[rows].astype("i8") @ q.astype("i8")

    def search(self, own: int, q: np.ndarray, k: int, first: int = 32) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores of the block's best k for query ``q``, the better and then smaller ids first."""
        n = len(self.x)
        high, low = np.flatnonzero(q > 0), np.flatnonzero(q < 0)
        seen = self.ids == own
        best = np.empty(0, "i8")
        score = np.empty(0, self.scores(best, q).dtype)
        depth, step = 0, first if len(high) + len(low) else n
        while depth < n:
            stop = min(n, depth + step)
            new = np.zeros(n, bool)
            if stop == n:
                new[:] = True
            else:
                new[self.up[high, n - stop : n - depth]] = True
                new[self.up[low, depth:stop]] = True
            rows = np.flatnonzero(new & ~seen)
            seen |= new
            got = self.scores(rows, q)
            if len(got) > k:  # ties at the k-th place stay
                fine = got >= np.partition(got, len(got) - k)[len(got) - k]
                rows, got = rows[fine], got[fine]
            best, score = np.concatenate([best, rows]), np.concatenate([score, got])
            keep = np.lexsort((best, -score))[:k]  # rows are in order of ids
            best, score = best[keep], score[keep]
            depth, step = stop, step * 4
            if depth < n and len(best) == k:
                bound = self.value[high, n - depth] @ q[high] + self.value[low, depth - 1] @ q[low]
                if bound < score[-1] - 1e-6 * abs(bound):
                    break
        return self.ids[best], score.astype("i8")


def search(vectors: DataFrame, queries: DataFrame, k: int = 5, scale: int = 256, rows_per_block: int = 8192, queries_per_block: int = 1024) -> DataFrame:
    """(query_id, rank, vec_id, score): for each row of ``queries`` its k best rows of ``vectors`` (both vec_id, embedding)."""
    spark = vectors.sparkSession

    def whole(df: DataFrame) -> DataFrame:
        fine = F.forall("embedding", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
        rows = df.filter(F.col("vec_id").isNotNull() & F.coalesce(fine, F.lit(False)))
        return rows.select(F.col("vec_id").cast("long").alias("id"), F.transform("embedding", lambda v: F.floor(v.cast("double") * scale)).alias("vec")).filter(F.size("vec") > 0)

    def numbered(blocks: DataFrame) -> DataFrame:
        return written(blocks.select("path", F.row_number().over(Window.orderBy("path")).alias("no")), "topk-numbered")  # a row a block

    rows, asked = written(whole(vectors), "topk-rows"), written(whole(queries), "topk-queries")
    found = None
    for dim in [r[0] for r in asked.select(F.size("vec").alias("d")).distinct().collect()]:
        at = F.size("vec") == dim
        mine = numbered(write_blocks(rows.filter(at), ["id"], rows_per_block, "topk-blocks"))
        theirs = numbered(write_blocks(asked.filter(at).coalesce(max(1, -(-asked.count() // queries_per_block))), ["id"], queries_per_block, "topk-asked"))
        # every block of rows meets every block of queries: pairs of file names, made by number
        each = mine.select(F.col("path").alias("block"), F.explode(F.sequence(F.lit(1), F.lit(theirs.count()))).alias("no"))
        pairs = each.join(theirs.select("no", F.col("path").alias("asked")), "no")
        pairs = pairs.repartition(4 * int(spark.conf.get("spark.sql.shuffle.partitions")), "block", "asked").sortWithinPartitions("block")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            name, lists = None, None
            for batch in batches:
                for p in batch.to_pylist():
                    if p["block"] != name:
                        data = load(p["block"])
                        name, lists = p["block"], SortedLists(data["id"], data["vec"])
                    q = load(p["asked"])
                    out = [lists.search(int(i), v, k) for i, v in zip(q["id"], q["vec"], strict=True)]
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(q["id"], [len(o[0]) for o in out])), pa.array(np.concatenate([o[0] for o in out])), pa.array(np.concatenate([o[1] for o in out]))], names=["query_id", "vec_id", "score"])

        got = pairs.mapInArrow(run, "query_id long, vec_id long, score long")
        found = got if found is None else found.unionByName(got)
    if found is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
