"""Exact engines on the relation (attr, v): value masks, heap merge, inverted index, pairwise comparison."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import has_bit, word_masks
from ..plans import written


def bits_of(mask: int) -> Iterator[int]:
    """The numbers of the set bits."""
    while mask:
        low = mask & -mask
        yield low.bit_length() - 1
        mask ^= low


def _ids(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n, numPartitions=1).select(F.col("id").cast("int").alias("attr"))


def value_masks(values: DataFrame, n: int) -> DataFrame:
    """Distinct sets of attributes that share a value, as 64-bit words.

    OR is idempotent, so repeats of (attr, v) needn't be dropped first: one shuffle of partially combined values, then one
    of the few distinct masks.
    """
    words = word_masks(F.col("attr"), n)
    return values.groupBy("v").agg(*words).drop("v").distinct()


def bitset(values: DataFrame, n: int) -> DataFrame:
    """(dep, ref): all inclusions among attributes 0..n-1, by ANDing the masks of each attribute's values.

    An attribute without values is in no mask: nothing rules anything out for it, and it is included in all others.
    """
    spark = values.sparkSession
    masks = value_masks(values, n)
    words = [c for c in masks.columns]
    member = F.filter(F.sequence(F.lit(0), F.lit(n - 1)), lambda x: has_bit(words, x))
    each = masks.select(F.explode(member).alias("attr"), *words).groupBy("attr").agg(*(F.bit_and(w).alias(w) for w in words))
    refs = _ids(spark, n).join(F.broadcast(each), "attr", "left").withColumns({w: F.coalesce(w, F.lit(-1).cast("long")) for w in words})
    ref = F.filter(F.sequence(F.lit(0), F.lit(n - 1)), lambda x: has_bit(words, x))
    return refs.select(F.col("attr").alias("dep"), F.explode(ref).alias("ref")).filter("dep <> ref")


def merge(values: DataFrame, n: int, candidates: dict[int, set[int]] | None = None) -> tuple[DataFrame, DataFrame]:
    """(dep, ref) and counters, by a simultaneous merge of sorted columns in each part of the values.

    ``values`` must be distinct. They are dealt by hash, as ranges would first need a pass over all values for their bounds. A partition is sorted by (value,
    attribute), externally where it doesn't fit in memory, which merges its part of every column; it is read as a stream. The attributes that share the smallest value lose all references that
    aren't among them, and each loss is mirrored in the dependents of the attribute lost. An attribute with neither references nor
    dependents left is processed: its later values are passed over. Sharing sets that occurred before change nothing, so only first
    occurrences are worked on, and what lies between them is counted at once. The partitions' reference sets are intersected.
    ``candidates`` (dep to its possible refs) bounds the first sets.
    """
    spark = values.sparkSession
    start = {a: set(range(n)) - {a} if candidates is None else set(candidates.get(a, ())) for a in range(n)}
    laid = values.repartition("v").sortWithinPartitions("v", "attr")
    n_words = -(-n // 64)

    def partition(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        refs = {a: sum(1 << r for r in s) for a, s in start.items()}
        deps = {a: sum(1 << d for d, s in start.items() if a in s) for a in range(n)}
        live, present = (1 << n) - 1, 0  # attributes that aren't processed; that have values here
        seen: set[int] = set()
        steps = read = stopped = 0

        def words_of(mask: int) -> np.ndarray:
            return np.frombuffer(mask.to_bytes(8 * n_words, "little"), "<u8")

        def counted(masks: np.ndarray) -> None:
            nonlocal steps, read
            mine = masks & words_of(live)
            bits = np.bitwise_count(mine).sum(axis=1)
            steps += int((bits > 0).sum())
            read += int(bits.sum())

        def work(masks: np.ndarray) -> None:
            nonlocal live, present, stopped
            keys = np.ascontiguousarray(masks).view(f"V{8 * n_words}").ravel()
            _, first = np.unique(keys, return_index=True)
            at = 0
            for k in np.sort(first).tolist():
                sharing = int.from_bytes(masks[k].tobytes(), "little")
                if sharing in seen:
                    continue
                seen.add(sharing)
                counted(masks[at : k + 1])
                at = k + 1
                present |= sharing
                sharing &= live
                for a in bits_of(sharing):
                    for r in bits_of(refs[a] & ~sharing):
                        refs[a] &= ~(1 << r)
                        deps[r] &= ~(1 << a)
                for a in bits_of(live):
                    if not refs[a] and not deps[a]:
                        live &= ~(1 << a)
                        stopped += present >> a & 1
            counted(masks[at:])

        tail: tuple[str, np.ndarray] | None = None
        for b in batches:
            if not b.num_rows:
                continue
            attr, v = b.column(0).to_numpy(), b.column(1)
            new = np.concatenate([[True], pc.not_equal(v.slice(1), v.slice(0, len(v) - 1)).to_numpy(zero_copy_only=False)])
            at = np.flatnonzero(new)
            masks = np.stack([np.bitwise_or.reduceat(np.where(attr // 64 == w, np.uint64(1) << (attr % 64).astype(np.uint64), np.uint64(0)), at) for w in range(n_words)], axis=1)
            if tail is not None:  # the last value of the batch before may go on
                if v[0].as_py() == tail[0]:
                    masks[0] |= tail[1]
                else:
                    work(tail[1][None, :])
            tail = v[-1].as_py(), masks[-1].copy()
            work(masks[:-1])
        if tail is None:
            return
        work(tail[1][None, :])
        names = list(bits_of(present))
        rows = [(a, list(bits_of(refs[a])), steps if k == 0 else 0, read if k == 0 else 0, stopped if k == 0 else 0) for k, a in enumerate(names)]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.list_(pa.int32()), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["attr", "refs", "steps", "read", "stopped"])

    local = laid.mapInArrow(partition, "attr int, refs array<int>, steps long, read long, stopped long")
    return local, spark.createDataFrame([(a, sorted(s)) for a, s in start.items()], "attr int, first array<int>")


def merge_inds(values: DataFrame, n: int, candidates: dict[int, set[int]] | None = None) -> DataFrame:
    """(dep, ref) by the merge engine: a reference survives if every partition in which the attribute has values kept it."""
    local, first = merge(values, n, candidates)
    local = written(local, "merge")  # used more than once; the values are sorted and merged once
    ranges = local.groupBy("attr").agg(F.count(F.lit(1)).alias("ranges"))
    kept = local.select("attr", F.explode("refs").alias("ref")).groupBy("attr", "ref").agg(F.count(F.lit(1)).alias("kept"))
    full = kept.join(ranges, "attr").filter("kept = ranges").select(F.col("attr").alias("dep"), "ref")
    empty = first.join(ranges, "attr", "left_anti").select(F.col("attr").alias("dep"), F.explode("first").alias("ref"))
    return full.unionByName(empty)


def merge_counters(values: DataFrame, n: int, candidates: dict[int, set[int]] | None = None) -> DataFrame:
    """(ranges, steps, read, stopped): work of the merge engine."""
    return merge(values, n, candidates)[0].agg(F.count_if(F.col("steps") > 0).alias("ranges"), F.sum("steps").alias("steps"), F.sum("read").alias("read"), F.sum("stopped").alias("stopped"))


def inverted_sets(values: DataFrame) -> DataFrame:
    """(members, n_values): the inverted index grouped by its distinct sets of attributes."""
    index = values.groupBy("v").agg(F.array_sort(F.collect_set("attr")).alias("members"))
    return index.groupBy("members").agg(F.count(F.lit(1)).alias("n_values"))


def inverted(values: DataFrame, n: int) -> DataFrame:
    """(dep, ref) from the inverted index: the intersection of the attribute sets of a column's values.

    An attribute is in the intersection if it is in as many of the index's distinct sets with the column as there are: sets are
    counted by pair and never gathered.
    """
    each = inverted_sets(values).select(F.explode("members").alias("dep"), "members")
    pairs = each.select("dep", F.explode("members").alias("ref")).groupBy("dep", "ref").agg(F.count(F.lit(1)).alias("c"))
    own = pairs.filter("dep = ref").select("dep", F.col("c").alias("sets"))
    full = pairs.join(F.broadcast(own), "dep").filter("c = sets and dep <> ref").select("dep", "ref")
    empty = _ids(values.sparkSession, n).withColumnRenamed("attr", "dep").join(F.broadcast(own), "dep", "left_anti")
    return full.unionByName(empty.select("dep", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("ref")).filter("dep <> ref"))


def shared_counts(values: DataFrame, n: int) -> DataFrame:
    """(dep, ref, distinct_values, shared): distinct values of ``dep`` and how many of them ``ref`` has, for pairs that share any.

    Pairs are formed from the distinct attribute sets with the number of values that have them, not from values.
    """
    words = word_masks(F.col("attr"), n)
    masks = values.groupBy("v").agg(*words).drop("v")
    names = masks.columns
    masks = masks.groupBy(*names).agg(F.count(F.lit(1)).alias("n"))
    member = F.filter(F.sequence(F.lit(0), F.lit(n - 1)), lambda x: has_bit(names, x))
    sets = masks.select(member.alias("m"), "n")
    total = sets.select(F.explode("m").alias("dep"), "n").groupBy("dep").agg(F.sum("n").alias("distinct_values"))
    pairs = sets.select(F.explode("m").alias("dep"), "m", "n").select("dep", F.explode("m").alias("ref"), "n").filter("dep <> ref")
    return pairs.groupBy("dep", "ref").agg(F.sum("n").alias("shared")).join(total, "dep").select("dep", "ref", "distinct_values", "shared")


def pairwise(values: DataFrame, candidates: DataFrame) -> DataFrame:
    """(dep, ref) by the definition, as a baseline: a value of ``dep`` that ``ref`` lacks rules a candidate out.

    All candidates(dep, ref) are tested in one anti-join of their dependents' values. ``values`` must be distinct.
    """
    asked = values.withColumnRenamed("attr", "dep").join(F.broadcast(candidates), "dep")
    there = values.withColumnRenamed("attr", "ref")
    return candidates.join(asked.join(there, ["ref", "v"], "left_anti").select("dep", "ref").distinct(), ["dep", "ref"], "left_anti")


def pairwise_joined(values: DataFrame) -> DataFrame:
    """(dep, ref) by a self-join on the value and a count of matches; ``values`` must be distinct."""
    size = values.groupBy(F.col("attr").alias("dep")).agg(F.count(F.lit(1)).alias("n"))
    other = values.select(F.col("attr").alias("ref"), "v")
    hits = values.withColumnRenamed("attr", "dep").join(other, "v").filter("dep <> ref").groupBy("dep", "ref").agg(F.count(F.lit(1)).alias("c"))
    return hits.join(size, "dep").filter("c = n").select("dep", "ref")
