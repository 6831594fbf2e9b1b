"""Best-fit packing of documents into sequences of at most ``capacity`` tokens.

Best-fit decreasing, serially on the driver over a histogram of lengths. Documents are cut into pieces; pieces of equal length are
interchangeable, and so are open sequences of equal gap, so both sorted lists are kept run-length encoded: at most
``capacity`` runs each, whatever the number of documents. A step takes the longest unplaced run, finds the
successor of its length among the gaps, matches rank by rank as many as both runs have (ranks beyond the shorter
run lose and go to the next step), and updates the gaps. What fits no gap opens new sequences. The plan's size
depends on ``capacity`` alone. Each piece then finds its place from its rank inside its length, a distributed
prefix sum over salted sub-groups, so a length that holds most of the pieces is no hot key.

Nulls: a null text is an empty document with only the end id. Repeated rows are packed as often as they occur.
An empty table gives no rows. Extra columns are ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import encoder
from .common import written

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def cut_pieces(docs: DataFrame, tokenizer: str, end_id: int = 2, capacity: int = 1024) -> DataFrame:
    """Pieces of each document's ids (with the end id): whole if short enough, else cut so that only the first may be shorter."""

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(tokenizer)
        for batch in batches:
            doc_ids = batch.column(0).to_pylist()
            for at in range(0, len(doc_ids), 256):
                out: list[tuple] = []
                some = batch.column(1).slice(at, 256).to_pylist()
                for doc_id, got in zip(doc_ids[at : at + 256], enc(some), strict=True):
                    ids = np.append(np.frombuffer(got, enc.dtype).astype("<u4"), np.uint32(end_id))
                    head = len(ids) % capacity or min(capacity, len(ids))
                    for k, a in enumerate([0, *range(head, len(ids), capacity)]):
                        b = head if k == 0 else a + capacity
                        out.append((doc_id, k, a, b - a, zlib.crc32(ids[a:b].tobytes())))
                cols = list(zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(pieces, PIECES)


def plan(counts: dict[int, int], capacity: int) -> tuple[dict[int, list[tuple[int, int, int, int, int]]], int]:
    """Best-fit decreasing over runs: ``counts`` maps length to number of pieces.

    Returns, for each length, runs (first rank, first sequence, sequences, pieces a sequence, offset), and the number of
    sequences. A run gives ranks first.. to ``sequences`` sequences, each taking ``pieces a sequence`` one after another.
    """
    bins: dict[int, list[tuple[int, int]]] = {}  # gap -> runs of open sequences (first, count)
    gaps: list[int] = []  # sorted gaps that have runs
    out: dict[int, list[tuple[int, int, int, int, int]]] = {}
    opened = 0

    def give(gap: int, first: int, count: int) -> None:
        if gap not in bins:
            bins[gap] = []
            insort(gaps, gap)
        bins[gap].append((first, count))

    for length in sorted(counts, reverse=True):
        left, rank, runs = counts[length], 0, out.setdefault(length, [])
        while left:
            at = bisect_left(gaps, length)
            if at < len(gaps):
                gap = gaps[at]
                first, have = bins[gap].pop()
                each = gap // length
            else:
                each = capacity // length
                gap, first, have = capacity, opened, max(1, left // each)
                opened += have
            each = min(each, left)
            use = min(have, left // each)
            if have > use:
                if gap == capacity:
                    raise AssertionError("opened more than used")
                bins[gap].append((first + use, have - use))
            elif gap in bins and not bins[gap]:
                del bins[gap]
                gaps.remove(gap)
            runs.append((rank, first, use, each, capacity - gap))
            if (rest := gap - each * length) > 0:
                give(rest, first, use)
            rank += use * each
            left -= use * each
    return out, opened


def pack(pieces: DataFrame, capacity: int = 1024, group_rows: int = 1000) -> DataFrame:
    """Add ``sequence_id`` and ``offset`` to ``pieces(doc_id, piece, start, length, ...)``; no sequence exceeds ``capacity``."""
    pieces = written(pieces, "pieces")
    counts = {r["length"]: r["count"] for r in pieces.groupBy("length").count().collect()}  # at most `capacity` rows
    salts = pieces.sparkSession.createDataFrame([(k, -(-n // group_rows)) for k, n in counts.items()], "length long, _salts long")
    salted = pieces.join(F.broadcast(salts), "length").withColumn("_salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.col("_salts"))).drop("_salts")
    sub = salted.groupBy("length", "_salt").agg(F.count(F.lit(1)).alias("_n"))
    runs, _ = plan(counts, capacity)
    starts = {k: np.asarray([r[0] for r in v], dtype="i8") for k, v in runs.items()}
    table = {k: np.asarray(v, dtype="i8") for k, v in runs.items()}
    before = Window.partitionBy("length").orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    base = sub.withColumn("_base", F.coalesce(F.sum("_n").over(before), F.lit(0))).drop("_n")
    inside = Window.partitionBy("length", "_salt").orderBy("doc_id", "piece", "ids_crc32")
    ranked = salted.withColumn("_rank", F.row_number().over(inside) - 1).join(base, ["length", "_salt"]).withColumn("_rank", F.col("_rank") + F.col("_base")).drop("_salt", "_base")

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lengths, ranks = batch.column("length").to_numpy(), batch.column("_rank").to_numpy()
            seq, off = np.zeros(len(ranks), "i8"), np.zeros(len(ranks), "i8")
            for length in np.unique(lengths):
                at = np.flatnonzero(lengths == length)
                run = table[int(length)][np.searchsorted(starts[int(length)], ranks[at], side="right") - 1]
                k = ranks[at] - run[:, 0]
                seq[at] = run[:, 1] + k // run[:, 3]
                off[at] = run[:, 4] + (k % run[:, 3]) * length
            kept = [c for n, c in zip(batch.schema.names, batch.columns, strict=True) if n != "_rank"]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(seq), pa.array(off)], names=[*(n for n in batch.schema.names if n != "_rank"), "sequence_id", "offset"])

    schema = ", ".join(f"`{n}` {t}" for n, t in pieces.dtypes) + ", sequence_id long, offset long"
    order = [n for n, _ in pieces.dtypes]
    return ranked.select(*order, F.col("_rank").cast("long")).mapInArrow(place, schema)
