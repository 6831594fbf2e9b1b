"""Vectors as block files in the shared folder: bounded blocks that tasks read one at a time."""

from __future__ import annotations

import io
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import new_folder, read_file, write_file, written


def write_blocks(rows: DataFrame, columns: list[str], rows_per_block: int, tag: str, matrix=None) -> DataFrame:
    """Write ``rows`` (whole-number ``columns``, then an array column of equal lengths) as blocks; returns the manifest (block, n, path).

    ``matrix`` maps a block's vectors, as doubles, to the arrays that are written in their place.
    """
    folder = new_folder(rows.sparkSession, tag)
    fields = pa.schema([("path", pa.string()), ("n", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        count = 0

        def flush() -> pa.RecordBatch:
            t = pa.Table.from_batches(held).combine_chunks()
            vec = t.column(len(columns)).combine_chunks()
            x = vec.flatten().to_numpy(zero_copy_only=False).astype("f8").reshape(len(t), -1)
            out = io.BytesIO()
            np.savez(out, **(matrix(x) if matrix else {"vec": x}), **{c: t.column(k).to_numpy() for k, c in enumerate(columns)})
            path = f"{folder}/block-{uuid.uuid4().hex}.npz"
            write_file(path, out.getvalue())
            return pa.RecordBatch.from_pylist([{"path": path, "n": len(t)}], schema=fields)

        for whole in batches:
            at = 0
            while at < whole.num_rows:
                part = whole.slice(at, rows_per_block - count)
                held.append(part)
                count += part.num_rows
                at += part.num_rows
                if count == rows_per_block:
                    yield flush()
                    held, count = [], 0
        if count:
            yield flush()

    return written(rows.mapInArrow(run, "path string, n long"), tag)


def load(path: str) -> dict[str, np.ndarray]:
    with np.load(io.BytesIO(read_file(path))) as z:
        return {k: z[k] for k in z.files}
