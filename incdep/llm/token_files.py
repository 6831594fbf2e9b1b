"""Token-ID output: flat unsigned integer files plus 64-bit document offsets, read back memory-mapped.

Documents are range-partitioned by id and sorted inside each partition; a task writes three files: ids
(``.ids``, unsigned 16 or 32 bit, little endian), document offsets (``.off``, signed 64 bit, one more than
documents, from 0) and document ids (``.doc``, signed 64 bit). The manifest, one row a part, is what readers
use; a part's global base is the prefix sum of the token counts of the parts before it.

Nulls: a null text is empty (only the end id is written); null document ids sort first, and the manifest has the number of them
at each part's start. Repeated ids keep all their rows, ordered by a hash of their text and then by it, and may span parts. An empty table gives no part
and no rows. Extra columns are ignored.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import encoder
from .common import mapped, new_folder, write_file, written

MANIFEST = "task int, part int, first_doc long, n_docs long, n_nulls long, n_tokens long, width int, path string"
_ARROW = pa.schema([("task", pa.int32()), ("part", pa.int32()), ("first_doc", pa.int64()), ("n_docs", pa.int64()), ("n_nulls", pa.int64()), ("n_tokens", pa.int64()), ("width", pa.int32()), ("path", pa.string())])


def write_tokens(docs: DataFrame, tokenizer: str, end_id: int = 2, folder: str | None = None, part_tokens: int = 32_000_000) -> DataFrame:
    """Write ``docs(doc_id, text)`` as token files; return the manifest with each part's global ``base``.

    A task holds one part of at most about ``part_tokens`` ids (a longer document makes a longer part).
    """
    folder = folder or new_folder(docs.sparkSession, "tokens")

    def parts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(tokenizer)
        end = np.asarray([end_id], dtype=enc.dtype).tobytes()
        width = enc.dtype.itemsize
        ids: list[bytes] = []
        lengths: list[int] = []
        names: list[int | None] = []
        held = done = 0

        def flush() -> pa.RecordBatch:
            path = f"{folder}/part-{uuid.uuid4().hex}"
            write_file(path + ".ids", *ids)
            write_file(path + ".off", np.concatenate([[0], np.cumsum(lengths)]).astype("<i8").tobytes())
            nulls = names.count(None)
            write_file(path + ".doc", np.asarray([0] * nulls + names[nulls:], dtype="<i8").tobytes())
            row = {"task": TaskContext.get().partitionId(), "part": done, "first_doc": names[0], "n_docs": len(names), "n_nulls": nulls, "n_tokens": held, "width": width, "path": path}
            return pa.RecordBatch.from_pylist([row], schema=_ARROW)

        for batch in batches:
            doc_ids = batch.column(0).to_pylist()
            for at in range(0, len(doc_ids), 256):
                some = batch.column(1).slice(at, 256).to_pylist()
                for doc_id, got in zip(doc_ids[at : at + 256], enc(some), strict=True):
                    got += end
                    if names and held + len(got) // width > part_tokens:
                        yield flush()
                        ids, lengths, names, held, done = [], [], [], 0, done + 1
                    ids.append(got)
                    lengths.append(len(got) // width)
                    names.append(doc_id)
                    held += lengths[-1]
        if names:
            yield flush()

    rows = docs.select(F.col("doc_id").cast("long"), "text", F.xxhash64("text").alias("_h"))
    laid = rows.repartitionByRange("doc_id", "_h").sortWithinPartitions("doc_id", "_h", "text").drop("_h")
    manifest = written(laid.mapInArrow(parts, MANIFEST), "manifest")
    before = Window.orderBy("task", "part").rowsBetween(Window.unboundedPreceding, -1)  # a row a part
    return manifest.withColumn("base", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)))


def read_tokens(manifest: DataFrame, per_document: bool = False) -> DataFrame:
    """Read token files back: (doc_id, start, n_tokens, ids_crc32), and with ``per_document`` the ``ids`` too."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in batch.to_pylist():
                ids = mapped(part["path"] + ".ids", f"<u{part['width']}")
                off = mapped(part["path"] + ".off", "<i8")
                doc = mapped(part["path"] + ".doc", "<i8")
                for at in range(0, len(doc), 2048):
                    some = range(at, min(at + 2048, len(doc)))
                    base = int(off[at])
                    data = ids[base : int(off[some.stop])].astype("<u4")
                    ends = (off[at : some.stop + 1] - base).tolist()
                    spans = [data[a:b] for a, b in zip(ends, ends[1:])]
                    out = {
                        "doc_id": pa.array(doc[at : some.stop], mask=np.arange(at, some.stop) < part["n_nulls"]),
                        "start": pa.array(off[at : some.stop] + part["base"], pa.int64()),
                        "n_tokens": pa.array(np.diff(ends), pa.int64()),
                        "ids_crc32": pa.array([zlib.crc32(s) for s in spans], pa.int64()),
                    }
                    if per_document:
                        out["ids"] = pa.array([s.astype("i8") for s in spans], pa.list_(pa.int64()))
                    yield pa.RecordBatch.from_pydict(out)

    n = manifest.sparkSession.conf.get("spark.sql.shuffle.partitions")
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * per_document
    return manifest.repartition(int(n), "path").mapInArrow(rows, schema)
