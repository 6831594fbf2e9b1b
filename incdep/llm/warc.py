"""WARC archives: writing with deduplicated payloads, and reading by boundary-chain verification.

Writing: one task writes plain WARC/1.1 files, each begun by a ``warcinfo`` record. Of records with equal payloads of
``min_revisit`` bytes or more the one with the smallest page id is a ``response``, the others are ``revisit`` records.
Payloads aren't shuffled: only digests are, and a page goes through a join only if a bit table of fixed size says that
its digest may be repeated.

Reading: files are cut in byte ranges. A task takes every place in its range where the version line stands as a
candidate, reads its header and notes the offset of its successor. Inside the range it follows successors to where each
candidate's chain leaves the range; chains between ranges are resolved by pointer jumping from offset 0. A range's
records are then read from the one offset that the chain enters by, so a version line inside a payload is never taken.
An incomplete last record, in its header or its block, is left out; a chain that breaks anywhere else, or a file shorter
than the manifest says, is an error. Headers may have any length.

Defined cases: null html is an empty payload; a null page id is written without one and read as null; a null URL is
``about:blank``; control characters and spaces in URLs are percent-encoded; repeated page ids each have a record, and
rows of the smallest id of a payload are all responses. Empty tables give no files and no rows.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import filesystem, may_match, new_folder, read_file, write_file, written

MAGIC = b"WARC/1.1\r\n"
END = b"\r\n\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
BITS = 1 << 20  # of the table of digests that may be repeated: 128 kB, whatever the input
RECORD = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long"
_ARROW = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())])


def _record_id(page_id: int | None, path: str = "", k: int = 0) -> str:
    return f"<urn:page:{page_id}>" if page_id is not None else f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{path}/{k}')}>"


def _page_of(record_id: str | None) -> int | None:
    m = re.fullmatch(r"<urn:page:(-?\d+)>", record_id or "")
    return int(m[1]) if m else None


def _record(kind: str, record_id: str, date: str, more: list[tuple[str, str]], block: bytes) -> bytes:
    head = [("WARC-Type", kind), ("WARC-Record-ID", record_id), ("WARC-Date", date), *more, ("Content-Length", str(len(block)))]
    return MAGIC + "".join(f"{k}: {v}\r\n" for k, v in head).encode() + b"\r\n" + block + END


def _uri(url: str | None) -> str:
    return re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url) if url else "about:blank"


def with_revisits(pages: DataFrame, min_revisit: int = 100) -> DataFrame:
    """(page_id, url, html, digest, refers_to): the page whose record each page's record revisits, null for responses."""
    payload = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    base = pages.select(F.col("page_id").cast("long"), "url", F.coalesce("html", F.lit("")).alias("html"), F.sha2(payload, 256).alias("digest"))
    light = written(base.select("page_id", "digest", F.octet_length("html").alias("_n")).filter(F.col("_n") >= min_revisit).drop("_n"), "warc-digests")
    groups = light.groupBy("digest").agg(F.min("page_id").alias("_first"), F.count(F.lit(1)).alias("_n")).filter("_n > 1").drop("_n")
    groups = written(groups, "warc-groups")
    later = light.join(groups, "digest").filter("page_id <> _first or (page_id is null) <> (_first is null)").select("page_id", "digest", F.col("_first").alias("refers_to")).distinct()
    marked = may_match(base, "digest", groups.select("digest"), BITS)
    cols = ["page_id", "url", "html", "digest"]
    alone = marked.filter(~F.col("_may")).select(*cols, F.lit(None).cast("long").alias("refers_to"))
    maybe = marked.filter("_may").select(*cols).join(later.withColumnRenamed("page_id", "_p").withColumnRenamed("digest", "_d"), F.col("page_id").eqNullSafe(F.col("_p")) & (F.col("digest") == F.col("_d")), "left").select(*cols, "refers_to")
    return alone.unionByName(maybe)


def write_archives(pages: DataFrame, folder: str | None = None, min_revisit: int = 100, date: str = "2026-01-01T00:00:00Z", file_bytes: int = 256 << 20) -> DataFrame:
    """Write ``pages(page_id, url, html)`` as archives of up to about ``file_bytes``; return the manifest (path, bytes, records)."""
    folder = folder or new_folder(pages.sparkSession, "warc")
    fields = pa.schema([("path", pa.string()), ("bytes", pa.int64()), ("records", pa.int64())])

    def files(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = path = None
        size = records = 0

        def done() -> pa.RecordBatch:
            out.close()
            return pa.RecordBatch.from_pylist([{"path": path, "bytes": size, "records": records}], schema=fields)

        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                for row in batch.slice(at, 128).to_pylist():
                    if out is None:
                        path, size, records = f"{folder}/part-{uuid.uuid4().hex}.warc", 0, 0
                        fs, local = filesystem(path)
                        fs.create_dir(local.rpartition("/")[0], recursive=True)
                        out = fs.open_output_stream(local)
                        info = _record("warcinfo", _record_id(None, path, -1), date, [("Content-Type", "application/warc-fields")], b"format: WARC File Format 1.1\r\n")
                        size += out.write(info) or len(info)
                    payload = row["html"].encode()
                    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
                    more = [("WARC-Target-URI", _uri(row["url"])), ("WARC-Payload-Digest", f"sha256:{row['digest']}"), ("Content-Type", "application/http; msgtype=response")]
                    if (to := row["refers_to"]) is not None:
                        more += [("WARC-Profile", PROFILE), ("WARC-Refers-To", _record_id(to))]
                    data = _record("response" if to is None else "revisit", _record_id(row["page_id"], path, records), date, more, http if to is not None else http + payload)
                    out.write(data)
                    size += len(data)
                    records += 1
                    if size >= file_bytes:
                        yield done()
                        out = None
        if out is not None:
            yield done()

    return written(with_revisits(pages, min_revisit).mapInArrow(files, "path string, bytes long, records long"), "warc-manifest")


def _head(data: bytes, at: int) -> tuple[dict[str, str], int] | None:
    """Header fields of a record at ``at`` and where its block begins; None if no whole, valid header stands there."""
    if not data.startswith(MAGIC, at) or (stop := data.find(END, at)) < 0:
        return None
    fields = {}
    for line in data[at + len(MAGIC) : stop].split(b"\r\n"):
        k, sep, v = line.partition(b":")
        if not sep:
            return None
        fields[k.decode("latin-1").strip().lower()] = v.decode("utf-8", "replace").strip()
    return (fields, stop + len(END)) if fields.get("content-length", "").isdigit() else None


def _part(path: str, begin: int, end: int) -> bytes:
    """Bytes from ``begin`` to ``end``, which the manifest says are there."""
    data = read_file(path, begin, end - begin)
    if len(data) < end - begin:
        raise ValueError(f"{path} has no bytes {begin + len(data)} to {end}, which the manifest gives")
    return data


def _open(data: bytes, at: int) -> bool:
    """Whether the data end inside what may be a header that begins at ``at``."""
    if not data.startswith(MAGIC, at):
        return len(data) - at < len(MAGIC) and MAGIC.startswith(data[at:])
    return data.find(END, at) < 0 and all(b":" in line for line in data[at + len(MAGIC) :].split(b"\r\n")[:-1] if line)


def _long_head(path: str, size: int, data: bytes, base: int, at: int) -> tuple[dict[str, str], int] | bool:
    """As ``_head`` for ``data`` from file offset ``base``, reading on while the header is cut by the data's end.

    Without a header: whether the file ends inside one.
    """
    if head := _head(data, at):
        return head
    begin, n, shift = base + at, len(data) - at, 0
    while is_open := _open(data, at):
        if begin + n >= size:
            break
        n = min(size - begin, max(2 * n, 1 << 16))
        data, at, shift = _part(path, begin, begin + n), 0, begin - base
        if head := _head(data, 0):
            return head[0], head[1] + shift
    return is_open


def _candidates(path: str, size: int, begin: int, end: int, head_bytes: int) -> list[tuple[int, int]]:
    """(offset, exit) of the range's candidates: where the chain from it leaves the range, -1 where it breaks."""
    data = _part(path, begin, min(size, end + max(head_bytes, len(MAGIC))))
    leaves: dict[int, int] = {}
    found: list[tuple[int, int]] = []
    at = data.find(MAGIC)
    while 0 <= at < end - begin:
        head = _long_head(path, size, data, begin, at)
        after = -1 if isinstance(head, bool) else begin + head[1] + int(head[0]["content-length"]) + len(END)
        found.append((begin + at, after if after <= size else -1))
        at = data.find(MAGIC, at + 1)
    for at, after in reversed(found):
        leaves[at] = after if after < 0 or after >= end else leaves.get(after, -1)
    return sorted(leaves.items())


def chain_entries(manifest: DataFrame, range_bytes: int, head_bytes: int) -> DataFrame:
    """(path, bytes, begin, entry): for each byte range the offset by which the record chain from the file's start enters it."""
    spark = manifest.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranges = manifest.filter("bytes > 0").select("path", "bytes", F.explode(F.sequence(F.lit(0).cast("long"), F.col("bytes") - 1, F.lit(range_bytes).cast("long"))).alias("begin")).repartition(n, "path", "begin")

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                got = _candidates(r["path"], r["bytes"], r["begin"], min(r["bytes"], r["begin"] + range_bytes), head_bytes)
                yield pa.RecordBatch.from_arrays([pa.array([r["path"]] * len(got), pa.string()), pa.array([r["bytes"]] * len(got), pa.int64()), pa.array([r["begin"]] * len(got), pa.int64()), pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], pa.int64())], names=["path", "bytes", "begin", "off", "exit"])

    links = written(ranges.mapInArrow(scan, "path string, bytes long, begin long, off long, exit long"), "warc-links")
    # only the file's start and places that some chain leaves to can be entered by
    targets = links.filter("exit >= 0").select("path", F.col("exit").alias("off")).distinct().unionByName(manifest.select("path", F.lit(0).cast("long").alias("off"))).distinct()
    jump = written(links.join(targets, ["path", "off"]).select("path", "off", "exit"), "warc-jump")
    reach = manifest.select("path", F.lit(0).cast("long").alias("off"))
    known = -1
    while True:
        step = reach.join(jump, ["path", "off"]).filter("exit >= 0").select("path", F.col("exit").alias("off"))
        reach = written(reach.unionByName(step).distinct(), "warc-reach")
        if (now := reach.count()) == known:
            break
        known = now
        over = jump.select("path", F.col("off").alias("exit"), F.col("exit").alias("_to"))
        jump = written(jump.join(over, ["path", "exit"], "left").select("path", "off", F.coalesce("_to", "exit").alias("exit")), "warc-jump")
    # a place where no record begins is kept too, for the reader to judge
    begin = F.col("off") - F.col("off") % range_bytes
    return reach.join(manifest.select("path", "bytes"), "path").filter("off < bytes").select("path", "bytes", begin.alias("begin"), F.col("off").alias("entry"))


def read_archives(manifest: DataFrame, range_bytes: int = 16 << 20, head_bytes: int = 1 << 16, payloads: bool = False) -> DataFrame:
    """Response and revisit records of the archives in ``manifest(path, bytes)``; with ``payloads`` the text too.

    ``head_bytes`` is how much is read at once beyond a range; longer headers are read on.
    """
    entries = written(chain_entries(manifest, range_bytes, head_bytes), "warc-entries")
    n = int(manifest.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def records(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fields = pa.schema([*_ARROW, ("payload", pa.string())]) if payloads else _ARROW
        for batch in batches:
            for r in batch.to_pylist():
                at, end = r["entry"], min(r["bytes"], r["begin"] + range_bytes)
                data, base = _part(r["path"], at, min(r["bytes"], end + max(head_bytes, len(MAGIC)))), at
                out: list[dict] = []
                while at < end:
                    head = _long_head(r["path"], r["bytes"], data, base, at - base)
                    if head is True:
                        break
                    if head is False:
                        raise ValueError(f"{r['path']}: no record at byte {at} of {r['bytes']}, where the one before ends")
                    f, body = head
                    after = base + body + int(f["content-length"])
                    if after + len(END) > r["bytes"]:
                        break
                    if f.get("warc-type") in ("response", "revisit"):
                        block = data[body : after - base] if after - base <= len(data) else _part(r["path"], base + body, after)
                        http, _, payload = block.partition(END)
                        whole = int(re.search(rb"(?i)content-length: *(\d+)", http)[1])
                        own = f["warc-type"] == "response"
                        row = {"page_id": _page_of(f.get("warc-record-id")), "url": f.get("warc-target-uri"), "payload_bytes": len(payload) if own else whole, "record_type": f["warc-type"], "refers_to": _page_of(f.get("warc-refers-to"))}
                        row["payload_digest"] = hashlib.sha256(payload).hexdigest() if own else f.get("warc-payload-digest", "").removeprefix("sha256:")
                        out.append(row | ({"payload": payload.decode("utf-8", "replace") if own else None} if payloads else {}))
                    at = after + len(END)
                    if len(out) >= 1000:
                        yield pa.RecordBatch.from_pylist(out, schema=fields)
                        out = []
                if out:
                    yield pa.RecordBatch.from_pylist(out, schema=fields)

    return entries.repartition(n, "path", "begin").mapInArrow(records, RECORD + ", payload string" * payloads)
