"""Licence scan: winnowed fingerprints, an inverted index of templates, and banded alignment.

Words are runs of ASCII letters and digits and of non-ASCII characters, lower-cased. Every window of ``WINDOW`` consecutive
hashes of ``GRAM`` words keeps its smallest, in templates and in documents alike, so any ``WINDOW + GRAM - 1`` words that
agree share a fingerprint. Shared fingerprints, grouped by template and diagonal, pick places; there the template's
words are aligned with the document's inside a band around the diagonals, and the match's coverage (matched template
words over all) and span are reported. Of overlapping matches the one with more matched words stays.

The index is built from the templates, whose number is the caller's and is checked against ``MAX_TEMPLATE_WORDS``; it is what
tasks get. Documents are read whole, row by row; nothing is shuffled.

Defined cases: null and empty texts have no match; repeated rows each report theirs; null ids pass through. An empty table
gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .license_texts import TEMPLATES
from .shingles import mix, numbers

GRAM, WINDOW, BAND = 3, 2, 6
MAX_TEMPLATE_WORDS = 5_000_000
_IS_WORD = np.zeros(256, bool)
_IS_WORD[[*range(48, 58), *range(97, 123), *range(128, 256)]] = True


def words(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Numbers, starts and ends (in bytes) of the words of a lower-cased text."""
    x = np.frombuffer(data, np.uint8)
    edge = np.flatnonzero(np.diff(np.concatenate([[False], _IS_WORD[x], [False]])))
    starts, ends = edge[0::2], edge[1::2]
    hashes = [np.empty(0, np.uint64)]
    for at in range(0, len(starts), 100_000):  # few words are objects at a time
        some = slice(at, at + 100_000)
        hashes.append(numbers([data[a:b] for a, b in zip(starts[some].tolist(), ends[some].tolist(), strict=True)]))
    return np.concatenate(hashes), starts, ends


def fingerprints(w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Winnowed (hash, word number) of a word sequence; a shorter sequence than a window keeps its smallest."""
    n = len(w) - GRAM + 1
    if n <= 0:
        return np.empty(0, np.uint64), np.empty(0, int)
    h = np.zeros(n, np.uint64)
    for j in range(GRAM):
        h = mix(h * np.uint64(3) + w[j : j + n] + np.uint64(j))
    if n < WINDOW:
        at = np.asarray([h.argmin()])
    else:
        win = np.lib.stride_tricks.sliding_window_view(h, WINDOW)
        at = np.unique(np.arange(len(win)) + WINDOW - 1 - win[:, ::-1].argmin(1))
    return h[at], at


@dataclass
class Index:
    names: list[str]
    seqs: list[np.ndarray]
    keys: np.ndarray  # sorted hashes
    owner: np.ndarray  # template of each
    place: np.ndarray  # word number in it
    prints: np.ndarray  # fingerprints of each template


def index(templates: dict[str, str]) -> Index:
    names = sorted(templates)
    seqs = [words(templates[n].encode().lower())[0] for n in names]
    if sum(map(len, seqs)) > MAX_TEMPLATE_WORDS:
        raise ValueError(f"templates have more than {MAX_TEMPLATE_WORDS} words")
    parts = [fingerprints(s) for s in seqs]
    keys = np.concatenate([p[0] for p in parts])
    order = np.argsort(keys, kind="stable")
    return Index(names, seqs, keys[order], np.repeat(np.arange(len(names)), [len(p[0]) for p in parts])[order], np.concatenate([p[1] for p in parts])[order], np.asarray([len(p[0]) for p in parts]))


def align(t: np.ndarray, d: np.ndarray, low: int, high: int) -> tuple[int, int, int]:
    """Best local alignment of template words ``t`` with document words ``d`` on diagonals (document minus template) low..high.

    A match scores 2, a mismatch or a gap -1. Returns matched words and the first and last aligned word of ``d`` (one past).
    """
    width = high - low + 1
    score, hits = np.zeros(width + 2, int), np.zeros(width + 2, int)
    first = np.full(width + 2, -1)
    best = (0, 0, 0, 0)
    for i in range(len(t)):
        new, nhits, nfirst = np.zeros(width + 2, int), np.zeros(width + 2, int), np.full(width + 2, -1)
        lo, hi = max(0, -(i + low)), min(width, len(d) - i - low)
        for b in range(lo, hi):
            j = i + low + b
            same = t[i] == d[j]
            s, k, f = score[b + 1] + (2 if same else -1), hits[b + 1] + same, first[b + 1] if score[b + 1] > 0 else j
            if score[b + 2] - 1 > s:
                s, k, f = score[b + 2] - 1, hits[b + 2], first[b + 2]
            if new[b] - 1 > s:
                s, k, f = new[b] - 1, nhits[b], nfirst[b]
            if s > 0:
                new[b + 1], nhits[b + 1], nfirst[b + 1] = s, k, f
                if s > best[0]:
                    best = (s, k, f, j + 1)
        score, hits, first = new, nhits, nfirst
    return int(best[1]), int(best[2]), int(best[3])


def scan_text(text: str, ix: Index, least: float) -> list[tuple[str, float, int, int, int]]:
    """(template, coverage, matched words, start, end) of the matches in a text; spans count its characters."""
    data = text.encode("utf-8", "surrogatepass").lower()
    w, starts, ends = words(data)
    h, at = fingerprints(w)
    lo, hi = np.searchsorted(ix.keys, h, "left"), np.searchsorted(ix.keys, h, "right")
    hit = np.flatnonzero(hi > lo)
    if not len(hit):
        return []
    n = hi[hit] - lo[hit]
    which = np.repeat(lo[hit], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
    pos, owner = np.repeat(at[hit], n), ix.owner[which]
    diag = pos - ix.place[which]
    found: list[tuple[int, int, int, int]] = []
    reach = [min(BAND, max(1, len(s) // 4)) for s in ix.seqs]  # below half a template, so that a repeat next to it is another place
    order = np.lexsort((diag, owner))
    group: list[int] = []

    def close() -> None:
        t = owner[group[0]]
        seq = ix.seqs[t]
        if len(group) < 0.2 * ix.prints[t]:
            return
        low, high = int(diag[group[0]]) - reach[t], int(diag[group[-1]]) + reach[t]
        from_ = max(0, low)
        matched, a, b = align(seq, w[from_ : high + len(seq)], low - from_, high - from_)
        if matched >= least * len(seq):
            found.append((matched, int(t), a + from_, b + from_))

    for k in order:
        if group and (owner[k] != owner[group[0]] or diag[k] - diag[group[0]] > 2 * reach[owner[k]]):
            close()
            group = []
        group.append(k)
    close()
    out: list[tuple[int, int, int, int]] = []
    taken: list[tuple[int, int]] = []
    for m in sorted(found, key=lambda m: (-m[0], m[0] / -len(ix.seqs[m[1]]), m[2], m[1])):
        if all(min(m[3], b) - max(m[2], a) <= 0 for a, b in taken):
            out.append(m)
            taken.append((m[2], m[3]))
    chars = lambda b: len(data[:b].decode("utf-8", "surrogatepass"))
    return [(ix.names[t], k / len(ix.seqs[t]), k, chars(starts[a]), chars(ends[b - 1])) for k, t, a, b in sorted(out, key=lambda m: m[2])]


def scan(docs: DataFrame, templates: dict[str, str] | None = None, least: float = 0.8) -> DataFrame:
    """(doc_id, license, coverage, matched_words, start, end): the matches of at least ``least`` coverage in ``docs(doc_id, text)``."""
    ix = index(templates or TEMPLATES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                rows = [(d, *m) for d, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True) if t for m in scan_text(t, ix, least)]
                if rows:
                    cols = list(zip(*rows, strict=True))
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.string(), pa.float64(), pa.int32(), pa.int64(), pa.int64()), strict=True)], names=["doc_id", "license", "coverage", "matched_words", "start", "end"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, license string, coverage double, matched_words int, start long, end long")
