"""Hashed word shingles of whole texts, many documents at a time.

A text's words are the runs of anything but ASCII white space, after lower-casing A-Z; its set is that of its distinct
runs of ``k`` words, or the whole sequence as one where it has fewer. A word's number is a keyed cryptographic digest of its
bytes (BLAKE2b, 64 bits), so that no family of words collides by its form; shingles mix the numbers of their words.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from hashlib import blake2b

import numpy as np

from .bpe import give_back

CACHE_BYTES = 48 << 20  # of remembered words in a worker
_SPACE = re.compile(rb"[\x20\x09-\x0D]")


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class _Digests(dict):
    """Word to number; forgets all once it holds about ``CACHE_BYTES``."""

    held = 0

    def __missing__(self, word: bytes) -> int:
        number = int.from_bytes(blake2b(word, digest_size=8, key=b"incdep-words").digest(), "little")
        self.held += len(word) + 200  # with the objects' own bytes
        if self.held > CACHE_BYTES:
            self.clear()
            self.held = len(word) + 200
        self[word] = number
        return number


_DIGESTS = _Digests()


def forget() -> None:
    """Forget all words and give their memory back; they are learned again when needed."""
    _DIGESTS.clear()
    _DIGESTS.held = 0
    give_back()


def numbers(words: list[bytes]) -> np.ndarray:
    """The number of each word."""
    return np.fromiter(map(_DIGESTS.__getitem__, words), np.uint64, len(words))


def _parts(data: bytes, size: int = 1 << 20) -> Iterator[bytes]:
    """``data`` in parts of about ``size`` bytes that end between words, so that few words are objects at a time."""
    at = 0
    while len(data) - at > size:
        space = _SPACE.search(data, at + size)
        stop = space.start() if space else len(data)
        yield data[at:stop]
        at = stop
    yield data[at:] if at else data


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of all words of lower-cased ``texts`` in order, and for each text the index of its first word (one more at the end)."""
    got = [[numbers(part.split()) for part in _parts(t)] for t in texts]
    first = np.cumsum([0, *(sum(map(len, g)) for g in got)])
    return np.concatenate([np.empty(0, np.uint64), *(x for g in got for x in g)]), first


def shingle_sets(texts: list[bytes], k: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text; empty for a text without words."""
    words, first = word_hashes(texts)
    joined = np.zeros(max(0, len(words) - k + 1), np.uint64)
    for j in range(k):
        joined = mix(joined * np.uint64(3) + words[j : j + len(joined)] + np.uint64(j))
    out = []
    for a, b in zip(first[:-1], first[1:], strict=True):
        if b - a >= k:
            out.append(np.unique(joined[a : b - k + 1]))
        elif b > a:
            h = np.full(1, b - a, np.uint64)
            for w in words[a:b]:
                h = mix(h * np.uint64(5) + w)
            out.append(h)
        else:
            out.append(np.empty(0, np.uint64))
    return out


def in_chunks(texts: Iterator[str | None], k: int, budget: int = 1 << 20) -> Iterator[list[np.ndarray]]:
    """Shingle sets of ``texts``, about ``budget`` bytes of text at a time (a longer text is a chunk of its own)."""
    batch: list[bytes] = []
    held = 0
    for text in texts:
        data = (text or "").encode("utf-8", "surrogatepass").lower()
        if batch and held + len(data) > budget:
            yield shingle_sets(batch, k)
            batch, held = [], 0
        batch.append(data)
        held += len(data)
    if batch:
        yield shingle_sets(batch, k)
