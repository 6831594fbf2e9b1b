"""Byte-level BPE ids of whole texts, equal to the tokenizers library's, with repeated words encoded once."""

from __future__ import annotations

import ctypes
import gc
import json
import os
import re
from itertools import chain, islice

import numpy as np
import pyarrow as pa

#: A single space between two characters that are no white space always starts a new pre-token, so the parts of a
#: text between such spaces can be encoded one by one. Python's ``\s`` covers all that the library's does.
_ODD_SPACE = re.compile(r" \s|\s ")
_LONE_SPACE = re.compile(r"(?<=\S) (?=\S)")
_OTHER_SPACES = [chr(c) for c in range(0x3001) if chr(c).isspace() and chr(c) not in " \n"]
CACHE_BYTES = 72 << 20  # of remembered words in a worker
_LOADED: dict[tuple[str, int], "WordEncoder"] = {}


def _splits(text: str) -> bool:
    """Whether all spaces stand alone, between other characters than white space."""
    if not text or text[-1].isspace() or "  " in text or " \n" in text or "\n " in text:
        return False
    return not (any(c in text for c in _OTHER_SPACES) and _ODD_SPACE.search(text))


class WordTable:
    """Ids of words in a few flat arrays, about 40 bytes a word; the word itself is compared, so no hash decides.

    A record is the word's ids and then its UTF-8 bytes, one after another in ``blob``; ``slots`` is an open-addressing table of
    record numbers by the word's hash.
    """

    def __init__(self, most_bytes: int):
        self.room = max(16, most_bytes // 46)  # words: some 10 bytes of slots, 8 of keys, 4 of ends and 24 of record each
        self.slots = np.zeros(1 << (3 * self.room // 2).bit_length(), np.int32)
        self.keys = np.zeros(self.room, np.int64)
        self.ends = np.zeros(self.room + 1, np.uint32)
        self.most_blob = 24 * self.room
        self.clear()

    def clear(self) -> None:
        self.slots[:] = 0
        self.blob = bytearray()
        self.n = 0

    def __len__(self) -> int:
        return self.n

    @property
    def full(self) -> bool:
        return self.n >= self.room or len(self.blob) >= self.most_blob

    def _places(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        key = np.fromiter(map(hash, words), np.int64, len(words))
        return key, (key ^ (key >> np.int64(32))) & np.int64(len(self.slots) - 1)

    def get(self, words: list[str]) -> list[bytes | None]:
        """The ids of each word, None where it isn't known."""
        key, at = self._places(words)
        found, live = np.full(len(words), -1), np.arange(len(words))
        while len(live):
            record = self.slots[at[live]] - 1
            same = (record >= 0) & (self.keys[record] == key[live])
            found[live[same]] = record[same]
            live = live[(record >= 0) & ~same]
            at[live] = (at[live] + 1) & (len(self.slots) - 1)
        out: list[bytes | None] = [None] * len(words)
        some = np.flatnonzero(found >= 0)
        blob = self.blob
        for k, a, b in zip(some.tolist(), self.ends[found[some]].tolist(), self.ends[found[some] + 1].tolist(), strict=True):
            word, record = words[k].encode("utf-8", "surrogatepass"), blob[a:b]
            if record.endswith(word):
                out[k] = bytes(record[: len(record) - len(word)])
        return out

    def add(self, ids: dict[str, bytes]) -> None:
        """Remember words that aren't known, as far as there is room."""
        words = list(ids)[: self.room - self.n]
        records = [ids[w] + w.encode("utf-8", "surrogatepass") for w in words]
        if not words:
            return
        last = self.n + len(words)
        self.ends[self.n + 1 : last + 1] = len(self.blob) + np.cumsum([len(r) for r in records])
        self.blob += b"".join(records)
        key, at = self._places(words)
        self.keys[self.n : last] = key
        live = np.arange(len(words))
        while len(live):
            free = self.slots[at[live]] == 0
            place, first = np.unique(at[live][free], return_index=True)
            won = live[free][first]
            self.slots[place] = won + self.n + 1
            live = np.setdiff1d(live, won, assume_unique=True)
            taken = self.slots[at[live]] != 0
            at[live[taken]] = (at[live[taken]] + 1) & (len(self.slots) - 1)
        self.n = last


class WordEncoder:
    """Encodes texts through a bounded table of word ids; a text that the split rule doesn't cover goes to the library whole.

    The rule holds for byte-level tokenizers that split by the usual expression and change no text first; with any other one
    all texts go to the library whole.
    """

    def __init__(self, path: str, cache_bytes: int = CACHE_BYTES):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        if hasattr(self.library.model, "_resize_cache"):  # this class's own table takes its place
            self.library.model._resize_cache(0)
        split = json.loads(self.library.pre_tokenizer.__getstate__()) if self.library.pre_tokenizer else {}
        self.covered = split.get("type") == "ByteLevel" and split.get("use_regex", True) and not split.get("add_prefix_space") and self.library.normalizer is None and not self.library.truncation and not self.library.padding
        self.special = [t.content for t in self.library.get_added_tokens_decoder().values()]
        size = self.library.get_vocab_size()
        self.dtype = np.dtype("<u2" if size <= 1 << 16 else "<u4")
        self.spaced = np.asarray([(self.library.id_to_token(i) or "").startswith("\u0120") for i in range(size)])  # the byte alphabet's sign for a space
        self.hot: dict[str, bytes] = {}  # the first words seen, most of the frequent ones among them
        self.hot_room = cache_bytes // 800
        self.words = WordTable(3 * cache_bytes // 4)

    def _ids(self, texts: list[str]) -> list[bytes]:
        return [np.asarray(e.ids, dtype=self.dtype).tobytes() for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def _joined(self, words: list[str]) -> list[bytes]:
        """Ids of words that each follow a space, from one call: an id whose bytes begin with a space begins a word."""
        ids = np.asarray(self.library.encode_batch_fast([" " + " ".join(words)], add_special_tokens=False)[0].ids, dtype=self.dtype)
        starts = np.flatnonzero(self.spaced[ids])
        if len(starts) != len(words):
            return self._ids([" " + w for w in words])
        data, at = ids.tobytes(), (np.append(starts, len(ids)) * self.dtype.itemsize).tolist()
        return [data[a:b] for a, b in zip(at, at[1:])]

    def _encoded(self, words: list[str], unique: int) -> dict[str, bytes]:
        """Ids of words after a space; they are remembered until the cache is full."""
        full = [w for w in words if w]
        out = {"": self._ids([" "])[0]} if len(full) < len(words) else {}
        for at in range(0, len(full), 1000):
            part = full[at : at + 1000]
            out.update(zip(part, self._joined(part), strict=True))
        if self.words.full and 2 * len(out) >= unique:  # the texts have changed
            self.words.clear()
            self.hot = {}
        if not self.words.full:
            at = max(0, self.hot_room - len(self.hot))
            self.hot.update((w, out[w]) for w in full[:at])
            self.words.add({w: out[w] for w in full[at:]})
        return out

    def __call__(self, texts: list[str], budget: int = 300_000):
        """Yield the ids of each text as bytes of ``dtype``; about ``budget`` characters are in work at a time."""
        batch: list[str] = []
        held = 0
        for text in texts:
            text = text or ""
            if len(text) > 4 * budget and (parts := self._parts(text, budget)):
                yield from self._batch(batch)
                batch, held = [], 0
                yield b"".join(chain.from_iterable(self._batch([p]) for p in parts))
                continue
            batch.append(text)
            held += len(text)
            if held >= budget:
                yield from self._batch(batch)
                batch, held = [], 0
        yield from self._batch(batch)

    def _parts(self, text: str, size: int) -> list[str]:
        """A long text cut before single spaces between other characters than white space; none if the rule doesn't cover the tokenizer."""
        if not self.covered or any(" " in s for s in self.special):
            return []
        out, at = [], 0
        while len(text) - at > size and (space := _LONE_SPACE.search(text, at + size)):
            out.append(text[at : space.start()])
            at = space.start()
        return [*out, text[at:]]

    def _batch(self, texts: list[str]) -> list[bytes]:
        split = [t.split(" ") if self.covered and _splits(t) and not any(s in t for s in self.special) else None for t in texts]
        whole = self._ids([t if w is None else w[0] for t, w in zip(texts, split, strict=True)])
        hot = self.hot.get
        got = [w and list(map(hot, w)) for w in split]
        rare = {word for w, ids in zip(split, got, strict=True) if w for word, x in zip(islice(w, 1, None), islice(ids, 1, None)) if x is None}
        words = list(rare)
        known = dict(zip(words, self.words.get(words), strict=True))
        known.update(self._encoded([w for w, ids in known.items() if ids is None], len(known)))
        out = []
        for head, w, ids in zip(whole, split, got, strict=True):
            if w is not None:
                ids[0] = head
                head = b"".join([known[word] if x is None else x for word, x in zip(w, ids)])
            out.append(head)
        return out


def encoder(path: str, cache_bytes: int = CACHE_BYTES) -> WordEncoder:
    """One encoder a worker process."""
    if (path, cache_bytes) not in _LOADED:
        _LOADED.clear()
        _LOADED[path, cache_bytes] = WordEncoder(path, cache_bytes)
    return _LOADED[path, cache_bytes]


def give_back() -> None:
    """Return freed memory to the system: workers serve one stage after another and would keep the most that any of them took."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
        libc.malloc_trim(0)


def forget() -> None:
    """Drop this worker's encoder, if it has one: other stages' tasks call this first."""
    if _LOADED:
        _LOADED.clear()
        give_back()
