"""Token files and packing against the tokenizers library."""

import random
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from incdep.llm import packing, token_files
from incdep.llm.bpe import WordEncoder
from incdep.llm.queries import tokenizer_path


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(tokenizer_path())


def ids_of(library, text):
    return [*library.encode(text or "", add_special_tokens=False).ids, 2]


def crc(ids):
    return zlib.crc32(np.asarray(ids, "<u4").tobytes())


PARTS = ["a", "b", " ", "  ", "\n", "\t", "é", " ", "　", "'s", "<|endoftext|>", "1", "!", "\x1c", "中", "😀", "don't", " the"]


@settings(max_examples=200, deadline=None)
@given(st.lists(st.sampled_from(PARTS), max_size=12).map("".join))
def test_word_cache_equals_library(text):
    enc = test_word_cache_equals_library.__dict__.setdefault("enc", WordEncoder(tokenizer_path(), cache_bytes=20 * 44))
    got = np.frombuffer(next(iter(enc([text]))), enc.dtype).tolist()
    assert got == enc.library.encode(text, add_special_tokens=False).ids


def test_files_round_trip(spark, odd_docs, library):
    rows = [(r["doc_id"], r["text"]) for r in odd_docs.collect()]
    got = token_files.read_tokens(token_files.write_tokens(odd_docs, tokenizer_path(), part_tokens=1000), per_document=True).collect()
    assert len(got) == len(rows)
    got.sort(key=lambda r: r["start"])
    at = 0
    for r in got:
        assert r["start"] == at and r["n_tokens"] == len(r["ids"]) and r["ids_crc32"] == crc(r["ids"])
        at += r["n_tokens"]
    keys = [(-1 if r["doc_id"] is None else r["doc_id"]) for r in got]
    assert keys == sorted(keys)
    want = sorted((-1 if d is None else d, ids_of(library, t)) for d, t in rows)
    assert sorted((k, list(r["ids"])) for k, r in zip(keys, got, strict=True)) == want


def test_files_of_nothing(no_docs):
    assert token_files.read_tokens(token_files.write_tokens(no_docs, tokenizer_path())).count() == 0


def test_given_documents(spark, small, library):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    at = 0
    for r in sorted(token_files.read_tokens(token_files.write_tokens(docs, tokenizer_path())).collect(), key=lambda r: r["doc_id"]):
        ids = ids_of(library, text[r["doc_id"]])
        assert tuple(r) == (r["doc_id"], at, len(ids), crc(ids))
        at += len(ids)


def packed(rows, capacity):
    by = {}
    for r in rows:
        assert 0 < r["length"] <= capacity
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for spans in by.values():
        at = 0
        for off, n in sorted(spans):
            assert off == at
            at += n
        assert at <= capacity
    return len(by)


def test_packing(spark, odd_docs, library):
    capacity = 64
    pieces = packing.cut_pieces(odd_docs, tokenizer_path(), capacity=capacity)
    rows = packing.pack(pieces, capacity, group_rows=2).collect()
    packed(rows, capacity)
    docs = sorted((-1 if r["doc_id"] is None else r["doc_id"], ids_of(library, r["text"])) for r in odd_docs.collect())
    want = []
    for d, ids in docs:
        head = len(ids) % capacity or min(len(ids), capacity)
        for k, a in enumerate([0, *range(head, len(ids), capacity)]):
            part = ids[a : head if k == 0 else a + capacity]
            want.append((d, k, a, len(part), crc(part)))
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows) == sorted(want)


def test_packing_nothing(no_docs):
    assert packing.pack(packing.cut_pieces(no_docs, tokenizer_path())).count() == 0


def one_by_one(lengths, capacity):
    """Best-fit decreasing, a document at a time."""
    gaps = []
    for n in sorted(lengths, reverse=True):
        fit = [k for k, g in enumerate(gaps) if g >= n]
        if fit:
            gaps[min(fit, key=lambda k: gaps[k])] -= n
        else:
            gaps.append(capacity - n)
    return len(gaps)


@settings(max_examples=100, deadline=None)
@given(st.lists(st.integers(1, 40), max_size=60))
def test_runs_pack_as_single_documents_do(lengths):
    counts = {n: lengths.count(n) for n in set(lengths)}
    runs, n = packing.plan(counts, 40)
    assert n == one_by_one(lengths, 40)
    used: dict = {}
    for length, parts in runs.items():
        placed = 0
        for rank, first, sequences, each, offset in parts:
            assert rank == placed
            placed += sequences * each
            for s in range(first, first + sequences):
                assert used.get(s, 0) == offset
                used[s] = offset + each * length
                assert used[s] <= 40
        assert placed == counts[length]


def test_packing_is_tight():
    r = random.Random(5)
    lengths = [min(1024, int(r.expovariate(1 / 300)) + 1) for _ in range(20000)]
    counts = {n: lengths.count(n) for n in set(lengths)}
    assert packing.plan(counts, 1024)[1] <= 1.002 * (sum(lengths) / 1024) + 1
