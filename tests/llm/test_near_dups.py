"""Near-duplicates of texts and of vectors, components and top-k search against brute force."""

import itertools
import os
import re
import time
from unittest import mock

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from incdep.llm import embedding_dups, near_dups, topk
from incdep.llm import common
from incdep.llm.common import components, may_match, shared_root, with_numbers, with_row_key, without, written
from incdep.llm.shingles import shingle_sets, word_hashes

LOWER = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def shingles(text, k):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def grouped(nodes, links):
    up = {n: n for n in nodes}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text("abC é \n\t  ", max_size=20), max_size=6), st.integers(1, 4))
def test_sets_have_as_many_items_as_texts_have_shingles(texts, k):
    got = shingle_sets([t.encode().lower() for t in texts], k)
    sets = [shingles(t, k) for t in texts]
    assert [len(g) for g in got] == [len(s) for s in sets]
    for (g, s), (h, t) in itertools.combinations(zip(got, sets, strict=True), 2):
        assert len(np.intersect1d(g, h)) == len(s & t)


def thue_morse(n, swap=False):
    return "".join("ab"[(k.bit_count() & 1) ^ swap] for k in range(n))


def test_words_that_collide_under_polynomials(spark):
    one, two = thue_morse(2048), thue_morse(2048, True)
    rows = [(1, one), (2, two), (3, f"{one} {one} x"), (4, f"{two} {one} x")]
    got = near_dups.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), 3, 85).collect()
    assert all(r["kept"] and r["component_id"] == r["doc_id"] for r in got)


def test_words_of_a_text_longer_than_a_part():
    text = b" ".join(b"w%d" % (k % 1000) for k in range(400_000)) + b" " + b"y" * (3 << 20) + b" end"
    words, first = word_hashes([text, b"w1 w2"])
    assert first.tolist() == [0, 400_002, 400_004] and len(np.unique(words)) == 1002
    assert words[1] == words[-2] and words[2] == words[-1]


def docs_with_copies(spark):
    r = np.random.default_rng(3)
    words = [f"w{k}" for k in range(400)]
    base = [list(r.choice(words, n)) for n in (120, 60, 200, 30, 8)]
    rows = []
    for b in base:
        for change in (0, 0, 1, 2, 4, 8, 15):
            t = list(b)
            for _ in range(min(change, len(b) // 8)):
                t[r.integers(len(t))] = str(r.choice(words))
            rows.append(" ".join(t))
    rows += [" ".join(r.choice(words, 50)) for _ in range(30)]
    chain = list(r.choice(words, 150))  # each like its neighbour, the ends unlike
    for k in range(12):
        chain = [*chain[5:], *r.choice(words, 5)]
        rows.append(" ".join(chain))
    return spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")


@pytest.mark.parametrize("k,percent", [(3, 85), (5, 80), (2, 60)])
def test_near_duplicates(spark, k, percent, monkeypatch):
    monkeypatch.setattr(near_dups, "BLOCK", 3)
    docs = docs_with_copies(spark)
    sets = {r["doc_id"]: shingles(r["text"], k) for r in docs.collect()}
    links = [(a, b) for a, b in itertools.combinations(sets, 2) if sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    want = grouped(sets, links)
    got = {r["doc_id"]: r for r in near_dups.near_duplicates(docs, k, percent).collect()}
    assert len(got) == len(sets) and len(set(want.values())) < len(want)
    for d in sets:
        assert (got[d]["n_shingles"], got[d]["component_id"], got[d]["kept"]) == (len(sets[d]), want[d], want[d] == d)
    assert {r["doc_id"] for r in near_dups.drop_near_duplicates(docs, k, percent).collect()} == set(want.values())


def test_a_large_group_of_near_copies(spark, monkeypatch):
    """Many variants of one text, most of them linked, and some just below the threshold, in buckets over the small limit."""
    r = np.random.default_rng(8)
    words = [f"v{k}" for k in range(5000)]
    base = list(r.choice(words, 100))
    rows = []
    for k in range(120):
        t = list(base)
        for p in r.choice(100, k % 4 + 1, replace=False):
            t[p] = str(r.choice(words))
        rows.append((k, " ".join(t)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(near_dups, "BLOCK", 40)
    sets = {d: shingles(t, 3) for d, t in rows}
    want = grouped(sets, [(a, b) for a, b in itertools.combinations(sets, 2) if 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b])])
    assert {r["doc_id"]: r["component_id"] for r in near_dups.near_duplicates(docs, 3, 85).collect()} == want


def test_odd_rows(odd_docs, no_docs):
    got = near_dups.near_duplicates(odd_docs, 3, 85).collect()
    assert len(got) == odd_docs.count()
    by = {r["doc_id"]: r for r in got if r["doc_id"] is not None}
    assert by[9]["component_id"] == by[8]["component_id"] == by[10]["component_id"] == 8
    assert all(by[k]["kept"] and by[k]["n_shingles"] == 0 for k in (0, 1, 2))
    assert by[4]["component_id"] == 4
    kept = near_dups.drop_near_duplicates(odd_docs, 3, 85)
    assert kept.columns == odd_docs.columns and kept.filter("doc_id in (9, 10)").isEmpty()
    assert near_dups.near_duplicates(no_docs, 3, 85).count() == 0 and near_dups.drop_near_duplicates(no_docs).count() == 0


def test_registers_merge_and_estimate():
    r = np.random.default_rng(1)
    a, b = (np.unique(r.integers(0, 1 << 63, 900).astype(np.uint64)) for _ in range(2))
    both = np.unique(np.concatenate([a, b]))
    ra, rb, rab = near_dups.registers([a, b, both], 400)
    assert (np.maximum(ra, rb) == rab).all()
    est = near_dups.similarity(np.asarray([float(len(a))]), np.asarray([float(len(both))]), np.asarray([(ra > rab).sum()]), np.asarray([(ra < rab).sum()]), 400)
    assert abs(est[0] - len(a) / len(both)) < 0.1


def test_components(spark):
    links = [(1, 2), (2, 3), (3, 4), (10, 11), (7, 7), (20, 4)] + [(30, k) for k in range(31, 200)] + [(k, k + 1) for k in range(300, 400)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == grouped({x for e in links for x in e}, links)
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_bit_table(spark):
    df, keys = spark.range(1000).withColumnRenamed("id", "k"), spark.createDataFrame([(5,), (7,), (None,)], "k long")
    assert {5, 7} <= {r["k"] for r in may_match(df, "k", keys, 1 << 12).filter("_may").collect()}
    assert sorted(r["k"] for r in without(df, "k", keys).collect()) == [k for k in range(1000) if k not in (5, 7)]


def shuffle_files(spark):
    """Names of the shuffle data files that the session holds."""
    files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    names = (files.apply(k).getName() for k in range(files.size()))
    return {n for n in names if n.startswith("shuffle_") and n.endswith(".data")}


def test_a_written_table_leaves_no_shuffle_files(spark):
    before = shuffle_files(spark)
    df = spark.range(5000).repartition(4).groupBy("id").count()
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    setting = spark.conf.get(name, None)
    table = written(df, "counts")  # the table's data frame is kept, as operators keep theirs
    for _ in range(50):
        if not (left := shuffle_files(spark) - before):
            break
        time.sleep(0.1)
    assert not left and table.count() == 5000 and df.count() == 5000
    assert spark.conf.get(name, None) == setting


def test_wide_tables_of_near_duplicates_go_early(spark, monkeypatch):
    """Registers of all documents are gone once candidates are known, and full sets once links are."""
    seen = {}
    root = shared_root(spark).removeprefix("file://")
    old = set(os.listdir(root))

    def watched(df, tag):
        out = written(df, tag)
        seen.setdefault(tag, []).append({f.rpartition("-")[0] for f in set(os.listdir(root)) - old})
        return out

    monkeypatch.setattr(near_dups, "written", watched)
    rows = near_dups.near_duplicates(docs_with_copies(spark), 3, 85).count()
    assert rows == docs_with_copies(spark).count()
    assert not {"sketches", "reps", "bands"} & seen["stars"][0] and "sets" in seen["links"][0]
    assert not {"sketches", "registers", "sets"} & seen["near-dups"][0]


def test_numbers_of_rows_in_several_files(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(common, "CHUNK", 7)
    spark.range(100).selectExpr("id", "repeat('x', 30) AS text").repartition(3, "id").write.parquet(str(tmp_path / "t"))
    df = with_row_key(spark.read.parquet(str(tmp_path / "t")), "k")
    want = {k: (k % 4 if k % 10 else 255) if k > 40 or k % 3 else 0 for k in range(100)}
    given_ = df.join(spark.createDataFrame([kv for kv in want.items() if kv[1]], "id long, n long"), "id").select("k", "n")
    assert {r["id"]: r["n"] for r in with_numbers(df, "k", "n", given_).collect()} == want
    assert {r["n"] for r in with_numbers(df, "k", "n", given_.limit(0)).collect()} == {0}
    with pytest.raises(Exception, match="from 0 to 255"):
        with_numbers(df, "k", "n", given_.selectExpr("k", "n + 1 AS n"))


def vectors(spark):
    r = np.random.default_rng(2)
    rows = [(k, v.tolist()) for k, v in enumerate(r.normal(size=(60, 12)))]
    rows += [(100 + k, (np.asarray(rows[k][1]) * (k + 1)).tolist()) for k in range(5)]
    rows += [(200 + k, (np.asarray(rows[3][1]) + r.normal(size=12) * 0.15).tolist()) for k in range(40)]
    rows += [(300 + k, rows[7][1]) for k in range(6)]
    rows += [(400, [0.0] * 12), (401, None), (402, [float("nan")] + [1.0] * 11), (403, [None] + [1.0] * 11), (404, [float("inf")] + [1.0] * 11), (405, [1.0, 2.0]), (406, [1.0, 2.1]), (407, [])]
    rows += [(None, rows[7][1])]
    return spark.createDataFrame(rows, "vec_id long, embedding array<double>"), rows


def usable(v):
    return v is not None and all(x is not None and np.isfinite(x) for x in v)


def test_embedding_links(spark):
    df, rows = vectors(spark)
    good = {i: np.asarray(v) for i, v in rows if i is not None and usable(v) and any(v)}
    links = [(a, b) for a, b in itertools.combinations(good, 2) if len(good[a]) == len(good[b]) and good[a] @ good[b] / np.linalg.norm(good[a]) / np.linalg.norm(good[b]) >= 0.9]
    want = grouped([i for i, _ in rows if i is not None], links)
    got = {r["vec_id"]: r for r in embedding_dups.near_duplicates(df, 0.9, rows_per_block=16).collect()}
    assert len(got) == len(rows) and len(links) > 100
    for i, _ in rows:
        n = sum(i in e for e in links) if i is not None else 0
        assert (got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (n, want.get(i), i is None or want[i] == i)


def test_links_exactly_at_the_threshold(spark):
    """Multiples of whole-numbered vectors whose cosines are 0.9 to the last bit, in sparse and in dense tiles."""
    base = [[10, 0, 0, 0], [9, 3, 3, 1], [9, -3, 3, 1], [0, 10, 0, 0], [3, 9, 1, 3], [9, 3, -3, -1], [0, 0, 10, 0], [3, 3, 9, 1]]
    rows = [(k, [float(x * (1 + k // 8) * (2.0**600 if k % 16 == 3 else 1)) for x in base[k % 8]]) for k in range(200)]
    whole = {k: np.asarray(base[k % 8], "f8") for k, _ in rows}
    links = {k: sum(j != k and whole[k] @ whole[j] / (np.linalg.norm(whole[k]) * np.linalg.norm(whole[j])) >= 0.9 for j in whole) for k in whole}
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {r["vec_id"]: r["n_links"] for r in embedding_dups.near_duplicates(df, 0.9, rows_per_block=64).collect()}
    assert got == links and len(set(links.values())) > 1


@pytest.mark.parametrize("clause", ["false", "vec_id = 400", "vec_id = 405"])
def test_embedding_few(spark, clause):
    df, _ = vectors(spark)
    rows = embedding_dups.near_duplicates(df.filter(clause)).collect()
    assert all(r["n_links"] == 0 and r["kept"] for r in rows) and len(rows) == (clause != "false")


@pytest.mark.parametrize("scale", [1, 256, 1 << 27])
def test_top_k(spark, scale):
    df, rows = vectors(spark)
    good = {i: [int(np.floor(scale * x)) for x in v] for i, v in rows if i is not None and usable(v) and len(v)}
    ask = [i for i in good if i % 4 == 0]
    got = topk.search(df, df.filter("vec_id % 4 = 0"), 5, scale, rows_per_block=32, queries_per_block=8).collect()
    want = []
    for q in ask:
        s = sorted(((-sum(a * b for a, b in zip(good[q], v, strict=True)), i) for i, v in good.items() if i != q and len(v) == len(good[q])))[:5]
        want += [(q, k + 1, i, -x) for k, (x, i) in enumerate(s)]
    assert sorted(map(tuple, got)) == sorted(want)


def test_top_k_of_nothing(spark):
    df, _ = vectors(spark)
    assert topk.search(df, df.limit(0)).count() == 0 and topk.search(df.limit(0), df.filter("vec_id < 3")).count() == 0


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 40), st.integers(1, 5), st.integers(0, 10**6))
def test_threshold_algorithm_with_ties(n, dims, seed):
    r = np.random.default_rng(seed)
    x, ids = r.integers(-2, 3, (n, dims)).astype("f8"), r.permutation(n * 2)[:n]
    q = r.integers(-2, 3, dims).astype("f8")
    got = topk.SortedLists(ids, x).search(int(ids[0]), q, 3, first=1)
    want = sorted((-s, i) for s, i in zip(x @ q, ids, strict=True) if i != ids[0])[:3]
    assert [(-s, i) for i, s in zip(*got, strict=True)] == want


def test_tasks_forget_words_and_encoder():
    from incdep.llm import bpe, near_dups, shingles

    class Docs:  # hands the task's function out
        def select(self, *_):
            return self

        def mapInArrow(self, run, schema):
            return run

    bpe._LOADED["path", 1] = object()
    texts = pa.RecordBatch.from_arrays([pa.array([1, 2]), pa.array(["one two three four five six", None])], names=["doc_id", "text"])
    with mock.patch.object(near_dups.F, "col"):
        tasks = near_dups.sketches(Docs(), 3, 10), near_dups.full_sets(Docs(), 3)
    for run in tasks:
        assert sum(b.num_rows for b in run(iter([texts]))) == 2
        assert not bpe._LOADED and not shingles._DIGESTS and not shingles._DIGESTS.held
