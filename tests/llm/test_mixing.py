"""Mixing: targets, closeness, copies, reruns."""

import hashlib
import itertools
import random
import re

import pytest
from pyspark.sql import functions as F

from incdep.llm import mixing


def reshared(sizes, weights, cap=3):
    """Targets by sharing again and again, as the definition says."""
    total, left, target = sum(sizes), set(range(len(sizes))), {}
    share = total
    while left:
        w = sum(weights[k] for k in left)
        over = {k for k in left if share * weights[k] / w > cap * sizes[k] + 1e-9}
        if not over:
            target |= {k: share * weights[k] / w for k in left}
            break
        for k in over:
            target[k] = cap * sizes[k]
            share -= cap * sizes[k]
        left -= over
    return [target[k] for k in range(len(sizes))]


@pytest.mark.parametrize("sizes", [[10, 10, 10], [1, 100, 1000], [1000, 1, 1, 1, 5, 0, 7], [0, 0, 5], [0], [3, 900, 20, 20, 1, 4000, 2, 2, 2]])
def test_targets(spark, sizes):
    df = spark.createDataFrame([(chr(97 + k), n) for k, n in enumerate(sizes)], "source string, source_size long")
    got = {r["source"]: r["target"] for r in mixing.source_targets(df).collect()}
    want = reshared(sizes, [(5, 2, 1)[k % 3] for k in range(len(sizes))])
    assert [got[chr(97 + k)] for k in range(len(sizes))] == pytest.approx(want)
    assert sum(got.values()) == pytest.approx(sum(sizes))


def test_mix_of_given_documents(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    got = mixing.mix(docs).persist()
    assert got.count() == docs.count()
    assert got.filter(F.col("taken") > 3 * F.col("size")).isEmpty()
    free = F.min(F.when((F.col("copies") < 3) & (F.col("size") > 0), F.col("size")))  # no free document would come nearer
    for r in got.groupBy("source").agg(F.sum("taken").alias("taken"), F.first("target").alias("target"), free.alias("free")).collect():
        assert abs(r["taken"] - r["target"]) <= max(0.05 * r["target"], (r["free"] or 0) / 2 + 1)
    again = mixing.mix(docs.repartition(7))
    assert got.exceptAll(again).isEmpty() and again.exceptAll(got).isEmpty()


def test_rates_are_shared_inside_a_source(spark):
    """Without weights each document of a source is as likely to be taken; odds differ between seeds only."""
    docs = spark.range(600).select(F.col("id").alias("doc_id"), F.lit("a b c d").alias("text"), F.when(F.col("id") < 400, "x").otherwise("y").alias("source"))
    taken = sum(mixing.mix(docs, (1, 1), seed=f"s{k}").filter("doc_id = 5").first()["copies"] for k in range(12))
    assert 3 <= taken <= 12
    heavy = mixing.mix(docs, (1, 1), weight=F.when(F.col("doc_id") % 2 == 0, 3.0).otherwise(1.0))
    by = {r["e"]: r["n"] for r in heavy.filter("source = 'x'").groupBy((F.col("doc_id") % 2 == 0).alias("e")).agg(F.sum("copies").alias("n")).collect()}
    assert by[True] > 1.5 * by[False]


def test_odd_rows(odd_docs, no_docs):
    rows = mixing.mix(odd_docs).collect()
    assert len(rows) == odd_docs.count()
    sizes = sorted(len(re.findall(r"[^\x20\x09-\x0D]+", r["text"] or "")) for r in odd_docs.collect())
    assert sorted(r["size"] for r in rows) == sizes
    assert all(r["taken"] == r["copies"] * r["size"] and 0 <= r["copies"] <= 3 for r in rows)
    assert mixing.mix(no_docs).count() == 0


def greedy(sizes, gap):
    """Places taken one after another as long as each still fits, and what is left."""
    taken = []
    for k, n in enumerate(sizes):
        if n <= gap:
            taken.append(k)
            gap -= n
    return taken, gap


def test_fill_equals_one_after_another(spark):
    rnd = random.Random(5)
    lists = {"falling": ([x for k in range(300) for x in (1, 300 - k)], 300.0), "nothing": ([9, 9], 8.5), "all": ([3] * 50, 1e6)}
    lists |= {f"r{k}": ([rnd.choice((1, 2, 5, 40, 700)) * rnd.randint(1, 9) for _ in range(400)], rnd.uniform(0, 9000)) for k in range(6)}
    rows, want = [], set()
    for name, (sizes, gap) in lists.items():
        cums = list(itertools.accumulate(sizes))
        rows += [(name, c, n) for c, n in zip(cums, sizes, strict=True)]
        want |= {(name, cums[k]) for k in greedy(sizes, gap)[0]}
    gaps = spark.createDataFrame([(name, gap) for name, (_, gap) in lists.items()], "g string, _gap double")
    taken, left = mixing.fill(spark.createDataFrame(rows, "g string, _cum long, size long"), gaps, ["g"])
    got = [tuple(r) for r in taken.collect()]
    assert len(got) == len(set(got)) and set(got) == want
    assert {r["g"]: r["_gap"] for r in left.collect()} == pytest.approx({name: greedy(*x)[1] for name, x in lists.items()})


def test_one_very_long_document(spark):
    """A source is filled from all its documents, also where a long one leaves a gap of hundreds of short ones."""
    sizes = {k: 9000 if k in (0, 1) else 4 + k % 9 for k in range(2400)}
    docs = spark.createDataFrame([(k, "w " * n, "ab"[k % 2]) for k, n in sizes.items()], "doc_id long, text string, source string")
    for seed in ("a", "b", "c"):
        rows = mixing.mix(docs, (5, 3), seed=seed).collect()
        for source in "ab":
            mine = [r for r in rows if r["source"] == source]
            target = mine[0]["target"]
            rate = target / mine[0]["source_size"]
            u = lambda r: (int(hashlib.md5(f"{r['doc_id']}{seed}".encode()).hexdigest()[:13], 16) + 0.5) / (1 << 52)  # noqa: B023, E731
            order = sorted(mine, key=lambda r: (u(r) / (1 - u(r)), r["doc_id"]))
            taken, gap = greedy([r["size"] for r in order], target - int(rate) * mine[0]["source_size"])
            free = [k for k in range(len(order)) if k not in set(taken)]
            if free and abs(gap - order[best := min(free, key=lambda k: abs(gap - order[k]["size"]))]["size"]) < gap:
                taken.append(best)
            assert {r["doc_id"] for r in mine if r["copies"] > int(rate)} == {order[k]["doc_id"] for k in taken}
            assert abs(sum(r["taken"] for r in mine) - target) <= min((order[k]["size"] for k in free), default=0) / 2 + 1
