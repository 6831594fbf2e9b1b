"""Tokens, fingerprints, combined hashes and registers."""

import numpy as np
from hypothesis import given
from hypothesis import strategies as st
from pyspark.sql import functions as F

from incdep.functions import fingerprint, fold, rho, rotate, row_token, token
from incdep.operators.sketch import _fold, lgk_for


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def test_rotate_then_xor(spark):
    h = signed(0x8000000000000001)
    assert spark.range(1).select(rotate(F.lit(h)).bitwiseXOR(F.lit(5)).alias("x")).first()["x"] == 6


def test_fold_of_one_is_identity_and_order_matters(spark):
    r = spark.range(1).select(fold([F.lit(7)]).alias("a"), fold([F.lit(7), F.lit(9)]).alias("b"), fold([F.lit(9), F.lit(7)]).alias("c")).first()
    assert r["a"] == 7 and r["b"] != r["c"]


@given(st.lists(st.integers(0, (1 << 64) - 1), min_size=1, max_size=5))
def test_vector_fold_matches_whole_numbers(values):
    acc = values[0]
    for v in values[1:]:
        acc = ((acc << 1) & ((1 << 64) - 1) | acc >> 63) ^ v
    assert int(_fold([np.asarray([v], np.uint64) for v in values])[0]) == acc


def test_null_differs_from_its_token_and_types_agree(spark):
    df = spark.createDataFrame([(None, 1), ("n", 1), ("vn", 1)], "s string, i int")
    assert len({r[0] for r in df.select(token(F.col("s"))).collect()}) == 3
    got = df.select(fingerprint(token(F.col("i"))).alias("a"), fingerprint(token(F.lit("1"))).alias("b"), fingerprint(token(F.lit(1).cast("long"))).alias("c")).first()
    assert got["a"] == got["b"] == got["c"]
    assert [r[0] for r in df.select(token(F.col("s"), "ignore")).collect()][0] is None


def test_long_values_become_digests_that_no_short_value_equals(spark):
    df = spark.createDataFrame([("a" * 65,), ("a" * 64,), ("x" + "a" * 64,)], "s string")
    got = [r[0] for r in df.select(token(F.col("s"))).collect()]
    assert got[0][0] == "x" and got[1][0] == "v" and got[2][0] == "x" and len(set(got)) == 3


def test_tuple_tokens_are_unambiguous(spark):
    df = spark.createDataFrame([("a", "b:1"), ("a:b", "1"), ("a1:", "b"), (None, "a")], "x string, y string")
    assert df.select(row_token([token(F.col("x")), token(F.col("y"))]).alias("t")).distinct().count() == 4


def test_rho(spark):
    r = spark.range(1).select(rho(F.lit(0), 4).alias("zero"), rho(F.lit(16), 4).alias("one"), rho(F.lit(32), 4).alias("two"), rho(F.lit(-1), 4).alias("all")).first()
    assert tuple(r) == (61, 1, 2, 1)


def test_registers_for_an_error():
    assert lgk_for(0.001) == 21 and lgk_for(0.0011) == 20 and lgk_for(0.5) == 4
