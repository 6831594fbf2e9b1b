"""Corpus pipeline: language ID, near-duplicates, mixing to target weights, best-fit packing.

Each stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept and returns a DataFrame, which is
written as Parquet and reread as the next one's ``docs``. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from incdep.llm import language, mixing, near_dups, packing
from incdep.llm.common import with_numbers, with_row_key, written
from incdep.llm.queries import tokenizer_path


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in one of the languages that the labelled rows teach; texts without any letter go."""
    return language.keep_identified(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: five-word shingles, a similarity of 0.8 or more."""
    return near_dups.drop_near_duplicates(docs, k=5, percent=80)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row as often as the mix takes it: absent, once, or up to three times; ids may be null or repeated."""
    key = "_row"
    while any(c.lower().startswith(key) for c in docs.columns):
        key += "_"
    keyed, copies = with_row_key(docs, key), f"{key}_copies"
    plan = mixing.mix(keyed, key=key).filter("copies > 0").select(key, F.col("copies").alias(copies))
    many = with_numbers(keyed, key, copies, plan)
    return many.withColumn(key, F.explode(F.array_repeat(F.lit(1), F.col(copies).cast("int")))).select(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 1024 tokens in as few sequences as best fit finds."""
    return packing.pack(packing.cut_pieces(docs, tokenizer_path()))


STAGES = [("language_id", language_id), ("near_duplicates", near_duplicates), ("mixture", mixture), ("packing", pack)]

#: Language ID and tokenization have no SQL form; the tests hold the stages against brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = written(docs, f"stage-{name}")
    return docs
