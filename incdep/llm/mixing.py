"""Mixing sources to target weights by Pareto order sampling.

Every document gets a rate, its expected number of copies. The whole part of the rate is allocated for certain;
the rest is an inclusion probability p. Documents of a source are ranked by random odds over inclusion odds,
u/(1-u) over p/(1-p), and the first ones are taken as far as their sizes fit what the certain copies leave of the
target; the rest of it is filled from all later ones in rank, each taken if it still fits, and by the one of those left
over whose size comes nearest to what is left, if that makes the difference smaller.
u comes from a hash of the document id and a seed, so reruns and other partitionings agree.

Defined cases: null text has size 0; a null source is a source of its own, last in order; a null id has a u of its
own; repeated rows each count and tie in rank; sources of size 0 get target 0; an empty table gives no rows.
Extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, running_total, written

MAX_COPIES = 3


def uniform(key: Column, seed: str) -> Column:
    """A number in (0, 1) from 52 bits of an md5 digest; other engines can compute the same."""
    text = F.concat(F.coalesce(key.cast("string"), F.lit("")), F.lit(seed))
    return (F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("long") + F.lit(0.5)) / F.lit(float(1 << 52))


def source_targets(sizes: DataFrame, weights: Sequence[int] = (5, 2, 1), max_copies: int = MAX_COPIES) -> DataFrame:
    """Targets of ``sizes(source, source_size)``, one row a source: the total shared by weight, none above ``max_copies`` times its source.

    Sources at their cap are those with the smallest cap a weight, so one sorted sweep finds how many stop, and the
    level of the others: no repeated resharing.
    """
    order = Window.orderBy(F.col("source").isNull(), "source")
    every = Window.partitionBy()
    w = F.array(*(F.lit(int(x)) for x in weights))
    t = sizes.withColumn("_w", F.element_at(w, (F.row_number().over(order) - 1) % len(weights) + 1)).withColumn("_cap", F.col("source_size") * max_copies)
    ratio = F.col("_cap") / F.col("_w")
    sweep = Window.orderBy(ratio, F.col("source").isNull(), "source").rowsBetween(Window.unboundedPreceding, -1)
    t = t.withColumn("_total", F.sum("source_size").over(every)).withColumn("_left", F.sum("_w").over(every) - F.coalesce(F.sum("_w").over(sweep), F.lit(0)))
    t = t.withColumn("_level", (F.col("_total") - F.coalesce(F.sum("_cap").over(sweep), F.lit(0))) / F.col("_left"))
    # the first source, in order of ratio, whose own ratio reaches the level that holds when all before it stop
    t = t.withColumn("_found", F.min(F.when(F.col("_level") <= ratio, F.struct(ratio.alias("r"), F.col("_level").alias("l")))).over(every))
    target = F.when(F.col("_found").isNull() | (ratio < F.col("_found.r")), F.col("_cap").cast("double")).otherwise(F.least(F.col("_found.l") * F.col("_w"), F.col("_cap").cast("double")))
    return t.select("source", "source_size", target.alias("target"))


def fill(rows: DataFrame, gaps: DataFrame, group: Sequence[str]) -> tuple[DataFrame, DataFrame]:
    """Take the rows of ``rows(*group, _cum, size)`` that still fit, one after another by ``_cum``, into ``gaps(*group, _gap)``.

    Returns the taken rows (*group, _cum) and what is left of each gap. A round sums the sizes up to half the gap along
    the order; up to their overflow they are all taken, unless a row above half fits before: then that one, and what
    stands in front of it. Rows passed over fit no later gap. Either way less than half of the gap is left, so rounds
    grow with the logarithm of the gap, whatever the number of rows. Sizes must be positive, ``_cum`` unique in a group.
    """
    group = list(group)
    columns = [*group, "_cum", "size"]
    taken: list[DataFrame] = []
    todo = written(rows.select(*columns).join(gaps, group).filter(F.col("size") <= F.col("_gap")), "mix-fill")
    while not todo.isEmpty():
        small = 2 * F.col("size") <= F.col("_gap")
        run = running_total(todo.withColumn("_part_size", F.when(small, F.col("size")).otherwise(0)), group, ["_cum"], "_part_size", "_acc", "mix-fill-laid")
        run = written(run.drop("_part_size"), "mix-fill-run")
        big = F.min(F.when(~small & (F.col("_acc") + F.col("size") <= F.col("_gap")), F.col("_cum"))).alias("_big")
        over = F.min(F.when(small & (F.col("_acc") > F.col("_gap")), F.col("_cum"))).alias("_over")
        stops = written(run.groupBy(*group).agg(big, over), "mix-fill-stops")
        run = run.join(stops, group)
        got = run.filter((small & (F.col("_acc") <= F.col("_gap")) & (F.col("_big").isNull() | (F.col("_cum") < F.col("_big")))) | (F.col("_cum") == F.col("_big")))
        got = written(got.select(*columns), "mix-fill-taken")
        taken.append(got.select(*group, "_cum"))
        used = got.groupBy(*group).agg(F.sum("size").alias("_used"))
        gaps = written(gaps.join(used, group, "left").select(*group, (F.col("_gap") - F.coalesce("_used", F.lit(0))).alias("_gap")), "mix-gaps")
        later = run.filter(F.col("_cum") > F.coalesce("_big", "_over")).select(*columns)
        todo = written(later.join(gaps, group).filter(F.col("size") <= F.col("_gap")), "mix-fill")
    none = rows.select(*group, "_cum").limit(0)
    return reduce(DataFrame.unionByName, taken, none), gaps


def mix(docs: DataFrame, weights: Sequence[int] = (5, 2, 1), max_copies: int = MAX_COPIES, seed: str = "mix", weight: Column | None = None, key: str | None = None) -> DataFrame:
    """(doc_id, source, size, source_size, target, copies, taken) for every row of ``docs(doc_id, text, source)``.

    ``weight`` (positive) makes the rates inside a source unequal: a document's rate is its source's times its weight
    over the source's mean weight by size, at most ``max_copies``. ``key`` names a column of ``docs`` to hand through.
    """
    keys = [F.col(key).alias("_row")] if key else []
    size = F.size(F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(WORD), F.lit(0))).cast("long")
    rows = docs.select(F.col("doc_id").cast("long"), "source", size.alias("size"), (F.lit(1.0) if weight is None else weight.cast("double")).alias("_wt"), *keys)
    rows = written(rows, "mix-sizes")
    by = rows.groupBy("source").agg(F.sum("size").alias("source_size"), F.sum(F.col("_wt") * F.col("size")).alias("_ws"))
    t = source_targets(by.select("source", "source_size"), weights, max_copies).join(by.select(F.col("source").alias("_s"), "_ws"), F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    t = t.withColumn("_rate", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0))
    t = t.withColumn("_mean", F.when(F.col("source_size") > 0, F.col("_ws") / F.col("source_size")).otherwise(1.0)).drop("_ws")
    t = written(t, "mix-targets")
    rows = rows.join(t.withColumnRenamed("source", "_s"), F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    rate = F.least(F.col("_rate") * F.col("_wt") / F.col("_mean"), F.lit(float(max_copies))) if weight is not None else F.col("_rate")
    rows = rows.withColumn("_rate", rate).withColumn("_sure", F.floor("_rate")).withColumn("_p", F.least(F.greatest(F.col("_rate") - F.col("_sure"), F.lit(1e-9)), F.lit(1 - 1e-9)))
    u = F.col("_u")
    rows = rows.withColumn("_u", uniform(F.col("doc_id"), seed)).withColumn("_key", (u / (1 - u)) / (F.col("_p") / (1 - F.col("_p"))))
    rows = rows.withColumn("_none", F.col("source").isNull().cast("int")).withColumn("_name", F.coalesce("source", F.lit("")))
    rows = rows.withColumn("_id", F.coalesce("doc_id", F.lit(-1)))
    group = ["_none", "_name"]
    sure = written(rows.groupBy(*group).agg(F.sum(F.col("size") * F.col("_sure")).alias("_certain")), "mix-certain")
    ranked = running_total(rows.drop("_wt", "_mean"), group, ["_key", "_id", "size"], "size", "_cum", "mix-ranked").join(sure, group)
    room = F.col("target") - F.col("_certain")
    can = F.col("_sure") < max_copies
    first = written(ranked.withColumn("_in", can & (F.col("_cum") <= room)), "mix-first")
    gaps = first.groupBy(*group).agg((F.first(room) - F.sum(F.when(F.col("_in"), F.col("size")).otherwise(0))).alias("_gap"))
    # what is left of a source's target is filled from the later documents in rank, each taken if it still fits; the
    # running sum is their order, and tells repeated rows apart, but for empty ones
    free = first.filter(can & ~F.col("_in") & (F.col("size") > 0)).select(*group, "_cum", "size")
    more, gaps = fill(free, written(gaps, "mix-gaps"), group)
    more = more.withColumn("_extra", F.lit(True))
    near = F.min(F.struct(F.abs(F.col("_gap") - F.col("size")).alias("miss"), F.col("_cum").alias("cum"), F.abs("_gap").alias("left"))).alias("_near")
    best = free.join(more, [*group, "_cum"], "left").filter(F.col("_extra").isNull()).join(gaps, group).groupBy(*group).agg(near)
    best = written(best.filter("_near.miss < _near.left").select(*group, F.col("_near.cum").alias("_best")), "mix-best")
    out = first.join(more, [*group, "_cum"], "left").join(best, group, "left")
    last = can & ~F.col("_in") & F.coalesce(F.col("_cum") == F.col("_best"), F.lit(False))
    extra = (F.coalesce("_extra", F.lit(False)) | last) & (F.col("size") > 0)
    copies = F.col("_sure") + (F.col("_in") | extra).cast("long")
    handed = [F.col("_row").alias(key)] if key else []
    return out.withColumn("copies", copies).select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("size") * F.col("copies")).alias("taken"), *handed)
