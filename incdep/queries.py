"""The registered queries: every method, variant, baseline, measure and workload of discovery on the given tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads as W
from .catalog import Catalog
from .discover import discover, flatten, profile, result, unary_pairs
from .functions import fingerprint, fold, has_bit, token
from .operators import attr_values, dedupe, derived, exact, lattice, sketch
from .plans import written
from .sources.writers import totals
from .streaming.incremental import IncrementalInds

Query = Callable[[SparkSession, str], DataFrame]


def found(spark: SparkSession, sf_dir: str, data: str = "core", **options) -> DataFrame:
    """Flat dependencies of a data set."""
    return flatten(discover((W.DATASETS | {"wide_all": W.wide_all})[data](spark, sf_dir), **options))


def names(df: DataFrame, catalog: Catalog, attr: str = "attr") -> DataFrame:
    one = catalog.dictionary(catalog.spark).select(F.col("attr").alias(attr), "table_name", "column_name")
    return df.join(F.broadcast(one), attr).drop(attr)


def deduped(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    catalog = W.core(spark, sf_dir)
    return names(dedupe.summary(dedupe.distinct_values(catalog, kind)), catalog)


def flat_pairs(pairs: DataFrame, catalog: Catalog) -> DataFrame:
    return flatten(result(lattice.as_level(pairs, catalog), catalog))


def inverted_index_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.inverted_sets(attr_values.unpivot_all(W.core(spark, sf_dir))).withColumn("members", F.concat_ws(",", "members"))


def pairwise_joined_unary(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog = W.core(spark, sf_dir)
    return flat_pairs(exact.pairwise_joined(attr_values.unpivot_all(catalog).distinct()), catalog)


def attr_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog = W.everything(spark, sf_dir)
    return names(attr_values.attr_stats(catalog), catalog)


def dataset_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return profile({n: f(spark, sf_dir) for n, f in W.DATASETS.items()}, {"wide": 1})


def lattice_candidates_2(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog = W.core(spark, sf_dir)
    return flatten(result(lattice.next_level(written(lattice.as_level(unary_pairs(catalog), catalog), "level"), 1), catalog))


def merge_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Work of the merge engine: value ranges, heap steps, values read, attributes that stopped early."""
    catalog = W.core(spark, sf_dir)
    return exact.merge_counters(dedupe.as_set(catalog), len(catalog.attributes))


def _orders_md5(spark: SparkSession, sf_dir: str) -> tuple[Catalog, DataFrame]:
    catalog = Catalog({"orders": spark.read.parquet(f"{sf_dir}/orders.parquet")})
    return catalog, sketch.hash_tables(catalog, "md5")["orders"]


def sketch_registers_md5(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog, hashed = _orders_md5(spark, sf_dir)
    return sketch.registers(sketch.fill({"orders": hashed}, [(a.id,) for a in catalog.attributes], None, catalog, 8, width=60))


def sketch_sample_md5(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog, hashed = _orders_md5(spark, sf_dir)
    return sketch.sample_rows(hashed, 50, 60).toDF(*(a.column for a in catalog.attributes))


def sketch_index_keys_md5(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog, hashed = _orders_md5(spark, sf_dir)
    return sketch.index_keys({"orders": sketch.sample_rows(hashed, 50, 60)}, [(a.id,) for a in catalog.attributes], catalog, 60)


def combined_hash_md5(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    h = fold([fingerprint(token(F.col(c), compact=False), "md5") for c in ("l_orderkey", "l_linenumber", "l_shipdate")], 60)
    return items.select(h.alias("h")).groupBy("h").agg(F.count(F.lit(1)).alias("n"))


def sketch_estimates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct values of each core column by registers of 2^12, without an index; to three places."""
    catalog = W.core(spark, sf_dir)
    filled = sketch.fill(sketch.hash_tables(catalog, "md5"), [(a.id,) for a in catalog.attributes], None, catalog, 12, width=60)
    return names(sketch.estimate(sketch.registers(filled), 12), catalog, "combo").withColumn("estimate", F.round("estimate", 3))


def _prepared(spark: SparkSession, sf_dir: str) -> tuple[Catalog, list[tuple[int, ...]], dict[str, DataFrame], DataFrame]:
    """The core tables hashed by md5, and the index keys of samples of 500."""
    catalog = W.core(spark, sf_dir)
    combos = [(a.id,) for a in catalog.attributes]
    hashed = sketch.hash_tables(catalog, "md5", keep=True)
    samples = {k: written(sketch.sample_rows(v, 500, 60), "sample") for k, v in hashed.items()}
    return catalog, combos, hashed, written(sketch.index_keys(samples, combos, catalog, 60), "keys")


def filled_counts(spark: SparkSession, sf_dir: str, engine: str) -> DataFrame:
    """(table_name, column_name, n_keys, n_registers, rho_sum): index entries and registers of each column after the fill, at the default parameters."""
    catalog, combos, hashed, keys = _prepared(spark, sf_dir)
    filled = sketch.fill(hashed, combos, keys, catalog, sketch.lgk_for(0.001), engine, 60)
    got = filled.groupBy("combo").agg(F.count_if("hit").alias("n_keys"), F.count_if(~F.col("hit")).alias("n_registers"), F.sum("rho").alias("rho_sum"))
    return names(got, catalog, "combo")


def filled_members(spark: SparkSession, sf_dir: str, members: str) -> DataFrame:
    """(members, n_values): the filled index by its distinct sets of columns."""
    catalog, combos, hashed, keys = _prepared(spark, sf_dir)
    n = len(combos)
    index = sketch.fill_index(hashed, combos, keys, catalog, members, 60)
    if members == "bits":
        words = [c for c in index.columns if c != "h"]
        index = index.select(F.filter(F.sequence(F.lit(0), F.lit(n - 1)), lambda x: has_bit(words, x)).alias("members"))
    return index.groupBy(F.concat_ws(",", "members").alias("members")).agg(F.count(F.lit(1)).alias("n_values"))


def worked_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flatten(discover(W.worked_example(spark, sf_dir)))


def partial_inds(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog = W.core(spark, sf_dir)
    got = derived.named(derived.partial_inds(attr_values.unpivot_all(catalog), len(catalog.attributes), 0.1), catalog)
    return got.select("dep_table", F.col("dep_col").alias("dep_cols"), "ref_table", F.col("ref_col").alias("ref_cols"), "dep_distinct", "missing", "error")


def validate_declared(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog, out = W.core(spark, sf_dir), None
    for d, dc, r, rc in W.DECLARED:
        one = derived.validate(catalog.tables[d], list(dc), catalog.tables[r], list(rc))
        one = one.select(F.lit(d).alias("dep_table"), F.lit(",".join(dc)).alias("dep_cols"), F.lit(r).alias("ref_table"), F.lit(",".join(rc)).alias("ref_cols"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog = W.core(spark, sf_dir)
    return derived.violations(catalog.tables["orders"], ["o_orderkey"], catalog.tables["lineitem"], ["l_orderkey"])


def fk_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog = W.core(spark, sf_dir)
    return derived.fk_candidates(written(unary_pairs(catalog), "pairs"), written(attr_values.attr_stats(catalog), "stats"), catalog)


def ind_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog = W.everything(spark, sf_dir)
    return names(derived.classes(written(unary_pairs(catalog), "pairs"), len(catalog.attributes)), catalog)


def ind_reduced(spark: SparkSession, sf_dir: str) -> DataFrame:
    catalog = W.everything(spark, sf_dir)
    return flat_pairs(derived.reduce_pairs(written(unary_pairs(catalog), "pairs"), len(catalog.attributes)), catalog)


def ind_totals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return totals(discover(W.core(spark, sf_dir)))


def join_suggestion(spark: SparkSession, sf_dir: str) -> DataFrame:
    joined = derived.join_on(W.core(spark, sf_dir), "orders", ["o_custkey"], "customer", ["c_custkey"])
    return joined.groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("o_orderkey").alias("orders"))


def events_incremental_inds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events arrive in four batches, the last ones first; the state answers as the whole table would."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    catalog = Catalog({"customer": spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey"), "events": events})
    state = IncrementalInds(catalog, ("customer",))
    for k in (3, 1, 0, 2):
        state.add("events", events.filter(F.pmod(F.xxhash64("event_id"), F.lit(4)) == k), k)
    return flat_pairs(state.inds(), catalog)


def queries() -> dict[str, Query]:
    unary: dict[str, dict] = {
        "exact_unary_core": {},
        "exact_unary_all": {"data": "all"},
        "exact_unary_typed": {"typed": True},
        "exact_unary_maxpruned": {"prune_max": True},
        "exact_unary_merge_engine": {"method": "merge"},
        "inverted_unary": {"method": "inverted"},
        "pairwise_unary": {"method": "pairwise", "prune_max": True},
        "exact_nary_core": {"max_arity": None},
        "exact_nary_high_arity": {"data": "high_arity", "max_arity": None},
        "exact_nary_sparse": {"data": "sparse", "max_arity": None},
        "sketch_unary_default": {"method": "sketch"},
        "sketch_unary_verified": {"method": "sketch", "lgk": 8, "verify": True},
        "sketch_unary_sets": {"method": "sketch", "members": "set"},
        "sketch_unary_hll_only": {"method": "sketch", "sample_n": 0},
        "sketch_unary_index_only": {"method": "sketch", "sample_n": None, "lgk": 4},
        "sketch_nary_high_arity": {"data": "high_arity", "method": "sketch", "max_arity": None},
        "wide_unary": {"data": "wide"},
        "wide_unary_259": {"data": "wide_all"},
        "exact_unary_merge_baseline": {"method": "merge", "kind": "column_scan"},
        "exact_unary_merge_set_single": {"method": "merge", "kind": "set_single"},
        "exact_unary_merge_auto": {"method": "merge", "kind": "auto"},
        "prose_unary": {"data": "prose"},
    }
    plain = (
        inverted_index_sets, pairwise_joined_unary, attr_stats, dataset_profile, lattice_candidates_2, merge_counters, sketch_registers_md5, sketch_sample_md5,
        sketch_index_keys_md5, combined_hash_md5, sketch_estimates, worked_example, partial_inds, validate_declared, violations, fk_candidates, ind_classes,
        ind_reduced, ind_totals, join_suggestion, events_incremental_inds,
    )
    return (
        {k: partial(found, **v) for k, v in unary.items()}
        | {f"dedupe_{k}": partial(deduped, kind=k) for k in dedupe.KINDS}
        | {f"fill_{k}": partial(filled_counts, engine=k) for k in ("row", "htab", "batch", "vector", "sql")}
        | {"fill_sets": partial(filled_members, members="set"), "fill_bits": partial(filled_members, members="bits"), "sketch_sweep_accuracy": W.accuracy_sweep, "level_counts": W.level_counts, "explosion_guard": W.explosion_guard, "index_lookups": W.index_lookups}
        | {f.__name__: f for f in plain}
    )
