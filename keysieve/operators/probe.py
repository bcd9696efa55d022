"""Probes: by key, by key and predicate, and by predicate alone.

A chained sketch is closed once on its own side: every group gets the payloads of the whole chain that starts
there. Binding a predicate then leaves a small set of live groups, and probing is one semi join on
(shard, pair_id, kappa), which Spark broadcasts when its measured size allows and shuffles otherwise.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Predicate
from ..functions import attrs as A
from ..functions.hashing import chain_pairs, locate
from . import chains
from .pairs import GROUP, Sketch, hybrid_bits, hybrid_hashes, prints, walked


def groups(sketch: Sketch) -> DataFrame:
    """(group, payloads, full) of vector entries."""
    packed = sketch.entries.groupBy(*GROUP).agg(F.array_sort(F.collect_list(F.struct(*prints(sketch.spec)))).alias("payloads"))
    return packed.withColumn("full", F.size("payloads") >= sketch.spec.d)


def close(sketch: Sketch, length: int | None = None) -> DataFrame:
    """(group, payloads, saturated): what a probe that starts at a group sees; saturated chains answer true to everything."""
    spec = sketch.spec
    length = length or spec.l_max
    own = groups(sketch)
    if length is None:
        raise ValueError("an unbounded chain is closed to a given length")
    state = own.withColumns({"chain": F.when(F.col("full"), chain_pairs(F.col("pair_id"), F.col("kappa"), spec, length)), "open": F.col("full")})
    for hop in range(1, length):
        nxt = own.select(F.col("shard").alias("s_"), F.col("pair_id").alias("p_"), F.col("kappa").alias("k_"), F.col("payloads").alias("more"), F.col("full").alias("full_"))
        at = F.when(F.col("open"), F.element_at("chain", hop + 1))
        state = state.withColumn("at", at).join(nxt, (F.col("shard") == F.col("s_")) & (F.col("kappa") == F.col("k_")) & (F.col("at") == F.col("p_")), "left")
        state = state.withColumns({"payloads": F.when(F.col("more").isNotNull(), F.concat("payloads", "more")).otherwise(F.col("payloads")), "open": F.col("open") & F.coalesce("full_", F.lit(False))})
        state = state.drop("s_", "p_", "k_", "more", "full_", "at")
    return state.select(*GROUP, "payloads", F.col("open").alias("saturated"))


def flat(closed: DataFrame, spec) -> DataFrame:
    """A closure with a row for each vector, saturated groups once: in this form it is stored, and predicates reach its files."""
    rows = closed.filter("not saturated").select(*GROUP, "saturated", F.explode("payloads").alias("p")).select(*GROUP, "saturated", "p.*").distinct()
    none = [F.lit(A.NULL_PRINT).alias(c) for c in prints(spec)]
    return rows.unionByName(closed.filter("saturated").select(*GROUP, "saturated", *none)).sortWithinPartitions(*prints(spec))


def derive_key_filter(sketch: Sketch, pred: Predicate, closure: DataFrame | None = None) -> DataFrame:
    """The groups that may hold a matching row: a key filter for anyone downstream."""
    spec, e = sketch.spec, sketch.entries
    if spec.variant == "keyonly" or not (pred.allowed or pred.options):
        return first_groups(sketch)
    if spec.variant == "bloomattr":
        return e.filter(A.match_mask(F.col("mask"), pred, spec)).select(*GROUP)
    if spec.variant == "plain":
        return e.filter(A.match_vector([F.col(c) for c in prints(spec)], pred, spec)).select(*GROUP).distinct()
    any_vector = lambda column: F.exists(column, lambda v: A.match_vector([v[c] for c in prints(spec)], pred, spec))
    if spec.variant == "hybrid":
        by_mask = A.match_mask(F.col("mask"), pred, spec, hybrid_bits(spec), hybrid_hashes(spec), of_prints=True)
        return e.filter(F.when(F.col("is_bloom"), by_mask).otherwise(any_vector("vectors"))).select(*GROUP)
    if closure is None and chains.suits(spec):  # a predicate that is known beforehand needs no payloads along chains
        hit = F.max(A.match_vector([F.col(c) for c in prints(spec)], pred, spec).cast("bigint")).alias("hit")
        own = e.groupBy(*GROUP).agg(hit, (F.count("*") >= spec.d).alias("full"))
        return walked(own, spec, ["hit"]).filter("saturated or hit <> 0").select(*GROUP)
    closed = close(sketch) if closure is None else closure
    if "payloads" not in closed.columns:
        return closed.filter(F.col("saturated") | A.match_vector([F.col(c) for c in prints(spec)], pred, spec)).select(*GROUP)
    return closed.filter(F.col("saturated") | any_vector("payloads")).select(*GROUP)


def derive_marked(sketch: Sketch, pred: Predicate) -> DataFrame:
    """Chained entries with a mark for matching ones: prints stay, so that chains keep their length."""
    return sketch.entries.withColumn("live", A.match_vector([F.col(c) for c in prints(sketch.spec)], pred, sketch.spec))


def probe_marked(marked: DataFrame, sketch: Sketch) -> DataFrame:
    """Live groups from marked entries: the same as binding the predicate on the closure."""
    spec = sketch.spec
    own = marked.groupBy(*GROUP).agg(F.max("live").alias("hit"), (F.count("*") >= spec.d).alias("full"))
    state = own.withColumns({"chain": chain_pairs(F.col("pair_id"), F.col("kappa"), spec, spec.l_max), "open": F.col("full")})
    for hop in range(1, spec.l_max):
        nxt = own.select(F.col("shard").alias("s_"), F.col("pair_id").alias("p_"), F.col("kappa").alias("k_"), F.col("hit").alias("hit_"), F.col("full").alias("full_"))
        state = state.withColumn("at", F.when(F.col("open"), F.element_at("chain", hop + 1))).join(nxt, (F.col("shard") == F.col("s_")) & (F.col("kappa") == F.col("k_")) & (F.col("at") == F.col("p_")), "left")
        state = state.withColumns({"hit": F.col("hit") | F.coalesce("hit_", F.lit(False)), "open": F.col("open") & F.coalesce("full_", F.lit(False))}).drop("s_", "p_", "k_", "hit_", "full_", "at")
    return state.filter("hit or open").select(*GROUP)


def first_groups(sketch: Sketch) -> DataFrame:
    """Groups with any entry: all that a key-only probe looks at, also in chains."""
    return sketch.entries.select(*GROUP).distinct()


def semi(df: DataFrame, key: str, live: DataFrame, spec) -> DataFrame:
    """Rows of df whose key's group is live; df keeps its columns."""
    names = [f"__{c}" for c in GROUP]
    there = locate(df.withColumn("__key", F.col(key)), "__key", spec).withColumnsRenamed(dict(zip(GROUP, names, strict=True)))
    # at most one row for each group of a sketch: Spark measures the size and broadcasts or shuffles by it
    own = live.select(*(F.col(c).alias(f"__l{c}") for c in GROUP))
    on = [F.col(n) == F.col(f"__l{c}") for n, c in zip(names, GROUP, strict=True)]
    return there.join(own, on, "left_semi").drop("__key", *names)


def contains_key(df: DataFrame, key: str, sketch: Sketch) -> DataFrame:
    return semi(df, key, first_groups(sketch), sketch.spec)


def contains(df: DataFrame, key: str, pred: Predicate, sketch: Sketch, closure: DataFrame | None = None) -> DataFrame:
    return semi(df, key, derive_key_filter(sketch, pred, closure), sketch.spec)
