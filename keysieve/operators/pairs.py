"""Sketch builders as relational plans.

A probe sees both buckets of a pair and only the entries with its print, so a sketch is the set of
(shard, pair_id, kappa, payload): which of the two buckets an entry lies in never changes an answer.
A chain keeps its print, so one exchange by (shard, kappa) serves all rounds of a chained build.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import SketchSpec
from ..functions import attrs as A
from ..functions.hashing import chain_pairs, locate, onward
from ..sources.folders import shared_root
from . import chains, places

GROUP = ["shard", "pair_id", "kappa"]


@dataclass
class Sketch:
    """Entries and how they were made; `discarded` counts vectors that found no place, `failed` marks groups that no bucket pair can hold."""

    spec: SketchSpec
    entries: DataFrame
    discarded: DataFrame | None = None
    failed: DataFrame | None = None


def prints(spec: SketchSpec) -> list[str]:
    return [f"a_{i}" for i in range(len(spec.attrs))]


def located(df: DataFrame, key: str, spec: SketchSpec) -> DataFrame:
    return locate(df, key, spec)


def build_keyonly(df: DataFrame, key: str, spec: SketchSpec) -> Sketch:
    return Sketch(spec, locate(df.select(key), key, spec).select(*GROUP).distinct())


def build_counting(df: DataFrame, key: str, spec: SketchSpec) -> Sketch:
    """A counter for each print instead of copies."""
    return Sketch(spec, locate(df.select(key), key, spec).groupBy(*GROUP).agg(F.count("*").alias("n")))


def delete_keys(counting: Sketch, keys: DataFrame, key: str) -> Sketch:
    """Takes one copy away for each row of keys; prints without copies go. Only for keys that were inserted."""
    away = locate(keys.select(key), key, counting.spec).groupBy(*GROUP).agg(F.count("*").alias("gone"))
    left = counting.entries.join(away, GROUP, "left").withColumn("n", F.col("n") - F.coalesce("gone", F.lit(0)))
    return Sketch(counting.spec, left.filter("n > 0").select(*GROUP, "n"))


def vectors(df: DataFrame, key: str, spec: SketchSpec) -> DataFrame:
    """Distinct (group, prints) of all rows."""
    own = df.select(key, *dict.fromkeys(a.name for a in spec.attrs if a.name != key))
    if places.suits(own, spec):
        return places.placed(own, key, spec, "prints").distinct()
    return locate(own, key, spec).select(*GROUP, *(c.alias(n) for n, c in A.vector(own, spec).items())).distinct()


def build_plain(df: DataFrame, key: str, spec: SketchSpec) -> Sketch:
    """Vectors as they come; a pair holds at most 2b of one print, so a group beyond fails."""
    entries = vectors(df, key, spec)
    failed = entries.groupBy(*GROUP).agg(F.count("*").alias("n")).filter(F.col("n") > 2 * spec.b)
    return Sketch(spec, entries, failed=failed)


def _home(spec: SketchSpec) -> list[str]:
    """What entries are dealt by: a chain keeps its shard and print. A constant shard would hide the match from the planner."""
    return ["kappa"] if spec.shards == 1 else ["shard", "kappa"]


def _least(rows: DataFrame, n: int, order: list[str]) -> DataFrame:
    """The first n rows of each group; tasks leave out the others before anything is exchanged, so no group meets as a whole."""
    return rows.withColumn("nth", F.row_number().over(Window.partitionBy(*GROUP).orderBy(*order))).filter(F.col("nth") <= n).drop("nth")


def _rounds(rows: DataFrame, spec: SketchSpec) -> DataFrame:
    """Rows (GROUP, prints, late) after all hops: late = 0 for entries, 1 for what found no place.

    A pair keeps at most d vectors of a print: those that are there, then the least arrivals; others go to the next pair.
    """
    a = prints(spec)
    if chains.suits(spec):
        return _rounds_by_print(rows, spec)
    rows = rows.repartition(*_home(spec)).withColumn("chain", chain_pairs(F.col("pair_id"), F.col("kappa"), spec, spec.l_max))
    same = Window.partitionBy(*GROUP, *a)
    order = Window.partitionBy(*GROUP).orderBy("late", *a)
    for hop in range(spec.l_max):
        # an entry that is there takes in equal arrivals; entries come first, so they never move
        rows = rows.withColumn("late", F.min("late").over(same)).withColumn("rank", F.dense_rank().over(order))
        stays = F.col("rank") <= spec.d
        further = F.element_at("chain", hop + 2) if hop + 1 < spec.l_max else F.col("pair_id")
        rows = rows.withColumns({"pair_id": F.when(stays, F.col("pair_id")).otherwise(further), "late": F.when(stays, 0).otherwise(1)}).drop("rank")
    return rows


def _rounds_by_print(rows: DataFrame, spec: SketchSpec) -> DataFrame:
    """The same with all rounds of whole prints in one call: sorted arrays, and one hash for each pair that something leaves."""
    import numpy as np

    a = prints(spec)
    schema = ["shard int", "pair_id bigint", "kappa int", *(f"{c} int" for c in a), "late int"]

    def run(batches):
        for table in chains.by_prints(batches):
            shards, kappas, slot, held, late = _settled(table, spec)
            out = [shards[slot // spec.m], slot % spec.m, kappas[slot // spec.m], *(h.astype(np.int32) for h in held), late.astype(np.int32)]
            yield from pa.table([pa.array(x) for x in out], names=["shard", "pair_id", "kappa", *a, "late"]).to_batches(chains.ROWS)

    return _by_print(rows.select("shard", "pair_id", "kappa", *a, "late"), spec).mapInArrow(run, ", ".join(schema))


def _settled(table: pa.Table, spec: SketchSpec):
    """(shards, prints, slots, vectors, late) of whole prints after all hops; shards and prints by the slots' homes."""
    import numpy as np

    a = prints(spec)
    home, shards, kappas = chains.homes(table)
    vecs = [table[c].to_numpy().astype(np.int64) for c in a]
    names = None
    if len(a) < 3:  # prints have 30 bits at most, so two of them are one number in the same order
        code = (vecs[0] << 31) + vecs[1] + 1 if len(a) == 2 else vecs[0] if a else np.zeros(len(table), np.int64)
    else:
        names, code = np.unique(np.stack(vecs, axis=1), axis=0, return_inverse=True)
    late = table["late"].to_numpy().astype(np.int64) if "late" in table.column_names else np.ones(len(table), np.int64)
    slot, code, late = chains.settled(home * spec.m + table["pair_id"].to_numpy(), code.reshape(-1), late, kappas.astype(np.int64), spec)
    held = [names[code, i] for i in range(len(a))] if names is not None else [code >> 31, (code & ((1 << 31) - 1)) - 1] if len(a) == 2 else [code][: len(a)]
    return shards, kappas, slot, held, late


def by_arrays(df: DataFrame, spec: SketchSpec) -> bool:
    """Whether a chained sketch of df can be built by print in arrays."""
    return chains.suits(spec) and places.suits(df, spec)


def arrivals(df: DataFrame, key: str, spec: SketchSpec) -> DataFrame:
    """(GROUP, prints) of rows, with copies; of a group, tasks send only the least that can find a place."""
    own = df.select(key, *dict.fromkeys(a.name for a in spec.attrs if a.name != key))
    return places.placed(own, key, spec, "prints", most=spec.d * spec.l_max)


def chained_masks(df: DataFrame, key: str, spec: SketchSpec, found: list[tuple[dict, tuple]], always: tuple[int, int]) -> DataFrame:
    """(GROUP, l0, l1) of the chained sketch of df, built and closed in one pass by print.

    `found`: masks of vectors, by their prints in some places; a saturated chain has the masks `always`.
    """
    import numpy as np

    tables = chains.coded(found)

    def run(batches):
        for table in chains.by_prints(batches):
            shards, kappas, slot, held, late = _settled(table, spec)
            slot, held = slot[late == 0], [h[late == 0] for h in held]
            slot, out = chains.closed(slot, chains.met(held, len(slot), tables), always, kappas.astype(np.int64), spec)
            some = (out[0] | out[1]) != 0
            slot, out = slot[some], [o[some] for o in out]
            columns = [shards[slot // spec.m], slot % spec.m, kappas[slot // spec.m], *out]
            yield from pa.table([pa.array(x) for x in columns], names=[*GROUP, "l0", "l1"]).to_batches(chains.ROWS)

    return _by_print(arrivals(df, key, spec), spec).mapInArrow(run, "shard int, pair_id bigint, kappa int, l0 bigint, l1 bigint")


def _by_print(rows: DataFrame, spec: SketchSpec) -> DataFrame:
    """Rows dealt by shard and print, in turn."""
    return rows.repartition(*_home(spec)).sortWithinPartitions("shard", "kappa")


def walked(groups: DataFrame, spec: SketchSpec, masks: list[str]) -> DataFrame:
    """(GROUP, masks, saturated) of groups (GROUP, masks, full): each mask joined with those along the group's chain."""
    import numpy as np

    def run(batches):
        for table in chains.by_prints(batches):
            home, shards, kappas = chains.homes(table)
            slot, out, saturated = chains.walked(home * spec.m + table["pair_id"].to_numpy(), table["full"].to_numpy(), [table[c].to_numpy() for c in masks], kappas.astype(np.int64), spec)
            columns = [shards[slot // spec.m], slot % spec.m, kappas[slot // spec.m], *out, saturated]
            yield from pa.table([pa.array(x) for x in columns], names=[*GROUP, *masks, "saturated"]).to_batches(chains.ROWS)

    schema = "shard int, pair_id bigint, kappa int, " + "".join(f"{c} bigint, " for c in masks) + "saturated boolean"
    return _by_print(groups.select(*GROUP, *masks, "full"), spec).mapInArrow(run, schema)


def build_chained(df: DataFrame, key: str, spec: SketchSpec) -> Sketch:
    """At most d vectors of a print in a pair; what is over goes on to the next pair of the chain, up to l_max pairs.

    Of one group only the least d * l_max vectors can find a place, so the others never travel.
    """
    if spec.l_max is None:
        return _build_uncapped(df, key, spec)
    a, most = prints(spec), spec.d * spec.l_max
    every = vectors(df, key, spec)
    few = arrivals(df, key, spec) if by_arrays(df, spec) else _least(every, most, a)
    rows = _rounds(few.withColumn("late", F.lit(1)), spec)
    entries = rows.filter("late = 0").select(*GROUP, *a).distinct()
    # what is over: vectors that the finished sketch holds nowhere on their chains, at its last pair
    beyond = every.withColumn("nth", F.row_number().over(Window.partitionBy(*GROUP).orderBy(*a))).filter(F.col("nth") > most)
    chain = beyond.withColumn("chain", chain_pairs(F.col("pair_id"), F.col("kappa"), spec, spec.l_max)).withColumn("last", F.element_at("chain", -1))
    # each chain for itself, as two chains may end at one pair and only one of them hold the vector
    there = chain.select("shard", "kappa", *a, F.col("pair_id").alias("first"), "last", F.explode("chain").alias("pair_id")).join(entries.withColumn("held", F.lit(1)), [*GROUP, *a], "left")
    lost = there.groupBy("shard", "kappa", *a, "first", "last").agg(F.max("held").alias("held")).filter("held is null").select("shard", F.col("last").alias("pair_id"), "kappa", *a)
    return Sketch(spec, entries, discarded=rows.filter("late = 1").select(*GROUP, *a).unionByName(lost).distinct())


def _build_uncapped(df: DataFrame, key: str, spec: SketchSpec) -> Sketch:
    """Rounds until nothing moves; lineage is cut after each, as their number follows the largest group.

    A chain goes on to a pair that it has not seen, by the next attempt where needed; a vector whose chain has
    no such pair is discarded, and its chain saturated.
    """
    a = prints(spec)
    start = vectors(df, key, spec).repartition(*_home(spec)).withColumns({"late": F.lit(1), "seen": F.array("pair_id")})
    rows, ended = kept(start), None
    same, order = Window.partitionBy(*GROUP, *a), Window.partitionBy(*GROUP).orderBy("late", *a)
    while rows.filter("late = 1").limit(1).count():
        rows = rows.withColumn("late", F.min("late").over(same)).withColumn("rank", F.dense_rank().over(order))
        rows = rows.withColumn("stays", F.col("rank") <= spec.d).withColumn("next", F.when(~F.col("stays"), onward(F.col("seen"), F.col("kappa"), spec)))
        rows = kept(rows.drop("rank"))
        over = rows.filter("not stays and next is null").select(*GROUP, *a)
        ended = over if ended is None else ended.unionByName(over)
        moved = F.when(F.col("stays"), F.col("pair_id")).otherwise(F.col("next"))
        seen = F.when(F.col("stays"), F.col("seen")).otherwise(F.concat("seen", F.array("next")))
        rows = rows.filter("stays or next is not null").select("shard", "kappa", *a, moved.alias("pair_id"), seen.alias("seen"), F.when(F.col("stays"), 0).otherwise(1).alias("late")).distinct()
    return Sketch(spec, rows.select(*GROUP, *a).distinct(), discarded=(rows.filter("false").select(*GROUP, *a) if ended is None else ended).distinct())


def kept(df: DataFrame) -> DataFrame:
    """df from a checkpoint in the shared folder, so that executors may be lost."""
    sc = df.sparkSession.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(shared_root(df.sparkSession))
    return df.checkpoint(eager=True)


def build_bloomattr(df: DataFrame, key: str, spec: SketchSpec) -> Sketch:
    own = df.select(key, *dict.fromkeys(a.name for a in spec.attrs if a.name != key))
    masked = places.placed(own, key, spec, "mask") if places.suits(own, spec) else locate(own, key, spec).select(*GROUP, A.row_mask(own, spec).alias("mask"))
    return Sketch(spec, masked.groupBy(*GROUP).agg(F.bit_or("mask").alias("mask")))


def hybrid_bits(spec: SketchSpec) -> int:
    """Bits of the mask in d entries: what prints and counts of the two buckets leave, and each entry's flag takes one."""
    entry = spec.key_bits + spec.vector_bits + 1
    return max(1, min(63, spec.d * entry - 2 * (spec.key_bits + math.ceil(math.log2(max(2, spec.d)))) - spec.d))


def hybrid_hashes(spec: SketchSpec) -> int:
    """The best number of hashes for d + 1 vectors in the mask, at least 1."""
    return max(1, round(hybrid_bits(spec) / ((spec.d + 1) * max(1, len(spec.attrs))) * math.log(2)))


def print_mask(spec: SketchSpec):
    """The mask over (place, print) items of one vector."""
    out, bits, hashes = F.lit(0).cast("bigint"), hybrid_bits(spec), hybrid_hashes(spec)
    for i, c in enumerate(prints(spec)):
        if spec.hash_family == "portable" and spec.attr_bits <= 8:  # few prints: their masks are worked out beforehand
            masks = places.mask(pa.array(range(1 << spec.attr_bits), pa.int64()), i, spec, bits, hashes).tolist()
            own = F.get(F.array(*(F.lit(x).cast("bigint") for x in masks)), F.col(c))
        else:
            own = A.item_mask(F.col(c), i, spec, bits, hashes)
        out = out.bitwiseOR(F.when(F.col(c) == A.NULL_PRINT, F.lit(0).cast("bigint")).otherwise(own))
    return out


def _hybrid(rows: DataFrame, spec: SketchSpec, masks: DataFrame | None = None) -> DataFrame:
    """Entries of distinct vectors, with masks (GROUP, mask) of groups that were converted before."""
    a = prints(spec)
    empty = F.expr(f"cast(array() as array<struct<{', '.join(f'{c}:int' for c in a)}>>)")
    sums = rows.select(*GROUP, print_mask(spec).alias("mask"), F.lit(0).alias("was"))
    if masks is not None:
        sums = sums.unionByName(masks.select(*GROUP, "mask", F.lit(1).alias("was")))
    sums = sums.groupBy(*GROUP).agg(F.bit_or("mask").alias("mask"), F.max("was").alias("was"))  # combined before the exchange
    few = _least(rows, spec.d + 1, a).groupBy(*GROUP).agg(F.array_sort(F.collect_list(F.struct(*a))).alias("vectors"))
    over = (F.col("was") == 1) | (F.coalesce(F.size("vectors"), F.lit(0)) > spec.d)
    return sums.join(few, GROUP, "left").select(*GROUP, over.alias("is_bloom"), F.when(over, empty).otherwise(F.col("vectors")).alias("vectors"), F.when(over, F.col("mask")).otherwise(F.lit(0).cast("bigint")).alias("mask"))


def build_hybrid(df: DataFrame, key: str, spec: SketchSpec) -> Sketch:
    """Up to d vectors as they are; beyond, one mask over (place, print) items of all vectors."""
    return Sketch(spec, _hybrid(vectors(df, key, spec), spec))


BUILDERS = {"keyonly": build_keyonly, "plain": build_plain, "chained": build_chained, "bloomattr": build_bloomattr, "hybrid": build_hybrid}


def build(df: DataFrame, key: str, spec: SketchSpec) -> Sketch:
    return BUILDERS[spec.variant](df, key, spec)


def merge(one: Sketch, two: Sketch) -> Sketch:
    """The sketch of both inputs, from entries alone.

    For all but chained sketches it equals the sketch built of both inputs. Chained entries go through the rounds
    anew from the pairs where they are: pairs that were full stay full, so every probe finds what it found before.
    """
    if one.spec != two.spec:
        raise ValueError("sketches of different specs cannot be merged")
    spec, both = one.spec, one.entries.unionByName(two.entries)
    if spec.variant == "bloomattr":
        return Sketch(spec, both.groupBy(*GROUP).agg(F.bit_or("mask").alias("mask")))
    if spec.variant in ("keyonly", "plain"):
        return Sketch(spec, both.distinct())
    if spec.variant == "hybrid":
        single = both.filter("not is_bloom").select(*GROUP, F.explode("vectors").alias("v")).select(*GROUP, "v.*").distinct()
        return Sketch(spec, _hybrid(single, spec, both.filter("is_bloom")))
    return rebuild_chained(both, spec)


def rebuild_chained(entries: DataFrame, spec: SketchSpec) -> Sketch:
    """Chained entries of several sketches as one sketch of the same shape."""
    if spec.l_max is None or spec.cycle_break:
        raise ValueError("chains that depend on where they began are built from their inputs")
    a = prints(spec)
    rows = _rounds(entries.select(*GROUP, *a).distinct().withColumn("late", F.lit(1)), spec)
    return Sketch(spec, rows.filter("late = 0").select(*GROUP, *a).distinct(), discarded=rows.filter("late = 1").select(*GROUP, *a).distinct())


def grown(df: DataFrame, key: str, spec: SketchSpec, loads: dict[int, float], most: int = 24) -> Sketch:
    """The sketch, rebuilt from its input in more or larger buckets until all its entries have a place.

    Buckets are doubled until the entries stay below the load that buckets of that size reached. A group that two
    buckets cannot hold needs larger ones, which only plain sketches can come to.
    """
    for _ in range(most):
        sketch = build(df, key, spec)
        sketch.entries = kept(sketch.entries)
        largest = None if sketch.failed is None else sketch.failed.agg(F.max("n")).first()[0]
        load = loads[max(b for b in loads if b <= max(spec.b, min(loads)))]
        if largest is not None:
            spec = spec.with_(b=-(-largest // 2))
        elif sketch.entries.count() > load * spec.m * spec.b * spec.shards:
            spec = spec.with_(m=spec.m * 2)
        else:
            return sketch
    raise ValueError("no size was enough")
