"""Sizes from data: duplicate profiles, predicted entries, samples, and the choice of shape."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import SketchSpec
from ..functions.hashing import h60

#: Load factors that chained sketches of d = 3 reach before the first failure, by entries per bucket.
LOADS = {4: 0.75, 6: 0.87, 8: 0.92}


def cap(spec: SketchSpec) -> float:
    """Most entries that one key can use."""
    if spec.variant in ("keyonly", "bloomattr"):
        return 1
    if spec.variant == "hybrid":
        return spec.d
    if spec.variant == "chained":
        return math.inf if spec.l_max is None else spec.d * spec.l_max
    return math.inf


def per_key(df: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """(key, dupes): distinct attribute vectors of each key."""
    return df.filter(F.col(key).isNotNull()).select(key, *columns).distinct().groupBy(key).agg(F.count("*").alias("dupes"))


def profile(df: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """Keys, vectors, and their average and largest number for a key."""
    return per_key(df, key, columns).agg(F.count("*").alias("n_keys"), F.sum("dupes").alias("vectors"), F.round(F.avg("dupes"), 6).alias("avg_dupes"), F.max("dupes").alias("max_dupes"))


def predict_entries(df: DataFrame, key: str, columns: list[str], most: float) -> DataFrame:
    used = F.col("dupes") if math.isinf(most) else F.least("dupes", F.lit(int(most)))
    return per_key(df, key, columns).agg(F.sum(used).cast("bigint").alias("entries"))


def predict_bottomk(df: DataFrame, key: str, columns: list[str], most: float, k: int, family: str = "xx") -> DataFrame:
    """Predicted entries from all rows of the k keys with the least hashes; the number of keys is counted exactly."""
    keys = df.select(key).filter(F.col(key).isNotNull()).distinct()
    some = keys.orderBy(h60(key, "sample", 0, family), key).limit(k)
    used = F.col("dupes") if math.isinf(most) else F.least("dupes", F.lit(int(most)))
    mean = per_key(df.join(some, key, "left_semi"), key, columns).agg(F.avg(used).alias("mean"))
    return mean.crossJoin(keys.agg(F.count("*").alias("n_keys"))).select(F.round(F.col("mean") * F.col("n_keys"), 3).alias("entries"))


def predict_twolevel(df: DataFrame, key: str, columns: list[str], most: float, share: float, per: int, family: str = "xx") -> DataFrame:
    """Predicted entries from keys below a hash threshold, each with at most `per` of its vectors looked at."""
    limit = int(share * (1 << 60))
    some = df.filter(h60(key, "sample", 0, family) < limit)
    used = F.least("dupes", F.lit(int(min(most, per))))
    return per_key(some, key, columns).agg(F.round(F.sum(used) / share, 3).alias("entries"))


def choose(entries: int, spec: SketchSpec, loads: dict[int, float] = LOADS) -> SketchSpec:
    """The least shape whose load stays below what buckets of that size reached: sizes m*b in ascending order."""
    found = []
    for b, load in loads.items():
        m = 2
        while entries / (m * b) > load:
            m *= 2
        found.append((m * b, b, m))
    _, b, m = min(found)
    return spec.with_(m=m, b=b)


#: Entries of one shard: beyond, keys are dealt to several sketches of one shape, each with prints and chains of its own.
SHARD = 1 << 24


def shape(per: DataFrame, spec: SketchSpec, shard: int | None = SHARD) -> SketchSpec:
    """The spec in the least shape for the entries that the duplicates of keys (key, dupes) predict.

    A plain sketch has to hold all vectors of the largest key in two buckets, whatever their load. Large sketches
    are cut into shards, so that builds and closures are dealt by shard and print to as many tasks as the data need;
    `shard` None makes one sketch of any size.
    """
    return shape_of(histogram(per), spec, shard)


def histogram(per: DataFrame) -> dict[int, int]:
    """How many keys have so many duplicates: of N vectors, fewer than the root of 2 N different numbers."""
    return dict(map(tuple, per.groupBy("dupes").agg(F.count("*")).collect()))


def predicted(counts: dict[int, int], spec: SketchSpec) -> int:
    """Entries that keys use, from how many keys have so many duplicates."""
    return sum(int(min(dupes, cap(spec))) * keys for dupes, keys in counts.items())


def shape_of(counts: dict[int, int], spec: SketchSpec, shard: int | None = SHARD) -> SketchSpec:
    """`shape` from the histogram of duplicates, which serves any number of specs."""
    entries, largest = predicted(counts, spec), max(counts, default=0)
    if not entries:
        return spec.with_(m=2)
    shards = 1 if shard is None else -(-entries // shard)
    entries, spec = -(-entries // shards), spec.with_(shards=shards)
    if spec.variant == "plain":
        return choose(entries, spec, {max(min(LOADS), -(-largest // 2)): max(LOADS.values())})
    return choose(entries, spec)


def defaults(spec: SketchSpec) -> SketchSpec:
    """The rule of thumb: buckets of twice as many slots as a pair may hold copies of one print."""
    return spec.with_(b=2 * spec.d)
