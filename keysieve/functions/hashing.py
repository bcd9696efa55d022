"""Hash roles and bucket places as column expressions.

Two families: `xx` stays inside code generation; `portable` is the first 15 hexadecimal digits of an MD5, which
any engine can compute. Both give non-negative integers below 2**60, and each role has its own salted input.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..config import SketchSpec


def text(col: Column | str) -> Column:
    """The canonical text of a key or value; doubles lose the sign of zero."""
    col = F.col(col) if isinstance(col, str) else col
    return col.cast("string")


def h60(col: Column | str, role: str, salt: int = 0, family: str = "xx") -> Column:
    named = F.concat(F.lit(f"{role}:{salt}:"), text(col))
    if family == "portable":
        return F.conv(F.substring(F.md5(named), 1, 15), 16, 10).cast("bigint")
    return F.shiftrightunsigned(F.xxhash64(named), 4)


def low(h: Column, bits: int) -> Column:
    return h.bitwiseAND(F.lit((1 << bits) - 1).cast("bigint"))


def print_of(key: Column | str, spec: SketchSpec) -> Column:
    return low(h60(key, "key", spec.salt, spec.hash_family), spec.key_bits).cast("int")


def first_bucket(key: Column | str, spec: SketchSpec) -> Column:
    return F.pmod(h60(key, "bucket", spec.salt, spec.hash_family), F.lit(spec.m))


def offset(kappa: Column | str, spec: SketchSpec) -> Column:
    """The distance (by XOR) of a print's two buckets; never zero, so they differ."""
    if spec.m == 2:
        return F.lit(1).cast("bigint")
    return F.lit(1) + F.pmod(h60(kappa, "pair", spec.salt, spec.hash_family), F.lit(spec.m - 1))


def pair_of(bucket: Column, kappa: Column | str, spec: SketchSpec) -> Column:
    return F.least(bucket, bucket.bitwiseXOR(offset(kappa, spec)))


def shard_of(key: Column | str, spec: SketchSpec) -> Column:
    return F.pmod(h60(key, "shard", spec.salt, spec.hash_family), F.lit(spec.shards)).cast("int") if spec.shards > 1 else F.lit(0)


def _next(pair: Column, kappa: Column, spec: SketchSpec, attempts: Column) -> Column:
    """Candidates for the pair after one in a print's chain, as an array over attempts."""
    plain = F.concat_ws(":", pair.cast("string"), kappa.cast("string"))
    name = lambda t: F.when(t == 0, plain).otherwise(F.concat_ws(":", plain, t.cast("string")))
    buckets = F.transform(attempts, lambda t: F.pmod(h60(name(t), "chain", spec.salt, spec.hash_family), F.lit(spec.m)))
    return F.transform(buckets, lambda b: pair_of(b, kappa, spec))


def next_pair(pair: Column, kappa: Column, spec: SketchSpec) -> Column:
    return F.element_at(_next(pair, kappa, spec, F.array(F.lit(0))), 1)


def onward(seen: Column, kappa: Column, spec: SketchSpec, attempts: int = 4) -> Column:
    """The pair after those of a chain so far: the first attempt's that it has not seen, null if there is none."""
    found = _next(F.element_at(seen, -1), kappa, spec, F.sequence(F.lit(0), F.lit(attempts - 1)))
    return F.get(F.filter(found, lambda p: ~F.array_contains(seen, p)), F.lit(0))


def chain_pairs(pair: Column, kappa: Column, spec: SketchSpec, length: int, attempts: int = 4) -> Column:
    """The first pairs of a chain as an array; with cycle breaking a pair seen before is replaced by the next attempt's."""
    if length < 2:
        return F.array(pair)
    tries = F.sequence(F.lit(0), F.lit(attempts - 1)) if spec.cycle_break else F.array(F.lit(0))

    def grow(seen: Column, _: Column) -> Column:
        found = _next(F.element_at(seen, -1), kappa, spec, tries)
        if spec.cycle_break:
            found = F.concat(F.filter(found, lambda p: ~F.array_contains(seen, p)), F.slice(found, 1, 1))
        return F.concat(seen, F.slice(found, 1, 1))

    return F.aggregate(F.sequence(F.lit(1), F.lit(length - 1)), F.array(pair), grow)


def locate(df, key: str, spec: SketchSpec):
    """df with shard, pair_id and kappa of its key; rows with a null key are dropped, as they join nothing."""
    kappa = print_of(key, spec)
    with_print = df.filter(F.col(key).isNotNull()).withColumn("kappa", kappa)
    return with_print.withColumns({"shard": shard_of(key, spec), "pair_id": pair_of(first_bucket(key, spec), F.col("kappa"), spec)})
