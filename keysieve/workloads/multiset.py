"""Multiset experiments: how full a sketch gets before an insert fails, by duplicates per key."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import h60
from ..operators.packed import ChainedFilter, PlainFilter, mix
from ..plans import bounds

OFFSET, RANKS = 2.7, 500


def constant_stream(keys: DataFrame, dupes: int, salt: int) -> DataFrame:
    """(key, attr, pos): every key with the same number of attributes, in an order of hashes."""
    rows = keys.select(F.col("k").alias("key"), F.explode(F.sequence(F.lit(1).cast("bigint"), F.lit(dupes).cast("bigint"))).alias("attr"))
    return ordered(rows, salt)


def ordered(rows: DataFrame, salt: int) -> DataFrame:
    name = F.concat_ws("/", "key", "attr")
    return rows.withColumn("pos", h60(name, "order", salt, "portable"))


def zipf_counts(mean: float, ranks: int = RANKS, offset: float = OFFSET) -> list[int]:
    """Copies by inverse distribution: how often values 1..ranks occur as duplicates of a key, at the exponent that gives the mean."""
    low, high = 0.0, 8.0

    def weights(a):
        w = [(offset + x) ** -a for x in range(1, ranks + 1)]
        s = sum(w)
        return [v / s for v in w]

    for _ in range(60):
        a = (low + high) / 2
        m = sum(x * p for x, p in enumerate(weights(a), 1))
        low, high = (a, high) if m > mean else (low, a)
    return [p for p in weights(low)]


def zipf_draw(share: list[float], u: float) -> int:
    total = 0.0
    for x, p in enumerate(share, 1):
        total += p
        if u < total:
            return x
    return len(share)


def drawn(keys: DataFrame, runs: int, most: int) -> DataFrame:
    """(run, keys): for each run the `most` keys k with the least hashes, in that order; tasks leave out the others."""

    def hashes(k: np.ndarray, run: int) -> np.ndarray:
        x = np.full(len(k), 0x9E3779B97F4A7C15, np.uint64)
        for p in (k.astype(np.int64).view(np.uint64), np.full(len(k), run, np.uint64), np.full(len(k), 17, np.uint64)):  # `mix` for many keys
            x = (x ^ p) * np.uint64(0xBF58476D1CE4E5B9)
            x ^= x >> np.uint64(29)
            x = x * np.uint64(0x94D049BB133111EB)
            x ^= x >> np.uint64(32)
        return x

    def least(k: np.ndarray, run: int) -> np.ndarray:
        k = np.unique(k)
        return k[np.argsort(hashes(k, run), kind="stable")[:most]]

    def within(batches):
        held: dict[int, np.ndarray] = {}
        for pdf in batches:
            for run in range(runs):
                held[run] = least(np.concatenate([held.get(run, np.zeros(0, np.int64)), pdf.k.to_numpy()]), run)
        if held:
            yield pd.DataFrame({"run": list(held), "keys": [v.tolist() for v in held.values()]})

    def across(pdf: pd.DataFrame) -> pd.DataFrame:
        run = int(pdf.run.iloc[0])
        return pd.DataFrame({"run": [run], "keys": [least(np.concatenate([np.asarray(v, np.int64) for v in pdf["keys"]]), run).tolist()]})

    schema = "run int, keys array<bigint>"
    return keys.filter("k is not null").select(F.col("k").cast("bigint").alias("k")).mapInPandas(within, schema).groupBy("run").applyInPandas(across, schema)


def simulate(variant: str, m: int, b: int, d: int, dupes: float, law: str, run: int, key_bits: int = 12, keys=None) -> tuple[int, float, int]:
    """(items placed before the first failure, load then, size in bits); the stream is a fifth longer than the capacity.

    `keys` are the keys that the stream takes, one after the other; without them numbers are. Where they are too few
    to fill the sketch, all are placed.
    """
    sketch = ChainedFilter(m, b, d, None, key_bits=key_bits, salt=run) if variant == "chained" else PlainFilter(m, b, key_bits=key_bits, salt=run)
    length = int(1.2 * m * b)
    rows = []
    share = zipf_counts(dupes) if law == "zipf" else None
    for key in range(length) if keys is None else map(int, keys):
        if len(rows) >= length:
            break
        n = zipf_draw(share, mix(key, run, 11) / 2.0**64) if share else int(dupes)
        rows += [(key, a) for a in range(n)]
    rows.sort(key=lambda r: mix(r[0], r[1], run, 13))
    for i, (k, a) in enumerate(rows):
        if not sketch.insert(k, a):  # attributes of a key are all different
            return i, sketch.load, m * b * (key_bits + 8)
    return len(rows), sketch.load, m * b * (key_bits + 8)


def _met(rows: DataFrame, keys: DataFrame | None, most: int) -> DataFrame:
    """Rows with a run, each with the keys that its run draws; null without a table of keys."""
    if keys is None:
        return rows.withColumn("keys", F.lit(None).cast("array<bigint>"))
    runs = rows.agg(F.max("run")).first()[0] + 1
    return rows.join(F.broadcast(drawn(keys, runs, most)), "run", "left").select(*rows.columns, F.coalesce("keys", F.array().cast("array<bigint>")).alias("keys"))


def experiment(spark, configs: list[tuple], keys: DataFrame | None = None) -> DataFrame:
    """One row for each (variant, m, b, d, dupes, law, run): runs in parallel, each in one task, over the keys k of a table."""
    rows = spark.createDataFrame(configs, "variant string, m int, b int, d int, dupes double, law string, run int")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        for r in pdf.itertuples(index=False):
            items, load, bits = simulate(r.variant, r.m, r.b, r.d, r.dupes, r.law, r.run, keys=r.keys)
            out.append((*r[:7], items, load, bits))
        return pd.DataFrame(out, columns=[*pdf.columns[:7], "items", "load", "bits"])

    schema = "variant string, m int, b int, d int, dupes double, law string, run int, items long, load double, bits long"
    rows = _met(rows, keys, max(int(1.2 * m * b) for _, m, b, *_ in configs))  # no stream takes more keys
    return rows.repartition(max(1, len(configs) // 4), "variant", "b", "d", "dupes", "run").groupBy("variant", "b", "d", "dupes", "run").applyInPandas(run, schema)


def efficiency(m: int, b: int, d: int, dupes: int, run: int, key_bits: int, keys=None) -> tuple[float, float, float]:
    """Bits per inserted copy and bit of the false positive rate, of the key prints of a chained sketch filled to its first failure.

    First with the rate that an absent key meets, by the different prints in its two buckets, then with the bound
    that takes all entries there as different; and that rate. Copies of a key beyond d lengthen its chain.
    """
    sketch = ChainedFilter(m, b, d, None, key_bits=key_bits, salt=run)
    most = int(1.2 * m * b / dupes) + 1
    rows = sorted(((k, a) for k in (range(most) if keys is None else map(int, keys[:most])) for a in range(dupes)), key=lambda r: mix(r[0], r[1], run, 13))
    done = 0
    for k, a in rows:
        if not sketch.insert(k, a):
            break
        done += 1
    pairs = [sketch.slots[i] + sketch.slots[(i + m // 2) % m] for i in range(m)]
    rates = [sum(len(x) for x in held) / m * 2.0**-key_bits for held in ([{e[0] for e in p} for p in pairs], pairs)]
    if not done:
        return math.nan, math.nan, 0.0
    one, bound = (m * b * key_bits / (done * math.log2(1 / r)) for r in rates)
    return one, bound, rates[0]


LINEAR = bounds.linear_probing_cost
