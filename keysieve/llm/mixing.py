"""Mixing sources to target weights by pivotal dependent rounding.

A source's documents each start with target / source size copies: a whole part, and a fraction that is the
same for all. Two documents with fractional parts meet; words move at random from one to the other, by as
much as makes one of them whole, so that each keeps its expected copies and the words of both together stay
what they were. Each group of documents leaves one fractional document at most; those meet again in a tree
of groups until one is left for a source, which is drawn alone. A source's words thus miss its target by
less than the size of its largest document.

Randomness is a keyed hash of the two documents, and groups are hashes of doc_id, so reruns agree.

Defined results: a null text has size 0 and takes 0 words; null sources are one source, the last. A source
without words has target 0. Rows of equal doc_id are documents of their own. An empty table gives no rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

WORD = r"[^\x20\x09-\x0D]+"
#: Most times a source may be repeated, rows of a group at the leaves, and groups that meet in a node.
MOST, LEAF, FAN = 3.0, 4000, 64


def targets(sizes: list[tuple[str | None, int]], weights: tuple[float, ...] = (1, 2, 3), most: float = MOST) -> dict[str | None, float]:
    """Target words of each source: shares by repeating weights over sources in code point order (null last), none above `most` times its size."""
    order = sorted(sizes, key=lambda s: (s[0] is None, s[0] or ""))
    weight = {s: weights[i % len(weights)] for i, (s, _) in enumerate(order)}
    size, out = dict(order), {}
    left, free = float(sum(size.values())), [s for s, _ in order]
    while free:
        total = sum(weight[s] for s in free)
        over = [s for s in free if left * weight[s] / total > most * size[s]]
        if not over:
            out |= {s: left * weight[s] / total for s in free}
            break
        out |= {s: most * size[s] for s in over}
        left -= sum(out[s] for s in over)
        free = [s for s in free if s not in out]
    return out


def _draw(a: int, b: int, seed: int) -> float:
    """A number in [0, 1) from two keys."""
    x = (a * 0x9E3779B97F4A7C15 ^ (b + seed) * 0xC2B2AE3D27D4EB4F) & 0xFFFFFFFFFFFFFFFF
    x = ((x ^ x >> 30) * 0xBF58476D1CE4E5B9) & 0xFFFFFFFFFFFFFFFF
    x = ((x ^ x >> 27) * 0x94D049BB133111EB) & 0xFFFFFFFFFFFFFFFF
    return (x ^ x >> 31) / 2.0**64


def pivot(keys: list[int], sizes: list[int], parts: list[float], seed: int, last: bool = False) -> list[float]:
    """The fractional parts after rounding: all 0 or 1, but for one at most, which is drawn if `last`."""
    out, held, tiny = list(parts), -1, 1e-12
    for i in range(len(keys)):
        if not tiny < out[i] < 1 - tiny:
            out[i] = float(round(out[i]))
            continue
        if held < 0:
            held = i
            continue
        a, b, sa, sb = out[held], out[i], sizes[held], sizes[i]
        to_held, to_new = min((1 - a) * sa, b * sb), min(a * sa, (1 - b) * sb)
        if _draw(keys[held], keys[i], seed) * (to_held + to_new) < to_new:
            moved = to_held
        else:
            moved = -to_new
        a, b = a + moved / sa, b - moved / sb
        out[held], out[i] = a, b
        whole_a, whole_b = not tiny < a < 1 - tiny, not tiny < b < 1 - tiny
        if whole_a:
            out[held] = float(round(a))
        if whole_b:
            out[i] = float(round(b))
        held = -1 if whole_a and whole_b else i if whole_a else held
    if last and held >= 0:
        out[held] = float(_draw(keys[held], 0, seed) < out[held])
    return out


def mix(docs: DataFrame, weights: tuple[float, ...] = (1, 2, 3), seed: int = 11, text: str = "text", source: str = "source") -> DataFrame:
    """(doc_id, size, source_size, target, taken, copies, source) of every row."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(source).cast("string").alias("source"), F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long").alias("size"))
    sized = written(rows, "sizes")
    spark = docs.sparkSession
    found = [(r["source"], int(r["n"]), int(r["docs"])) for r in sized.groupBy("source").agg(F.sum("size").alias("n"), F.count("*").alias("docs")).collect()]  # one row for each source
    goal = targets([f[:2] for f in found], weights)
    table = [(s, n, float(goal[s]), goal[s] / n if n else 0.0, math.ceil(docs / LEAF)) for s, n, docs in found]
    plan = F.broadcast(spark.createDataFrame(table, "source string, source_size long, target double, ratio double, cells long")).alias("plan")
    cells = max((t[4] for t in table), default=1)
    dealt = sized.alias("d").join(plan, F.col("d.source").eqNullSafe(F.col("plan.source"))).select(
        F.coalesce("doc_id", F.lit(0)).alias("key"), "doc_id", F.col("d.source").alias("source"), "size", "source_size", "target",
        F.floor("ratio").alias("whole"), F.when(F.col("size") > 0, F.col("ratio") - F.floor("ratio")).otherwise(0.0).alias("part"),
        F.pmod(F.xxhash64("doc_id", "size"), F.col("cells")).alias("cell"),
    )
    kinds = "doc_id long, source string, size long, source_size long, target double, whole long, part double, cell long, key long"

    def rounding(last: bool):
        def run(group: pa.Table) -> pa.Table:
            group = group.sort_by([("size", "descending"), ("key", "ascending")])  # what is left over is small
            out = pivot(group["key"].to_pylist(), group["size"].to_pylist(), group["part"].to_pylist(), seed, last)
            at = group.schema.get_field_index("part")
            return group.set_column(at, "part", pa.array(out, pa.float64())).select([k.split()[0] for k in kinds.split(", ")])

        return run

    done, level = None, dealt.select([k.split()[0] for k in kinds.split(", ")])
    whole = (F.col("part") == 0) | (F.col("part") == 1)
    while True:
        level = written(level.groupBy("source", "cell").applyInArrow(rounding(cells == 1), kinds), "rounded")
        done = level.filter(whole) if done is None else done.unionByName(level.filter(whole))
        if cells == 1:
            break
        cells = math.ceil(cells / FAN)
        level = level.filter(~whole).withColumn("cell", F.floor(F.col("cell") / FAN))
    copies = (F.col("whole") + F.col("part")).cast("long")
    return done.select("doc_id", "size", "source_size", "target", (copies * F.col("size")).alias("taken"), copies.alias("copies"), "source")
