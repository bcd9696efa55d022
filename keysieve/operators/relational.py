"""Relational operators around the sketches: joins by strategy, as-of, interval and range joins, and small helpers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

HINTS = {"broadcast": "broadcast", "shuffle_hash": "shuffle_hash", "merge": "merge", None: None}


def join(a: DataFrame, b: DataFrame, on, how: str = "inner", strategy: str | None = None) -> DataFrame:
    """A join with a strategy hint; without one Spark decides by measured sizes. A broadcast side must be known to be small."""
    hint = HINTS[strategy]
    return a.join(b.hint(hint) if hint else b, on, how)


def semi(a: DataFrame, b: DataFrame, on) -> DataFrame:
    return a.join(b, on, "left_semi")


def anti(a: DataFrame, b: DataFrame, on) -> DataFrame:
    return a.join(b, on, "left_anti")


def range_join(a: DataFrame, x: str, ranges: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """Rows of a with every range that holds x: an equi join on cells of a fixed width, then the exact bounds."""
    cells = ranges.withColumn("__cell", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    met = a.withColumn("__cell", F.floor(F.col(x) / width)).join(cells, "__cell")
    return met.filter(F.col(x).between(F.col(lo), F.col(hi))).drop("__cell")


def asof(left: DataFrame, right: DataFrame, by: str, time: str, value: str) -> DataFrame:
    """left with the last value of right up to its time: one exchange by key instead of a range join."""
    marked = left.withColumns({value: F.lit(None).cast(right.schema[value].dataType), "__left": F.lit(1)})
    rest = right.select(by, time, value, F.lit(0).alias("__left"))
    order = Window.partitionBy(by).orderBy(time, "__left").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = marked.unionByName(rest, allowMissingColumns=True)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(order)).filter("__left = 1").drop("__left")


def interval_join(a: DataFrame, b: DataFrame, key: str, ta: str, tb: str, days: int) -> DataFrame:
    """Pairs of one key with 0 <= tb - ta <= days: an equi join on key and blocks of days, then the exact bound."""
    at = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    block = lambda c: F.floor(at(c) / (86_400_000_000 * max(1, days)))
    left = a.withColumn("__b", F.explode(F.array(block(ta), block(ta) + 1)))
    met = left.join(b.withColumn("__b", block(tb)), [key, "__b"]).drop("__b")
    gap = at(tb) - at(ta)  # in microseconds: whole seconds would let a pair through that is up to one second beyond
    return met.filter((gap >= 0) & (gap <= 86_400_000_000 * days))


def top_per_group(df: DataFrame, group: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group; Spark prunes each partition to k before it moves rows."""
    return df.withColumn("__r", F.row_number().over(Window.partitionBy(*group).orderBy(*order))).filter(F.col("__r") <= k).drop("__r")


def grid(*axes: DataFrame) -> DataFrame:
    """All combinations of small tables of parameters."""
    out = axes[0]
    for a in axes[1:]:
        out = out.crossJoin(a)
    return out
