"""Range predicates as in-lists: equal-width and equal-depth bins, and dyadic intervals."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def width_bin(col: Column, low: int, high: int, bins: int) -> Column:
    """Bin of an integer by equal widths of [low, high]; values outside go to the outer bins."""
    size = -(-(high - low + 1) // bins)
    return F.least(F.greatest(F.floor((col - low) / size), F.lit(0)), F.lit(bins - 1)).cast("bigint")


def width_inlist(lo: int | None, hi: int | None, low: int, high: int, bins: int) -> list[int]:
    """Bins that a closed range touches."""
    size = -(-(high - low + 1) // bins)
    first = 0 if lo is None else min(max((lo - low) // size, 0), bins - 1)
    last = bins - 1 if hi is None else min(max((hi - low) // size, 0), bins - 1)
    return [] if lo is not None and hi is not None and lo > hi else list(range(first, last + 1))


def depth_edges(df: DataFrame, column: str, bins: int) -> DataFrame:
    """(bin, lo, hi): bins over the ordered distinct values with as many values each."""
    values = df.select(column).filter(F.col(column).isNotNull()).distinct()
    cut = values.withColumn("bin", F.ntile(bins).over(Window.orderBy(column)) - 1)
    return cut.groupBy("bin").agg(F.min(column).alias("lo"), F.max(column).alias("hi"))


def dyadic_items(col: Column, levels: int) -> Column:
    """The intervals that hold a value in [0, 2**levels): codes 2**level + prefix, from the whole range down to the value."""
    return F.array(*(F.lit(1 << i) + F.shiftright(col.cast("bigint"), levels - i) for i in range(levels + 1)))


def dyadic_cover(lo: int, hi: int, levels: int) -> list[int]:
    """The fewest dyadic intervals that make up a closed range, as codes."""
    out, lo, hi = [], max(lo, 0) + (1 << levels), min(hi, (1 << levels) - 1) + (1 << levels) + 1
    while lo < hi:
        if lo & 1:
            out.append(lo)
            lo += 1
        if hi & 1:
            hi -= 1
            out.append(hi)
        lo >>= 1
        hi >>= 1
    return sorted(out)
