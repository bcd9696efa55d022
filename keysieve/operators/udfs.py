"""Sketches as SQL functions: a probe over packed groups, a mask aggregate, a table function, and SQL text."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Most groups that are packed into one broadcast array; beyond it the semi join is the way.
MOST_GROUPS = 1 << 22


def packed_groups(live: DataFrame) -> np.ndarray | None:
    """Live groups as a sorted array of pair_id * 2**32 + kappa, or None if there are too many to broadcast."""
    if live.limit(MOST_GROUPS + 1).count() > MOST_GROUPS:
        return None
    rows = live.select((F.shiftleft(F.col("pair_id").cast("bigint"), 32) + F.col("kappa")).alias("g")).toArrow()
    return np.sort(rows["g"].to_numpy())


def contains_udf(spark: SparkSession, groups: np.ndarray):
    """(pair_id, kappa) -> whether the group is live."""
    shared = spark.sparkContext.broadcast(groups)

    @F.pandas_udf("boolean")
    def paf_contains(pair_id: pd.Series, kappa: pd.Series) -> pd.Series:
        g, want = shared.value, (pair_id.to_numpy().astype(np.int64) << 32) + kappa.to_numpy()
        if not len(g):
            return pd.Series(np.zeros(len(want), bool))
        at = np.searchsorted(g, want)
        at[at == len(g)] = 0
        return pd.Series(g[at] == want)

    return paf_contains


@F.pandas_udf(T.LongType())
def paf_mask(mask: pd.Series) -> int:
    """The union of masks of a group."""
    return int(np.bitwise_or.reduce(mask.to_numpy().astype(np.int64))) if len(mask) else 0


@F.udtf(returnType=T.StructType([T.StructField("pair_id", T.LongType()), T.StructField("kappa", T.IntegerType())]))
class EntriesOf:
    """Groups of a packed array of 8-byte numbers."""

    def eval(self, blob: bytes):
        for g in np.frombuffer(blob, "<i8").tolist():
            yield g >> 32, g & 0xFFFFFFFF


def register(spark: SparkSession, name: str, live: DataFrame) -> str:
    """Makes live groups a view and gives the SQL condition that probes it for columns pair_id and kappa of an alias p."""
    live.createOrReplaceTempView(name)
    return f"exists (select 1 from {name} l where l.pair_id = p.pair_id and l.kappa = p.kappa)"
