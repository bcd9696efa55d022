"""Reduction factors and false positive rates from counts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def reduction_factor(semi: Column, pred: Column) -> Column:
    return F.when(pred > 0, F.round(semi / pred, 6))


def workload_fpr(sketch: Column, exact: Column, pred: Column) -> Column:
    """False rows over rows that ought to go."""
    return F.when(pred > exact, F.round((sketch - exact) / (pred - exact), 6)).otherwise(F.lit(0.0))


def overall(instances: DataFrame, columns: list[str]) -> DataFrame:
    """Pooled reduction factors of several methods, and their means over instances."""
    pooled = [F.round(F.sum(c) / F.sum("m_pred"), 6).alias(c.replace("m_", "rf_")) for c in columns]
    means = [F.round(F.avg(F.col(c) / F.col("m_pred")), 6).alias(c.replace("m_", "mean_")) for c in columns]
    return instances.agg(F.count("*").alias("instances"), *pooled, *means)


def by_joins(instances: DataFrame, columns: list[str]) -> DataFrame:
    return instances.groupBy("n_rel").agg(F.count("*").alias("instances"), *(F.round(F.sum(c) / F.sum("m_pred"), 6).alias(c.replace("m_", "rf_")) for c in columns))
