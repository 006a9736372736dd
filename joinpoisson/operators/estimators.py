"""Horvitz-Thompson estimates from a sample that carries the probability of each row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NORMAL_95 = 1.959963984540054


def ht_sum(sample: DataFrame, value: Column, weight: str = "weight", by: list[str] | None = None) -> DataFrame:
    """estimate of the sum of value, its variance's estimate and a 95 % interval, by group."""
    w = F.col(weight)
    out = sample.groupBy(*(by or [])).agg(F.sum(value / w).alias("estimate"), F.sum(value * value * (1 - w) / (w * w)).alias("variance"), F.count("*").alias("sampled"))
    half = F.lit(NORMAL_95) * F.sqrt("variance")
    return out.withColumns({"low": F.col("estimate") - half, "high": F.col("estimate") + half})


def ht_count(sample: DataFrame, weight: str = "weight", by: list[str] | None = None) -> DataFrame:
    return ht_sum(sample, F.lit(1.0), weight, by)


def ht_avg(sample: DataFrame, value: Column, weight: str = "weight", by: list[str] | None = None) -> DataFrame:
    """Ratio of the two estimates, with the linearised variance."""
    w = F.col(weight)
    groups = by or []
    sums = sample.groupBy(*groups).agg(F.sum(value / w).alias("s"), F.sum(1 / w).alias("n"), F.sum(value * value * (1 - w) / (w * w)).alias("vv"), F.sum(value * (1 - w) / (w * w)).alias("v1"), F.sum((1 - w) / (w * w)).alias("v0"), F.count("*").alias("sampled"))
    r = F.col("s") / F.col("n")
    return sums.select(*groups, r.alias("estimate"), ((F.col("vv") - 2 * r * F.col("v1") + r * r * F.col("v0")) / (F.col("n") * F.col("n"))).alias("variance"), "sampled")
