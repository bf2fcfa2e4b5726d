"""Exact aggregates over the full data: what the samples estimate, and the costly way to get it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def per_key(long: DataFrame, relevant: list[str]) -> DataFrame:
    """(key, total, high, low, n, weights): sum, maximum and minimum over ``relevant``; an absent weight is zero."""
    rows = long.where(F.col("assignment").isin(relevant) & (F.col("weight") > 0))
    out = rows.groupBy("key").agg(F.sum("weight").alias("total"), F.max("weight").alias("high"), F.min("weight").alias("least"), F.count(F.lit(1)).alias("n"), F.sort_array(F.collect_list("weight"), asc=False).alias("weights"))
    return out.withColumn("low", F.when(F.col("n") == len(relevant), F.col("least")).otherwise(0)).drop("least")


def norms(long: DataFrame, relevant: list[str]) -> DataFrame:
    """One row: keys, sums of minima, maxima and differences, and the weighted Jaccard similarity."""
    k = per_key(long, relevant)
    sums = k.agg(F.count(F.lit(1)).alias("keys"), F.sum("low").alias("sum_min"), F.sum("high").alias("sum_max"), F.sum(F.col("high") - F.col("low")).alias("sum_l1"))
    return sums.withColumn("jaccard", F.round(F.col("sum_min") / F.col("sum_max"), 9))


def lth_total(long: DataFrame, relevant: list[str], ell: int) -> DataFrame:
    return per_key(long, relevant).agg(F.sum(F.coalesce(F.get("weights", F.lit(ell - 1)), F.lit(0))).alias("total"))


def sums(long: DataFrame, d: Column | None = None, by: list[str] | None = None) -> DataFrame:
    rows = long if d is None else long.where(d)
    return rows.groupBy("assignment", *(by or [])).agg(F.sum("weight").alias("total"), F.count(F.lit(1)).alias("keys"))


def outer_join_vectors(long: DataFrame, a: str, b: str) -> DataFrame:
    """(key, wa, wb) of two assignments by a full outer join: what collating all data costs."""
    left = long.where(F.col("assignment") == a).select("key", F.col("weight").alias("wa"))
    right = long.where(F.col("assignment") == b).select("key", F.col("weight").alias("wb"))
    return left.join(right, "key", "full_outer").select("key", F.coalesce("wa", F.lit(0)).alias("wa"), F.coalesce("wb", F.lit(0)).alias("wb"))


def heavier_in(long: DataFrame, a: str, b: str) -> DataFrame:
    """Total of b over the keys that weigh more in b than in a."""
    return outer_join_vectors(long, a, b).where("wb > wa").agg(F.count(F.lit(1)).alias("keys"), F.sum("wb").alias("total"))
