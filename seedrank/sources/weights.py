"""Weight assignments: long tables (assignment, key, weight) and wide ones (key, weights map).

Weights are summed as whole numbers and become doubles only when ranked, so a sum is the same in
every plan.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class BadWeights(ValueError):
    """A weight that is negative, null or not a number, or a pair of assignment and key that occurs twice."""


def composite_key(*parts: Column) -> Column:
    return F.concat_ws("|", *[p.cast("string") for p in parts])


def aggregate(rows: DataFrame, assignment: Column, key: Column, weight: Column, attributes: dict[str, Column] | None = None) -> DataFrame:
    """Long weights: ``weight`` is an aggregate such as a sum; attributes take any value of the group."""
    more = [F.any_value(c).alias(n) for n, c in (attributes or {}).items()]
    return rows.groupBy(assignment.cast("string").alias("assignment"), key.cast("string").alias("key")).agg(weight.alias("weight"), *more)


def distinct_weight(rows: DataFrame, assignment: Column, key: Column, counted: Column) -> DataFrame:
    """Long weights that count distinct values, in two plain aggregations."""
    inner = rows.groupBy(assignment.cast("string").alias("assignment"), key.cast("string").alias("key"), counted.alias("counted")).agg(F.lit(1).alias("one"))
    return inner.where(F.col("counted").isNotNull()).groupBy("assignment", "key").agg(F.count(F.lit(1)).alias("weight"))


def to_wide(long: DataFrame) -> DataFrame:
    """key and its weights as a map; assignments without a row are absent."""
    entry = F.struct(F.col("assignment"), F.col("weight").cast("double"))
    return long.groupBy("key").agg(F.map_from_entries(F.array_sort(F.collect_list(entry))).alias("weights"))


def to_long(wide: DataFrame) -> DataFrame:
    return wide.select("key", F.explode("weights").alias("assignment", "weight"))


def wide_of_columns(rows: DataFrame, key: Column, columns: dict[str, Column], attributes: dict[str, Column] | None = None) -> DataFrame:
    """Wide weights of colocated numeric columns (already one row a key)."""
    entries = F.create_map(*[x for n, c in columns.items() for x in (F.lit(n), c.cast("double"))])
    more = [c.alias(n) for n, c in (attributes or {}).items()]
    return rows.select(key.cast("string").alias("key"), F.map_filter(entries, lambda b, w: w > 0).alias("weights"), *more)


def moments(rows: DataFrame, key: Column, x: Column) -> DataFrame:
    """Two assignments from one measurement: its sum and the sum of its squares."""
    summed = rows.groupBy(key.cast("string").alias("key")).agg(F.sum(x).alias("x"), F.sum(x * x).alias("xx"))
    return wide_of_columns(summed, F.col("key"), {"x": F.col("x"), "xx": F.col("xx")})


def validate(long: DataFrame, policy: str = "fail") -> DataFrame:
    """``long`` without bad weights (``drop``), or as it is after a check that there are none (``fail``)."""
    good = F.col("weight").isNotNull() & (F.col("weight") >= 0) & ~F.isnan(F.col("weight").cast("double"))
    if policy == "drop":
        return long.where(good)
    bad = long.where(~F.coalesce(good, F.lit(False))).limit(1).count()
    twice = long.groupBy("assignment", "key").count().where("count > 1").limit(1).count()
    if bad or twice:
        raise BadWeights("negative, null or undefined weight" if bad else "a key occurs twice in an assignment")
    return long
