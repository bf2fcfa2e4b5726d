"""Relational helpers around the samples, each a lazy plan."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def join_attributes(rows: DataFrame, dimension: DataFrame, on: str, strategy: str = "auto", how: str = "inner") -> DataFrame:
    """``rows`` with columns of a dimension; ``strategy``: auto, broadcast, shuffle_hash or merge."""
    return rows.join(dimension if strategy == "auto" else dimension.hint(strategy), on, how)


def semi_keys(rows: DataFrame, keys: DataFrame, key: str = "key") -> DataFrame:
    return rows.join(keys, key, "left_semi")


def anti_keys(rows: DataFrame, keys: DataFrame, key: str = "key") -> DataFrame:
    return rows.join(keys, key, "left_anti")


def top_changes(adjusted: DataFrame, n: int, per: str | None = None) -> DataFrame:
    """The ``n`` largest adjusted values, over all or for each value of ``per``; ties by key."""
    order = [F.col("adjusted").desc(), F.col("key")]
    if per is None:
        return adjusted.orderBy(*order).limit(n)
    place = F.row_number().over(Window.partitionBy(per).orderBy(*order))
    return adjusted.withColumn("place", place).where(F.col("place") <= n)


def pairs(long: DataFrame) -> DataFrame:
    """(key, a, b, wa, wb) of the pairs of assignments that a key has both, made inside the key's own list."""
    entry = F.array_sort(F.collect_list(F.struct("assignment", "weight")))
    held = long.where(F.col("weight") > 0).groupBy("key").agg(entry.alias("xs")).where(F.size("xs") > 1)
    first = held.select("key", "xs", F.posexplode("xs").alias("i", "x"))
    later = F.slice("xs", F.col("i") + 2, F.size("xs"))
    return first.select("key", "x", F.explode(later).alias("y")).select("key", F.col("x.assignment").alias("a"), F.col("y.assignment").alias("b"), F.col("x.weight").alias("wa"), F.col("y.weight").alias("wb"))


def change_vs_previous(long: DataFrame) -> DataFrame:
    by = Window.partitionBy("key").orderBy("assignment")
    return long.withColumn("change", F.col("weight") - F.lag("weight").over(by))


def moving_sum(long: DataFrame, n: int) -> DataFrame:
    by = Window.partitionBy("key").orderBy("assignment").rowsBetween(-(n - 1), 0)
    return long.withColumn("moving", F.sum("weight").over(by))


def asof_last(cuts: DataFrame, rows: DataFrame, key: str, label: str, at: str, value: str, tie: str) -> DataFrame:
    """The last ``value`` of each key before each cut-off time (few cut-offs; rows are never sorted whole).

    Each row goes to the first cut-off after it, where only the last row of a key survives; the
    survivors are then carried forward over the cut-offs.
    """
    spans = cuts.select(label, F.col(at).alias("until"), F.lag(at).over(Window.orderBy(at)).alias("since"))
    placed = rows.join(F.broadcast(spans), (F.col(at) < F.col("until")) & (F.col("since").isNull() | (F.col(at) >= F.col("since"))))
    last = placed.groupBy(key, label).agg(F.max_by(F.struct(value), tie).alias("v"))
    keys = last.select(key).distinct()
    grid = keys.join(F.broadcast(cuts.select(label)))
    run = Window.partitionBy(key).orderBy(label).rowsBetween(Window.unboundedPreceding, 0)
    full = grid.join(last, [key, label], "left").withColumn("v", F.last("v", ignorenulls=True).over(run))
    return full.where(F.col("v").isNotNull()).select(key, label, f"v.{value}")


def interval_join(points: DataFrame, spans: DataFrame, x: str, lo: str, hi: str, cell: int) -> DataFrame:
    """Points with the spans they lie in; spans are laid out on cells of width ``cell``, and cells are joined."""
    laid = spans.withColumn("_cell", F.explode(F.sequence(F.floor(F.col(lo) / cell), F.floor(F.col(hi) / cell))))
    placed = points.withColumn("_cell", F.floor(F.col(x) / cell))
    return placed.join(laid, "_cell").where(F.col(x).between(F.col(lo), F.col(hi))).drop("_cell")


def json_field(column: Column, name: str, kind: str = "string") -> Column:
    return F.get_json_object(column, f"$.{name}").cast(kind)


def aggregate_weights(rows: DataFrame, key: str, counted: str, distinct: str = "exact") -> DataFrame:
    """(key, weight): distinct values of ``counted``, exactly or by a sketch of distinct values."""
    count = F.count_distinct(counted) if distinct == "exact" else F.approx_count_distinct(counted, 0.02)
    return rows.groupBy(F.col(key).cast("string").alias("key")).agg(count.alias("weight"))
