"""What coordinated weighted samples are compared with."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seedrank.functions import ranks as R
from seedrank.operators import estimators as E
from seedrank.operators.sketch import Sketch, bottom_k, poisson


def unweighted_sketch(weights: DataFrame, k: int, family: str = "ipps", joint: str = "shared", salt: str = "v1", runs: int = 1) -> Sketch:
    """A sample that ignores weights (each positive one counts as 1) and carries them along."""
    held = weights.where(F.col("weight") > 0).select("assignment", "key", F.lit(1).alias("weight"), F.col("weight").cast("double").alias("value"))
    return bottom_k(R.rank_long(held, family, joint, salt, runs), k, family, joint, salt)


def unweighted(sketch: Sketch, relevant: list[str], f: Callable[[Column], Column]) -> DataFrame:
    """Estimates from an unweighted coordinated sample: a key counts if its seed beats every threshold,
    and then all its positive weights are known."""
    rows = sketch.members(relevant).withColumn("w", F.col("value"))
    bound = sketch.meta.where(F.col("assignment").isin(relevant)).groupBy("run")
    least = bound.agg(F.map_from_entries(F.collect_list(F.struct("assignment", F.struct("rk", "rk1")))).alias("th"))
    names = F.array(*[F.lit(b) for b in relevant])
    keyed = rows.groupBy("run", "key").agg(F.max("rank").alias("rank"), F.map_from_entries(F.collect_list(F.struct("assignment", "w"))).alias("m"))
    keyed = keyed.join(F.broadcast(least), "run")
    cell = lambda b: F.struct(b.alias("b"), F.coalesce(F.col("m")[b], F.lit(0.0)).alias("w"), F.when(F.col("m")[b].isNotNull(), F.col("th")[b]["rk1"]).otherwise(F.col("th")[b]["rk"]).alias("theta"))
    keyed = keyed.withColumn("cells", F.transform(names, cell))
    cells = F.col("cells")
    return E.template(keyed.drop("rank_"), F.col("rank") < E.min_theta(cells), f(cells), R.cdf(sketch.family, F.lit(1.0), E.min_theta(cells))).drop("rank")


def single_primary(summary: DataFrame, base: str, f: Callable[[Column], Column], family: str) -> DataFrame:
    """Another function estimated from one assignment's sample by weight ratios.

    Keys with no weight in ``base`` are never seen, so the estimate is biased where they matter.
    """
    cells = F.col("cells")
    own = F.element_at(F.filter(cells, lambda c: c["b"] == base), 1)
    return E.template(summary, own["inn"], f(cells), R.cdf(family, own["w"], own["theta"]))


def primary_function(vectors: DataFrame, f: Callable[[Column], Column], k: int, family: str = "ipps", salt: str = "v1", runs: int = 1) -> DataFrame:
    """A sample drawn with the function itself as weight (needs whole vectors when sampling)."""
    cells = F.transform(F.map_entries("weights"), lambda e: F.struct(e["key"].alias("b"), e["value"].alias("w")))
    rows = vectors.select("key", cells.alias("cells")).where(F.size("cells") > 0)
    weights = rows.select(F.lit("f").alias("assignment"), "key", f(F.col("cells")).alias("weight"))
    return E.plain(bottom_k(R.rank_long(weights, family, "shared", salt, runs), k, family, "shared", salt), "f")


def poisson_same_size(weights: DataFrame, tau: DataFrame, k: int, assignment: str, salt: str = "v1", runs: int = 1) -> DataFrame:
    """Inverse-probability estimates from a Poisson sample of the same expected size."""
    return E.plain(poisson(R.rank_long(weights, "ipps", "shared", salt, runs), tau, k), assignment)
