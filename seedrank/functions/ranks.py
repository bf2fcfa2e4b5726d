"""Rank families and joint distributions of rank vectors.

A rank is a random number that is stochastically smaller for a larger weight.  ``ipps`` ranks are
uniform over a range that is inverse to the weight, ``exp`` ranks are exponential with the weight as rate.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seedrank.functions import seeds

FAMILIES = ("ipps", "exp")
JOINTS = ("shared", "independent", "inddiff")
INFINITY = float("inf")


class UnsupportedDesign(ValueError):
    """A combination of rank family, joint distribution and data layout that has no definition."""


def check_design(family: str, joint: str, layout: str = "colocated") -> None:
    if family not in FAMILIES or joint not in JOINTS:
        raise UnsupportedDesign(f"unknown design: {family}, {joint}")
    if joint == "inddiff" and family != "exp":
        raise UnsupportedDesign("independent differences are defined for exponential ranks")
    if joint == "inddiff" and layout == "dispersed":
        raise UnsupportedDesign("independent differences need a key's whole weight vector")


def rank(family: str, weight: Column, seed: Column) -> Column:
    """The rank of a weight for a seed; a weight of zero ranks last."""
    value = seed / weight if family == "ipps" else -F.log1p(-seed) / weight
    return F.when(weight > 0, value).otherwise(F.lit(INFINITY))


def cdf(family: str, weight: Column, x: Column) -> Column:
    """Probability that the rank of ``weight`` is below ``x``; zero for a weight of zero, at any ``x``."""
    value = F.least(F.lit(1.0), weight * x) if family == "ipps" else -F.expm1(-(weight * x))
    return F.when(weight > 0, value).otherwise(F.lit(0.0))


def quantile(family: str, weight: Column, probability: Column) -> Column:
    """The inverse of ``cdf`` in its second argument."""
    return rank(family, weight, probability)


def with_runs(df: DataFrame, runs: int = 1) -> DataFrame:
    """``df`` once for each replication 0 .. runs-1, as column ``run``."""
    if runs == 1:
        return df.withColumn("run", F.lit(0))
    return df.withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))


def rank_long(weights: DataFrame, family: str = "ipps", joint: str = "shared", salt: str = "v1", runs: int = 1, algo: str = "md5") -> DataFrame:
    """(run, assignment, key, weight, seed, rank) of every positive weight of a long table.

    No row needs another one, so assignments can be ranked by separate jobs.
    """
    check_design(family, joint, "dispersed")
    rows = with_runs(weights.where(F.col("weight") > 0).withColumn("weight", F.col("weight").cast("double")), runs)
    s = seeds.salted(salt, F.col("run"))
    seed = seeds.key_seed(F.col("key"), s, algo) if joint == "shared" else seeds.pair_seed(F.col("key"), F.col("assignment"), s, algo)
    return rows.withColumn("seed", seed).withColumn("rank", rank(family, F.col("weight"), F.col("seed")))


def rank_wide(vectors: DataFrame, family: str = "ipps", joint: str = "shared", salt: str = "v1", runs: int = 1, algo: str = "md5", unit: bool = False) -> DataFrame:
    """(run, key, cells) of every key with a positive weight; ``cells`` holds b, w, seed and rank in order of b.

    ``vectors``: key, weights map<string,double>.  ``unit`` ranks every positive weight as if it were 1.
    """
    check_design(family, joint)
    rows = with_runs(vectors.withColumn("w", F.map_filter("weights", lambda b, w: w > 0)).where(F.size("w") > 0), runs)
    s = seeds.salted(salt, F.col("run"))
    if joint == "inddiff":
        return _independent_differences(rows, s, algo)
    if joint == "shared":
        rows = rows.withColumn("u", seeds.key_seed(F.col("key"), s, algo))
        seed_of = lambda b: F.col("u")
    else:
        seed_of = lambda b: seeds.pair_seed(F.col("key"), b, s, algo)
    drawn = F.transform(F.map_entries("w"), lambda e: F.struct(e["key"].alias("b"), e["value"].cast("double").alias("w"), seed_of(e["key"]).alias("seed")))
    ranked = F.transform(F.array_sort(drawn), lambda c: F.struct(c["b"].alias("b"), c["w"].alias("w"), c["seed"].alias("seed"), rank(family, F.lit(1.0) if unit else c["w"], c["seed"]).alias("rank")))
    return rows.select("run", "key", ranked.alias("cells"), *_attributes(vectors))


def _attributes(df: DataFrame) -> list[str]:
    return [c for c in df.columns if c not in ("key", "weights")]


def _independent_differences(rows: DataFrame, salt: Column, algo: str) -> DataFrame:
    """Weights in ascending order; the rank of one is the least exponential draw of the gaps up to it."""
    ascending = F.array_sort(F.transform(F.map_entries("w"), lambda e: F.struct(e["value"].cast("double").alias("w"), e["key"].alias("b"))))

    def ranked(asc: Column) -> Column:
        gap = lambda c, i: c["w"] - F.when(i > 0, F.get(asc, i - 1)["w"]).otherwise(0.0)
        draws = F.transform(asc, lambda c, i: rank("exp", gap(c, i), seeds.gap_seed(F.col("key"), i, salt, algo)))
        cell = lambda c, r: F.struct(c["b"].alias("b"), c["w"].alias("w"), F.lit(None).cast("double").alias("seed"), r.alias("rank"))
        return _bind(draws, lambda d: F.transform(asc, lambda c, i: cell(c, F.array_min(F.slice(d, 1, i + 1)))))

    keep = [c for c in rows.columns if c not in ("key", "weights", "w", "run")]
    return rows.select("run", "key", F.array_sort(_bind(ascending, ranked)).alias("cells"), *keep)


def _bind(value: Column, body) -> Column:
    """``body`` of ``value``, which is evaluated once a row however often the body uses it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def to_long(ranked: DataFrame) -> DataFrame:
    """The rows of ``rank_long`` from those of ``rank_wide``."""
    return ranked.select("run", "key", F.explode("cells").alias("c")).select("run", F.col("c.b").alias("assignment"), "key", F.col("c.w").alias("weight"), "c.seed", "c.rank")


def inconsistent_keys(ranked: DataFrame) -> DataFrame:
    """Keys for which a heavier assignment has a larger rank than a lighter one (``ranked``: long)."""
    by_weight = Window.partitionBy("run", "key").orderBy(F.col("weight").desc(), "rank")
    lighter_first = F.col("rank") < F.max("rank").over(by_weight.rowsBetween(Window.unboundedPreceding, -1))
    heavier = F.col("weight") < F.lag("weight").over(by_weight)
    return ranked.withColumn("bad", lighter_first & heavier).where("bad").select("run", "key").distinct()


def min_rank(ranked: DataFrame, relevant: list[str]) -> DataFrame:
    """(run, key, weight, rank): the least rank over the relevant assignments is a rank of the greatest weight."""
    rows = ranked.where(F.col("assignment").isin(relevant))
    return rows.groupBy("run", "key").agg(F.max("weight").alias("weight"), F.min("rank").alias("rank"))
