"""Accuracy and size of samples, averaged over replications (``run``)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seedrank.functions import ranks as R
from seedrank.operators import estimators as E
from seedrank.operators.sketch import Sketch


def key_variance(f: Column, p: Column) -> Column:
    """Variance of a key's adjusted value given the other keys' ranks; zero where f is."""
    return F.when(f > 0, f * f * (1 / p - 1)).otherwise(0.0)


def l1_variance(high: Column, low: Column, p_high: Column, p_low: Column) -> Column:
    """The same for the difference of two estimates of which the lower one counts only with the other."""
    a = high / p_high
    b, both = F.when(low > 0, low / p_low).otherwise(0.0), F.when(low > 0, p_low).otherwise(0.0)
    return F.when(high > 0, both * (a - b) * (a - b) + (p_high - both) * a * a - (high - low) * (high - low)).otherwise(0.0)


def conditional_variance(full: DataFrame, f: Callable[[Column], Column], p: Callable[[Column], Column]) -> DataFrame:
    """(run, sv): sum over all keys of f^2 (1/p - 1), the variance given the others' ranks.

    Its mean over runs is the sum of variances, also where keys are too rare ever to be drawn.
    """
    cells = F.col("cells")
    rows = full.select("run", f(cells).cast("double").alias("f"), p(cells).alias("p"))
    return rows.groupBy("run").agg(F.sum(key_variance(F.col("f"), F.col("p"))).alias("sv"))


def conditional_variance_l1(full: DataFrame, p_max: Callable[[Column], Column], p_min: Callable[[Column], Column]) -> DataFrame:
    """The same for the difference of the estimates of maximum and minimum, whose events are nested."""
    cells = F.col("cells")
    rows = full.select("run", E.f_max(cells).alias("h"), E.f_min(cells).alias("l"), p_max(cells).alias("ph"), p_min(cells).alias("pl"))
    return rows.groupBy("run").agg(F.sum(l1_variance(F.col("h"), F.col("l"), F.col("ph"), F.col("pl"))).alias("sv"))


def sigma_v(adjusted: DataFrame, exact: DataFrame, runs: int) -> DataFrame:
    """(sv, nsv): mean over runs of the squared errors of all keys; ``exact``: key, f.

    Keys that a run did not sample err by f; only sampled rows are touched, the rest is one sum of f^2.
    """
    base = exact.agg(F.sum(F.col("f").cast("double") ** 2).alias("ff"), F.sum(F.col("f").cast("double")).alias("s"))
    change = adjusted.agg(F.sum(F.col("adjusted") ** 2 - 2 * F.col("adjusted") * F.col("f")).alias("c"))
    sv = F.col("ff") + F.coalesce("c", F.lit(0.0)) / runs
    return base.crossJoin(F.broadcast(change)).select(sv.alias("sv"), (sv / F.col("s") ** 2).alias("nsv"))


def per_key_variance(adjusted: DataFrame, exact: DataFrame, runs: int) -> DataFrame:
    """(key, mean, variance) of the adjusted values over all runs, unsampled ones as zero."""
    seen = adjusted.groupBy("key").agg(F.sum("adjusted").alias("s"), F.sum(F.col("adjusted") ** 2).alias("ss"))
    rows = exact.join(seen, "key", "left").na.fill(0.0, ["s", "ss"])
    return rows.select("key", "f", (F.col("s") / runs).alias("mean"), (F.col("ss") / runs - F.col("f").cast("double") ** 2).alias("variance"))


def squared_error(estimates: DataFrame, truth: float) -> DataFrame:
    """(mse, relative_error) of a subpopulation's estimate over runs."""
    e = F.col("estimate") - F.lit(float(truth))
    return estimates.agg(F.avg(e**2).alias("mse"), (F.sqrt(F.avg(e**2)) / truth).alias("relative_error"))


def covariance(adjusted: DataFrame, pairs: list[tuple[str, str]], exact: dict[str, float], runs: int) -> DataFrame:
    """(a, b, covariance) of the adjusted values of pairs of keys over runs."""
    rows = adjusted.where(F.col("key").isin([x for p in pairs for x in p])).groupBy("run").agg(F.map_from_entries(F.collect_list(F.struct("key", "adjusted"))).alias("m"))
    value = lambda k: F.coalesce(F.col("m")[k], F.lit(0.0))
    found = rows.agg(*[F.sum(value(a) * value(b)).alias(f"c{i}") for i, (a, b) in enumerate(pairs)])
    out = None
    for i, (a, b) in enumerate(pairs):
        one = found.select(F.lit(a).alias("a"), F.lit(b).alias("b"), (F.coalesce(F.col(f"c{i}"), F.lit(0.0)) / runs - exact[a] * exact[b]).alias("covariance"))
        out = one if out is None else out.unionByName(one)
    return out


def bound_check(nsv: float, k: int) -> float:
    """(k-2) times the normalised variance: at most one by theory."""
    return (k - 2) * nsv


def combined_size(sketch: Sketch) -> DataFrame:
    """(run, keys): distinct keys of a summary."""
    return sketch.members().groupBy("run").agg(F.count_distinct("key").alias("keys"))


def sharing_index(sketch: Sketch, k: int, m: int) -> DataFrame:
    """Distinct keys over ``k * m``, between 1/m (all samples equal) and 1 (all disjoint), averaged over runs."""
    return combined_size(sketch).agg(F.avg(F.col("keys") / (k * m)).alias("sharing_index"))


def usable_for_max(sketch: Sketch, relevant: list[str]) -> DataFrame:
    """(run, keys) that the estimate of the maximum counts: at least k-1."""
    return E.maximum(sketch, relevant).groupBy("run").agg(F.count(F.lit(1)).alias("keys"))


def bound_violations(full: DataFrame, family: str, primary: DataFrame) -> DataFrame:
    """Counts of keys that break what theory says of a key's probabilities and variances (shared seeds; all zero).

    ``primary``: thresholds by run of a sample drawn with the maximum itself as weight.
    """
    cells, eps = F.col("cells"), 1e-12
    each = F.transform(cells, lambda c: R.cdf(family, c["w"], c["theta"]))
    own = F.array_min(F.transform(cells, lambda c: c["rank"]))
    rows = full.join(F.broadcast(primary.select("run", "rk", "rk1")), "run")
    high, low, near = E.f_max(cells), E.f_min(cells), E.min_theta(cells)
    rows = rows.select(
        each.alias("each"), E.inclusive_p(cells, family, "shared").alias("incl"), E.generic_p(cells, family).alias("generic"), high.alias("h"), low.alias("l"),
        R.cdf(family, high, near).alias("ph"), R.cdf(family, low, near).alias("ps"), R.cdf(family, high, F.when(own < F.col("rk1"), F.col("rk1")).otherwise(F.col("rk"))).alias("pt"),
    ).withColumn("pl", F.array_min("each"))
    v = {"h": key_variance(F.col("h"), F.col("ph")), "l": key_variance(F.col("l"), F.col("pl")), "t": key_variance(F.col("h"), F.col("pt")), "c": key_variance(F.col("h"), F.col("incl")), "r": key_variance(F.col("h") - F.col("l"), F.col("incl"))}
    rows = rows.select("*", *[x.alias(f"v{n}") for n, x in v.items()], l1_variance(F.col("h"), F.col("l"), F.col("ph"), F.col("pl")).alias("vd"))
    above = lambda a, b: F.count_if(a > b + 1e-9 * (1 + F.abs(b)))
    return rows.agg(
        F.count_if(F.exists("each", lambda p: p > F.col("incl") + eps)).alias("plain_above_inclusive"),
        F.count_if(F.col("generic") > F.col("incl") + eps).alias("generic_above_inclusive"),
        F.count_if(F.col("ps") > F.col("pl") + eps).alias("s_above_l"),
        F.count_if(F.col("ps") > F.col("ph") + eps).alias("min_above_max"),
        above(F.col("vh"), F.col("vt")).alias("max_above_primary"),
        above(F.col("vc"), F.col("vh")).alias("colocated_above_dispersed"),
        above(F.col("vr"), F.col("vc")).alias("colocated_l1_above_max"),
        above(F.col("vd"), F.col("vh") + F.col("vl")).alias("l1_above_sum"),
        F.count_if((F.col("l") > 0) & (F.col("l") / F.col("pl") > F.col("h") / F.col("ph") * (1 + 1e-9))).alias("l1_negative"),
    )
