"""Unbiased estimates from samples: each counted key gets ``adjusted = f / p``.

All estimators share one intermediate form, *cells*: for each sampled key an array with a cell for each
assignment (b, w, rank, seed, inn, theta).  ``inn`` says whether the key is in that assignment's sample;
``theta`` is the threshold it had to beat, the k-th smallest rank among the *other* keys, which is
constant over the draws of this key alone.  The functions that decide whether a key counts, and
with what probability, are column expressions over cells; they serve samples and full data alike.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seedrank.functions import ranks as R
from seedrank.functions import seeds
from seedrank.operators.sketch import Sketch

INF = R.INFINITY


#: Keys of a sample of fixed size at most: its estimator compares all pairs of them.
FIXED_BUDGET = 5000


class NoEstimator(ValueError):
    """The quantity has no unbiased non-negative estimator from such a sample."""


# ---------------------------------------------------------------- cells


def dispersed_cells(sketch: Sketch, relevant: list[str]) -> DataFrame:
    """(run, key, cells) of the keys in any relevant sample; a weight is known only where sampled.

    Samples of other assignments say nothing here and are not read.
    """
    names = F.array(*[F.lit(b) for b in relevant])
    held = F.map_from_entries(F.collect_list(F.struct(F.col("assignment"), F.struct("weight", "rank", "seed"))))
    thresholds = F.struct(F.col("assignment"), F.struct("rk", "rk1"))
    if sketch.shape == "bottom_k":
        # entries know their thresholds: a window over the sample shows each row those of all assignments
        rows = sketch.entries.where(F.col("assignment").isin(relevant))
        rows = rows.withColumn("th", F.collect_set(thresholds).over(Window.partitionBy("run"))).where("member")
        rows = rows.groupBy("run", "key").agg(held.alias("m"), F.map_from_entries(F.any_value("th")).alias("th"))
    else:
        mine = sketch.members(relevant).groupBy("run", "key").agg(held.alias("m"))
        meta = sketch.meta.where(F.col("assignment").isin(relevant)).groupBy("run").agg(F.map_from_entries(F.collect_list(thresholds)).alias("th"))
        rows = mine.join(F.broadcast(meta), "run")

    def cell(b: Column) -> Column:
        inn = F.col("m")[b].isNotNull()
        theta = F.when(inn, F.col("th")[b]["rk1"]).otherwise(F.col("th")[b]["rk"])
        return F.struct(
            b.alias("b"),
            F.coalesce(F.col("m")[b]["weight"], F.lit(0.0)).alias("w"),
            F.coalesce(F.col("m")[b]["rank"], F.lit(INF)).alias("rank"),
            F.col("m")[b]["seed"].alias("seed"),
            inn.alias("inn"),
            F.coalesce(theta, F.lit(INF)).alias("theta"),
        )

    return rows.select("run", "key", F.transform(names, cell).alias("cells"))


def full_cells(ranked: DataFrame, meta: DataFrame, relevant: list[str]) -> DataFrame:
    """Cells of every key of a ranked wide table: all weights known, ``inn`` by comparison with ``rk1``.

    The colocated summary is the part of it with any ``inn``; variances use all of it.
    """
    th = meta.where(F.col("assignment").isin(relevant)).groupBy("run").agg(F.map_from_entries(F.collect_list(F.struct("assignment", F.struct("rk", "rk1")))).alias("th"))
    own = F.map_from_entries(F.transform("cells", lambda c: F.struct(c["b"], F.struct(c["w"].alias("w"), c["rank"].alias("rank"), c["seed"].alias("seed")))))
    rows = ranked.withColumn("m", own).join(F.broadcast(th), "run")

    def cell(b: Column) -> Column:
        rank = F.coalesce(F.col("m")[b]["rank"], F.lit(INF))
        rk, rk1 = F.coalesce(F.col("th")[b]["rk"], F.lit(INF)), F.coalesce(F.col("th")[b]["rk1"], F.lit(INF))
        inn = rank < rk1
        return F.struct(
            b.alias("b"), F.coalesce(F.col("m")[b]["w"], F.lit(0.0)).alias("w"), rank.alias("rank"), F.col("m")[b]["seed"].alias("seed"), inn.alias("inn"), F.when(inn, rk1).otherwise(rk).alias("theta")
        )

    names = F.array(*[F.lit(b) for b in relevant])
    keep = [c for c in ranked.columns if c not in ("cells",)]
    return rows.select(*keep, F.transform(names, cell).alias("cells"))


def colocated_summary(ranked: DataFrame, sketch: Sketch, names: list[str]) -> DataFrame:
    """Cells, with whole weight vectors, of the keys that any assignment's sample holds.

    ``ranked`` is compared with broadcast thresholds; no key of the data is joined or shuffled.
    """
    return full_cells(ranked, sketch.meta, names).where(F.exists("cells", lambda c: c["inn"]))


# ---------------------------------------------------------------- expressions over cells


def _product(values: Column) -> Column:
    return F.aggregate(values, F.lit(1.0), lambda a, x: a * x)


def _restrict(cells: Column, relevant: list[str] | None) -> Column:
    return cells if relevant is None else F.filter(cells, lambda c: c["b"].isin(relevant))


def _by_weight(cells: Column) -> Column:
    """Cells from the heaviest down; equal weights by name."""
    keyed = F.transform(cells, lambda c: F.struct((-c["w"]).alias("minus"), c["b"].alias("b"), c.alias("c")))
    return F.transform(F.array_sort(keyed), lambda k: k["c"])


def top_weights(cells: Column, ell: int) -> Column:
    return F.transform(F.slice(_by_weight(cells), 1, ell), lambda c: c["w"])


def top_assignments(cells: Column, ell: int) -> Column:
    return F.transform(F.slice(_by_weight(cells), 1, ell), lambda c: c["b"])


def lth_weight(cells: Column, ell: int) -> Column:
    return F.element_at(_by_weight(cells), ell)["w"]


def min_theta(cells: Column) -> Column:
    return F.array_min(F.transform(cells, lambda c: c["theta"]))


def s_set_counts(cells: Column, ell: int) -> Column:
    """At least ``ell`` ranks are below the least threshold of all."""
    return F.size(F.filter(cells, lambda c: c["rank"] < min_theta(cells))) >= ell


def s_set_p(cells: Column, ell: int, family: str, joint: str) -> Column:
    if joint == "independent":  # only for ell = number of assignments
        return _product(F.transform(cells, lambda c: R.cdf(family, c["w"], min_theta(cells))))
    return R.cdf(family, lth_weight(cells, ell), min_theta(cells))


def l_set_counts(cells: Column, ell: int, m: int, family: str, seed_of: Callable[[Column], Column]) -> Column:
    """The ``ell`` heaviest are sampled, and the seeds rule out that any other assignment is heavier."""
    sampled = F.filter(cells, lambda c: c["inn"])
    enough = F.size(sampled) >= ell
    if ell == m:
        return enough
    bar, top = lth_weight(sampled, ell), top_assignments(sampled, ell)
    bounded = F.forall(cells, lambda c: F.array_contains(top, c["b"]) | (seed_of(c) < R.cdf(family, bar, c["theta"])))
    return enough & bounded


def l_set_p(cells: Column, ell: int, family: str, joint: str) -> Column:
    """Probability that the heaviest ``ell`` beat their thresholds and the others' seeds theirs."""
    bar, top = lth_weight(cells, ell), top_assignments(cells, ell)
    each = F.transform(cells, lambda c: R.cdf(family, F.when(F.array_contains(top, c["b"]), c["w"]).otherwise(bar), c["theta"]))
    return _product(each) if joint == "independent" else F.array_min(each)


def inclusive_p(cells: Column, family: str, joint: str) -> Column:
    """Probability that any assignment's sample takes the key."""
    each = F.transform(cells, lambda c: R.cdf(family, c["w"], c["theta"]))
    if joint == "shared":
        return F.array_max(each)
    if joint == "independent":
        return 1 - _product(F.transform(each, lambda x: 1 - x))
    # ascending weights; a gap's draw must beat the largest threshold from there on
    asc = F.reverse(_by_weight(cells))
    gaps = F.transform(asc, lambda c, i: (c["w"] - F.when(i > 0, F.get(asc, i - 1)["w"]).otherwise(0.0)) * F.array_max(F.transform(F.slice(asc, i + 1, F.size(asc)), lambda x: x["theta"])))
    # a gap of zero counts for nothing even where the threshold is infinite
    whole = F.aggregate(F.transform(gaps, lambda g: F.when(F.isnan(g), F.lit(0.0)).otherwise(g)), F.lit(0.0), lambda a, x: a + x)
    return -F.expm1(-whole)


def inclusive_p_by_events(cells: Column) -> Column:
    """The same for independent differences, as a sum over the first gap whose draw gets the key in."""
    asc = F.reverse(_by_weight(cells))
    reach = lambda i: F.array_max(F.transform(F.slice(asc, i + 1, F.size(asc)), lambda x: x["theta"]))
    hit = F.transform(asc, lambda c, i: R.cdf("exp", c["w"] - F.when(i > 0, F.get(asc, i - 1)["w"]).otherwise(0.0), reach(i)))
    start = F.struct(F.lit(0.0).alias("p"), F.lit(1.0).alias("none"))
    done = F.aggregate(hit, start, lambda a, h: F.struct((a["p"] + a["none"] * h).alias("p"), (a["none"] * (1 - h)).alias("none")))
    return done["p"]


def generic_counts(cells: Column) -> Column:
    return F.array_min(F.transform(cells, lambda c: c["rank"])) <= min_theta(cells)


def generic_p(cells: Column, family: str) -> Column:
    return R.cdf(family, lth_weight(cells, 1), min_theta(cells))


# ---------------------------------------------------------------- functions of a weight vector


def f_max(cells: Column) -> Column:
    return lth_weight(cells, 1)


def f_lth(ell: int) -> Callable[[Column], Column]:
    return lambda cells: lth_weight(cells, ell)


def f_min(cells: Column) -> Column:
    return F.array_min(F.transform(cells, lambda c: c["w"]))


def f_l1(cells: Column) -> Column:
    return f_max(cells) - f_min(cells)


def f_single(b: str) -> Callable[[Column], Column]:
    return lambda cells: F.coalesce(F.element_at(F.filter(cells, lambda c: c["b"] == b), 1)["w"], F.lit(0.0))


# ---------------------------------------------------------------- estimators


def template(rows: DataFrame, counts: Column, f: Column, p: Column, d: Column | None = None) -> DataFrame:
    """(run, key, f, p, adjusted, ...) of the keys that count and satisfy ``d``: the general form.

    ``p`` must be the probability that the key counts, given the ranks of all others.
    """
    keep = [c for c in rows.columns if c not in ("cells", "m", "th", "f", "p", "adjusted")]
    out = rows.where(counts).withColumn("f", f.cast("double")).withColumn("p", p)
    if d is not None:
        out = out.where(d)
    return out.where(F.col("f") != 0).select(*keep, "f", "p", (F.col("f") / F.col("p")).alias("adjusted"))


def check_support(vectors: DataFrame, f: Column) -> int:
    """Keys with a positive ``f`` and no positive weight: they could never be sampled."""
    return vectors.where((f > 0) & ~F.exists(F.map_values("weights"), lambda w: w > 0)).count()


def plain(sketch: Sketch, assignment: str) -> DataFrame:
    """One assignment's weights from its own sample (rank conditioning, or inverse probability for Poisson)."""
    rows = sketch.members([assignment])
    if "rk1" not in rows.columns:
        rows = rows.join(F.broadcast(sketch.meta.where(F.col("assignment") == assignment).select("run", "rk1")), "run")
    p = R.cdf(sketch.family, F.col("weight"), F.col("rk1"))
    return template(rows, F.lit(True), F.col("weight"), p).drop("pos", "member", "rank", "seed", "rk", "rk1", "weight")


def secondary(adjusted: DataFrame, h: Column) -> DataFrame:
    """Adjusted values of another per-key number ``h`` that is positive only where ``f`` is."""
    return adjusted.withColumn("adjusted", F.col("adjusted") * h / F.col("f")).withColumn("f", h)


def _check_top(sketch: Sketch, ell: int, m: int, kind: str) -> None:
    if ell < m and sketch.joint == "independent" and (kind == "s" or not sketch.known_seeds):
        raise NoEstimator("from independent samples only the minimum has an estimator, unless seeds are known (l-set)")
    if kind == "l" and sketch.joint == "inddiff":
        raise NoEstimator("the l-set has a closed form for shared seeds and for independent ranks only")
    if kind == "l" and ell < m and not sketch.known_seeds:
        raise NoEstimator("the l-set needs the seeds of unsampled weights")


def _check_function(f) -> None:
    if f is f_l1:
        raise NoEstimator("the range is no function of the heaviest weights alone; l1 takes it as a difference")


def s_set(sketch: Sketch, relevant: list[str], ell: int, f: Callable[[Column], Column] | None = None, d: Callable[[Column], Column] | None = None) -> DataFrame:
    """A function of the ``ell`` heaviest weights, counted where all of them beat the least threshold."""
    m = len(relevant)
    _check_function(f)
    _check_top(sketch, ell, m, "s")
    rows, cells = dispersed_cells(sketch, relevant), F.col("cells")
    value = (f or f_lth(ell))(cells)
    return template(rows, s_set_counts(cells, ell), value, s_set_p(cells, ell, sketch.family, sketch.joint), None if d is None else d(cells))


def l_set(sketch: Sketch, relevant: list[str], ell: int, f: Callable[[Column], Column] | None = None, d: Callable[[Column], Column] | None = None) -> DataFrame:
    """The same, counted wherever the sample determines the ``ell`` heaviest weights: the most inclusive choice."""
    m = len(relevant)
    _check_function(f)
    _check_top(sketch, ell, m, "l")
    rows, cells = dispersed_cells(sketch, relevant), F.col("cells")
    if sketch.joint == "shared":
        rows = rows.withColumn("u", F.array_max(F.transform("cells", lambda c: c["seed"])))
        seed_of = lambda c: F.col("u")
    else:  # hashed seeds are known for unsampled weights as well
        seed_of = lambda c: seeds.pair_seed(F.col("key"), c["b"], seeds.salted(sketch.salt, F.col("run")))
    value = (f or f_lth(ell))(F.filter(cells, lambda c: c["inn"]) if ell < m else cells)
    out = template(rows, l_set_counts(cells, ell, m, sketch.family, seed_of), value, l_set_p(cells, ell, sketch.family, sketch.joint), None if d is None else d(cells))
    return out.drop("u")


def maximum(sketch: Sketch, relevant: list[str], d=None) -> DataFrame:
    return s_set(sketch, relevant, 1, d=d)


def minimum(sketch: Sketch, relevant: list[str], kind: str = "l", d=None) -> DataFrame:
    return (l_set if kind == "l" else s_set)(sketch, relevant, len(relevant), d=d)


def lth_largest(sketch: Sketch, relevant: list[str], ell: int, kind: str = "l") -> DataFrame:
    return (l_set if kind == "l" else s_set)(sketch, relevant, ell)


def median(sketch: Sketch, relevant: list[str], kind: str = "l") -> DataFrame:
    if len(relevant) % 2 == 0:
        raise ValueError("a median weight needs an odd number of assignments")
    return lth_largest(sketch, relevant, (len(relevant) + 1) // 2, kind)


def l1(sketch: Sketch, relevant: list[str], kind: str = "l") -> DataFrame:
    """(run, key, adjusted): the greatest less the least weight, as the difference of both estimates.

    Both are taken from the same cells, in one pass over the sample.
    """
    m = len(relevant)
    _check_top(sketch, 1, m, "s")
    _check_top(sketch, m, m, kind)
    rows, cells = dispersed_cells(sketch, relevant), F.col("cells")
    high = F.when(s_set_counts(cells, 1), f_max(cells) / s_set_p(cells, 1, sketch.family, sketch.joint))
    if kind == "l":
        counted, p = F.forall(cells, lambda c: c["inn"]), l_set_p(cells, m, sketch.family, sketch.joint)
    else:
        counted, p = s_set_counts(cells, m), s_set_p(cells, m, sketch.family, sketch.joint)
    low = F.when(counted & (f_min(cells) > 0), f_min(cells) / p)
    both = rows.select("run", "key", high.alias("high"), low.alias("low")).where(F.col("high").isNotNull() | F.col("low").isNotNull())
    return both.select("run", "key", (F.coalesce("high", F.lit(0.0)) - F.coalesce("low", F.lit(0.0))).alias("adjusted"))


def inclusive(summary: DataFrame, f: Callable[[Column], Column], family: str = "ipps", joint: str = "shared", d: Callable[[Column], Column] | None = None) -> DataFrame:
    """Any function of the whole vector from a colocated summary; every sample's keys count."""
    cells = F.col("cells")
    return template(summary, F.lit(True), f(cells), inclusive_p(cells, family, joint), None if d is None else d(cells))


def generic_consistent(summary: DataFrame, f: Callable[[Column], Column], family: str, relevant: list[str]) -> DataFrame:
    """For any consistent ranks: counted where the least rank beats the least threshold."""
    rows = summary.withColumn("cells", _restrict(F.col("cells"), relevant))
    cells = F.col("cells")
    return template(rows, generic_counts(cells), f(cells), generic_p(cells, family))


def inclusive_fixed(ranked: DataFrame, sketch: Sketch, names: list[str], k: int, f: Callable[[Column], Column]) -> DataFrame:
    """The inclusive estimator for a sample with a fixed number of distinct keys.

    The common size l depends on the key itself, so its thresholds would bias the estimate.  In their
    place stands l1: the largest size at which the union over the *other* keys stays below the budget.
    """
    budget = len(names) * k
    if budget > FIXED_BUDGET:
        raise ValueError(f"a sample of more than {FIXED_BUDGET} keys; the places of all others are compared for each of them")
    rows = sketch.entries.select("run", "assignment", "key", "rank", "pos")
    keys = rows.where(F.col("pos") <= F.lit(budget)).select("run", "key").distinct()
    mine = rows.select("run", F.col("key").alias("me"), "assignment", F.col("pos").alias("at"))
    others = rows.select("run", "assignment", F.col("key").alias("other"), "pos")
    # the places of the others once this key is taken out; samples only, a few hundred rows each way
    grid = keys.select("run", F.col("key").alias("me")).join(others, "run").where("me <> other")
    grid = grid.join(mine, ["run", "assignment", "me"], "left")
    moved = grid.withColumn("pos", F.col("pos") - F.when(F.col("at") < F.col("pos"), 1).otherwise(0))
    best = moved.groupBy("run", "me", "other").agg(F.min("pos").alias("best"))
    counts = best.groupBy("run", "me").agg(F.array_sort(F.collect_list("best")).alias("places"))
    # the largest size whose count of places stays within budget - 1
    limit = F.when(F.size("places") <= budget - 1, F.lit(budget)).otherwise(F.get("places", F.lit(budget - 1)) - 1)
    size = counts.select("run", F.col("me").alias("key"), limit.alias("l1"))
    at = rows.groupBy("run", "assignment").agg(F.map_from_entries(F.collect_list(F.struct("pos", "rank"))).alias("by_pos"))
    places = rows.groupBy("run", "key").agg(F.map_from_entries(F.collect_list(F.struct("assignment", "pos"))).alias("place"))
    th = at.groupBy("run").agg(F.map_from_entries(F.collect_list(F.struct("assignment", "by_pos"))).alias("th"))
    local = ranked.join(F.broadcast(places), ["run", "key"]).join(F.broadcast(size), ["run", "key"]).join(F.broadcast(th), "run")
    own = F.map_from_entries(F.transform("cells", lambda c: F.struct(c["b"], c["w"])))
    local = local.withColumn("m", own)

    def cell(b: Column) -> Column:
        pos = F.coalesce(F.col("place")[b], F.lit(2**30))
        theta = F.coalesce(F.col("th")[b][F.when(pos > F.col("l1"), F.col("l1")).otherwise(F.col("l1") + 1)], F.lit(INF))
        return F.struct(b.alias("b"), F.coalesce(F.col("m")[b], F.lit(0.0)).alias("w"), (pos <= F.col("l1")).alias("inn"), theta.alias("theta"))

    names_ = F.array(*[F.lit(b) for b in names])
    summary = local.select("run", "key", F.transform(names_, cell).alias("cells")).where(F.exists("cells", lambda c: c["inn"]))
    return inclusive(summary, f, sketch.family, sketch.joint)


# ---------------------------------------------------------------- k-mins


def kmins_total(kmins: DataFrame, k: int) -> DataFrame:
    """(assignment, total): sums of all weights from exponential k-mins."""
    return kmins.groupBy("assignment").agg((F.lit(k - 1) / F.sum("rank")).alias("total"))


def jaccard_kmins(kmins: DataFrame, a: str, b: str) -> DataFrame:
    """Share of draws in which two assignments have the same least rank *value* (independent differences)."""
    wide = kmins.where(F.col("assignment").isin(a, b)).groupBy("t").agg(F.max(F.when(F.col("assignment") == a, F.col("rank"))).alias("ra"), F.max(F.when(F.col("assignment") == b, F.col("rank"))).alias("rb"))
    return wide.agg(F.avg(F.when(F.col("ra") == F.col("rb"), 1.0).otherwise(0.0)).alias("jaccard"))


def jaccard_all_pairs(kmins: DataFrame, k: int) -> DataFrame:
    """(a, b, jaccard) of every pair that shares a least rank in some of k draws: one equi-join on draw and value."""
    left = kmins.select("t", "rank", F.col("assignment").alias("a"))
    right = kmins.select("t", "rank", F.col("assignment").alias("b"))
    return left.join(right, ["t", "rank"]).where("a < b").groupBy("a", "b").agg((F.count(F.lit(1)) / k).alias("jaccard"))


def jaccard_all_pairs_collapsed(kmins: DataFrame, k: int) -> DataFrame:
    """``jaccard_all_pairs`` where many assignments are equal: those of equal least ranks are paired as one."""
    drawn = F.array_sort(F.collect_list(F.struct("t", "rank")))
    member = kmins.groupBy("assignment").agg(F.xxhash64(drawn).alias("h1"), F.xxhash64(F.lit("second"), drawn).alias("h2"))
    groups = member.groupBy("h1", "h2").agg(F.min("assignment").alias("rep"), F.collect_list("assignment").alias("members"))
    one = groups.select("rep", "members")
    apart = jaccard_all_pairs(kmins.join(one.select(F.col("rep").alias("assignment")), "assignment", "left_semi"), k)
    left, right = one.select(F.col("rep").alias("a"), F.col("members").alias("xs")), one.select(F.col("rep").alias("b"), F.col("members").alias("ys"))
    across = apart.join(left, "a").join(right, "b").select("jaccard", F.explode("xs").alias("x"), "ys").select("jaccard", "x", F.explode("ys").alias("y"))
    equal = one.where(F.size("members") > 1).select(F.lit(1.0).alias("jaccard"), F.explode("members").alias("x"), "members").select("jaccard", "x", F.explode("members").alias("y")).where("x < y")
    return across.unionByName(equal).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "jaccard")


# ---------------------------------------------------------------- sums


def total(adjusted: DataFrame, d: Column | None = None, by: list[str] | None = None) -> DataFrame:
    """Sum over the sampled keys that satisfy ``d``, for each run and group."""
    rows = adjusted if d is None else adjusted.where(d)
    return rows.groupBy("run", *(by or [])).agg(F.sum("adjusted").alias("estimate"))


def jaccard_ratio(sketch: Sketch, relevant: list[str], kind: str = "l") -> DataFrame:
    """Estimated sum of minima over estimated sum of maxima (consistent, not unbiased)."""
    low = total(minimum(sketch, relevant, kind)).withColumnRenamed("estimate", "low")
    high = total(maximum(sketch, relevant)).withColumnRenamed("estimate", "high")
    return high.join(low, "run", "left").select("run", (F.coalesce("low", F.lit(0.0)) / F.col("high")).alias("jaccard"))


def std_error(adjusted: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Estimate and standard error from the sample alone: f^2 (1-p) / p^2 is unbiased for a key's variance."""
    v = F.col("f") ** 2 * (1 - F.col("p")) / F.col("p") ** 2
    return adjusted.groupBy("run", *(by or [])).agg(F.sum("adjusted").alias("estimate"), F.sqrt(F.sum(v)).alias("std_error"))


def linear_combination(parts: list[tuple[float, DataFrame]]) -> DataFrame:
    """A sum of functions, each estimated by itself; unbiased, though one template may not cover the sum."""
    rows = None
    for c, part in parts:
        scaled = part.select("run", "key", (F.lit(float(c)) * F.col("adjusted")).alias("adjusted"))
        rows = scaled if rows is None else rows.unionByName(scaled)
    return rows.groupBy("run", "key").agg(F.sum("adjusted").alias("adjusted"))
