"""Samples: bottom-k, Poisson and k-mins, their unions, merges and sizes.

A sketch is two small tables.  ``entries`` has the sampled (run, assignment, key, weight, seed, rank, pos);
``meta`` has for each (run, assignment) the thresholds ``rk`` and ``rk1`` (the k-th and the next smallest rank,
or the Poisson threshold in both; infinite where there are fewer keys).  Entries of bottom-k samples carry
their thresholds as well, so that estimates need one pass over the data and no join.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seedrank.functions import ranks as R

GROUP = ["run", "assignment"]
INF = R.INFINITY


class IncompatibleSketches(ValueError):
    """Sketches of unlike design or salt cannot be combined."""


@dataclass(frozen=True)
class Sketch:
    entries: DataFrame
    meta: DataFrame
    k: object
    shape: str = "bottom_k"
    family: str = "ipps"
    joint: str = "shared"
    salt: str = "v1"
    known_seeds: bool = True

    def members(self, relevant: list[str] | None = None) -> DataFrame:
        """Sampled rows, without the one kept for the next threshold."""
        rows = self.entries.where("member")
        return rows if relevant is None else rows.where(F.col("assignment").isin(relevant))

    def design(self) -> tuple:
        return self.shape, self.family, self.joint, self.salt


def _size(k) -> tuple[int, Column]:
    """The greatest sample size, and that of a row's assignment."""
    if isinstance(k, dict):
        table = F.create_map(*[x for b, n in k.items() for x in (F.lit(b), F.lit(n))])
        return max(k.values()), table[F.col("assignment")]
    return k, F.lit(k)


#: Parts that the rows of one group are dealt to where Spark does not prune a window by its limit.
SPREAD = 64


def _pruned(rows: DataFrame, n: int) -> bool:
    """Whether Spark keeps the first ``n`` rows of each group in every partition before it shuffles."""
    return n <= int(rows.sparkSession.conf.get("spark.sql.optimizer.windowGroupLimitThreshold", "1000"))


def first_rows(rows: DataFrame, group: list[str], order: list, n: int, name: str = "pos") -> DataFrame:
    """``rows`` of the ``n`` first places of each group, with the place as ``name``.

    Up to the limit of Spark's pruning a window limit does it.  Beyond it the rows of a group are
    dealt by key to ``SPREAD`` parts, each part keeps its ``n`` first, and only those meet in one task.
    """
    if not _pruned(rows, n):
        part = F.pmod(F.xxhash64("key"), F.lit(SPREAD))
        rows = rows.withColumn("part_", part)
        inside = F.row_number().over(Window.partitionBy(*group, "part_").orderBy(*order))
        rows = rows.withColumn("inside_", inside).where(F.col("inside_") <= n).drop("part_", "inside_")
    return rows.withColumn(name, F.row_number().over(Window.partitionBy(*group).orderBy(*order))).where(F.col(name) <= n)


def prefilter(ranked: DataFrame, k: int, slack: int = 4) -> DataFrame:
    """``ranked`` without the rows that cannot be among the k+1 smallest ranks of their assignment.

    A Poisson sample of ``slack * (k + 1)`` expected keys holds the k+1 smallest ranks whenever it has
    that many rows, which is checked; assignments that fail it are left whole.  What reaches the sort
    and the shuffle is then in proportion to k and not to the keys.
    """
    totals = ranked.groupBy(*GROUP).agg(F.sum("weight").alias("total"))
    loose = ranked.join(F.broadcast(totals), GROUP).where(F.col("rank") * F.col("total") < slack * (k + 1))
    enough = loose.groupBy(*GROUP).agg(F.count(F.lit(1)).alias("kept"))
    bounds = totals.join(enough, GROUP, "left").select(*GROUP, F.when(F.coalesce("kept", F.lit(0)) > k, slack * (k + 1) / F.col("total")).otherwise(F.lit(INF)).alias("bound"))
    return ranked.join(F.broadcast(bounds), GROUP).where(F.col("rank") < F.col("bound")).drop("bound")


def bottom_k(ranked: DataFrame, k, family: str = "ipps", joint: str = "shared", salt: str = "v1", known_seeds: bool = True, early: bool | None = None) -> Sketch:
    """The k smallest ranks of each assignment (``k``: a number, or a map from assignment to number).

    ``early`` puts the threshold prefilter in front; without it the window limit prunes each partition.
    Left open, it stands for sizes that the window limit does not serve, so that what is shuffled and
    sorted is in proportion to k at any size.
    """
    most, own = _size(k)
    if early is None:
        early = not _pruned(ranked, most + 1)
    rows = prefilter(ranked, most) if early else ranked
    rows = first_rows(rows, GROUP, ["rank", "key"], most + 1).where(F.col("pos") <= own + 1)
    entries = rows.withColumn("member", F.col("pos") <= own)
    group = Window.partitionBy(*GROUP)
    at = lambda n: F.coalesce(F.max(F.when(F.col("pos") == n, F.col("rank"))).over(group), F.lit(INF))
    entries = entries.withColumn("rk", at(own)).withColumn("rk1", at(own + 1))
    return Sketch(entries, _meta(entries, own), k, "bottom_k", family, joint, salt, known_seeds)


#: Columns that sampling adds to ranked rows.
SAMPLED = ("pos", "member", "rk", "rk1")


def _meta(entries: DataFrame, own: Column) -> DataFrame:
    at = lambda n: F.coalesce(F.max(F.when(F.col("pos") == n, F.col("rank"))), F.lit(INF))
    return entries.groupBy(*GROUP).agg(at(own).alias("rk"), at(own + 1).alias("rk1"), F.count_if("member").alias("size"))


def poisson(ranked: DataFrame, tau: DataFrame, k=None, family: str = "ipps", joint: str = "shared", salt: str = "v1") -> Sketch:
    """Every key whose rank is below its assignment's threshold; ``tau``: assignment, tau."""
    on = [c for c in GROUP if c in tau.columns]
    rows = ranked.join(F.broadcast(tau), on).where(F.col("rank") < F.col("tau"))
    entries = rows.drop("tau").withColumn("pos", F.lit(None).cast("int")).withColumn("member", F.lit(True))
    runs = ranked.select("run").distinct() if "run" not in tau.columns else None
    meta = tau if runs is None else runs.crossJoin(F.broadcast(tau))
    return Sketch(entries, meta.select(*GROUP, F.col("tau").alias("rk"), F.col("tau").alias("rk1")), k, "poisson", family, joint, salt)


def ipps_tau(weights: DataFrame, k: int) -> DataFrame:
    """(assignment, tau) with k expected keys, exactly, for ``ipps`` ranks.

    At most k keys can have probability one, and they are the heaviest; so the k heaviest and the sum
    of all weights settle the threshold.  Infinite where there are no more than k keys.
    """
    positive = weights.where(F.col("weight") > 0)
    total = positive.groupBy("assignment").agg(F.sum(F.col("weight").cast("double")).alias("total"), F.count(F.lit(1)).alias("n"))
    top = first_rows(positive.select("assignment", "weight", "key"), ["assignment"], [F.col("weight").desc(), "key"], k, "j")
    run = Window.partitionBy("assignment").orderBy("j")
    # with the j-1 heaviest certain, the rest share k-j+1
    step = top.join(F.broadcast(total), "assignment").withColumn("rest", F.col("total") - F.sum(F.col("weight").cast("double")).over(run) + F.col("weight"))
    step = step.withColumn("tau", (k - F.col("j") + 1) / F.col("rest")).where(F.col("weight") * F.col("tau") <= 1)
    found = step.groupBy("assignment").agg(F.min_by("tau", "j").alias("tau"))
    return total.join(found, "assignment", "left").select("assignment", F.when(F.col("n") <= k, F.lit(INF)).otherwise(F.col("tau")).alias("tau"))


def solve_tau(weights: DataFrame, k: int, family: str = "ipps", rounds: int = 9, ways: int = 64) -> dict[str, float]:
    """Thresholds with k expected keys by a search that narrows ``ways``-fold with each pass."""
    positive = weights.where(F.col("weight") > 0).withColumn("weight", F.col("weight").cast("double"))
    start = positive.groupBy("assignment").agg(F.sum("weight").alias("s"), F.min("weight").alias("least"), F.count(F.lit(1)).alias("n")).collect()
    out = {r["assignment"]: INF for r in start if r["n"] <= k}
    spans = {r["assignment"]: (k / r["s"], max(1.0, 40.0 if family == "exp" else 1.0) / r["least"]) for r in start if r["n"] > k}
    for _ in range(rounds if spans else 0):
        grid = {b: [lo + (hi - lo) * j / ways for j in range(ways + 1)] for b, (lo, hi) in spans.items()}
        table = F.create_map(*[x for b, g in grid.items() for x in (F.lit(b), F.array(*[F.lit(v) for v in g]))])
        rows = positive.where(F.col("assignment").isin(list(grid))).withColumn("grid", table[F.col("assignment")])
        sums = rows.groupBy("assignment").agg(*[F.sum(R.cdf(family, F.col("weight"), F.col("grid")[j])).alias(f"p{j}") for j in range(ways + 1)]).collect()
        for r in sums:
            j = max([0, *(j for j in range(ways) if r[f"p{j}"] <= k)])
            spans[r["assignment"]] = (grid[r["assignment"]][j], grid[r["assignment"]][j + 1])
    return out | {b: (lo + hi) / 2 for b, (lo, hi) in spans.items()}


def k_mins(vectors: DataFrame, k: int, family: str = "exp", joint: str = "shared", salt: str = "v1", algo: str = "md5") -> DataFrame:
    """(assignment, t, rank, key, weight): the least rank of each assignment in each of k draws.

    ``vectors`` is wide.  Each key draws its k ranks; only k minima an assignment leave a partition.
    """
    R.check_design(family, joint)
    from seedrank.functions import seeds

    rows = vectors.withColumn("w", F.map_filter("weights", lambda b, w: w > 0)).where(F.size("w") > 0)
    rows = rows.select("key", "w", F.explode(F.sequence(F.lit(1), F.lit(k))).alias("t"))
    salt_t = F.concat_ws("#", F.lit(salt), F.col("t").cast("string"))
    if joint == "inddiff":
        drawn = R._independent_differences(rows.withColumn("run", F.col("t")), salt_t, algo)
    else:
        seed = (lambda b: seeds.draw_seed(F.col("key"), F.col("t"), salt, algo)) if joint == "shared" else (lambda b: seeds.pair_seed(F.col("key"), b, salt_t, algo))
        cells = F.transform(F.map_entries("w"), lambda e: F.struct(e["key"].alias("b"), e["value"].cast("double").alias("w"), R.rank(family, e["value"].cast("double"), seed(e["key"])).alias("rank")))
        drawn = rows.select("key", "t", cells.alias("cells"))
    flat = drawn.select("key", "t", F.explode("cells").alias("c"))
    least = F.min(F.struct(F.col("c.rank").alias("rank"), F.col("key").alias("key"), F.col("c.w").alias("weight")))
    return flat.groupBy(F.col("c.b").alias("assignment"), "t").agg(least.alias("m")).select("assignment", "t", "m.rank", "m.key", "m.weight")


def k_mins_of_long(weights: DataFrame, k: int, salt: str = "v1", algo: str = "md5") -> DataFrame:
    """``k_mins`` of the joint ``inddiff`` from long weights, for assignments too many for a key's map.

    Assignments that give a key the same weight have the same rank of it, so each (key, weight) draws
    its ranks once, and no row holds all assignments of a key.
    """
    from seedrank.functions import seeds

    rows = weights.where(F.col("weight") > 0).select("assignment", "key", F.col("weight").cast("double").alias("weight"))
    ascending = Window.partitionBy("key").orderBy("weight")
    levels = rows.groupBy("key", "weight").agg(F.count(F.lit(1)).alias("n"))
    below = F.coalesce(F.sum("n").over(ascending.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    levels = levels.select("key", "weight", below.alias("level"), (F.col("weight") - F.coalesce(F.lag("weight").over(ascending), F.lit(0.0))).alias("gap"))
    draws = levels.withColumn("t", F.explode(F.sequence(F.lit(1), F.lit(k))))
    seed = seeds.gap_seed(F.col("key"), F.col("level"), F.concat_ws("#", F.lit(salt), F.col("t").cast("string")), algo)
    least = F.min(R.rank("exp", F.col("gap"), seed)).over(Window.partitionBy("key", "t").orderBy("weight"))
    drawn = draws.select("key", "weight", "t", least.alias("rank")).groupBy("key", "weight")
    ranks = drawn.agg(F.transform(F.array_sort(F.collect_list(F.struct("t", "rank"))), lambda x: x["rank"]).alias("ranks"))
    flat = rows.join(ranks, ["key", "weight"]).select("assignment", "key", "weight", F.posexplode("ranks").alias("t", "rank"))
    found = flat.groupBy("assignment", (F.col("t") + 1).alias("t")).agg(F.min(F.struct("rank", "key", "weight")).alias("m"))
    return found.select("assignment", "t", "m.rank", "m.key", "m.weight")


def max_union(sketch: Sketch, relevant: list[str], name: str = "max") -> Sketch:
    """The sketch of the greatest weight over ``relevant``, from the sketches of each (consistent ranks)."""
    if sketch.joint == "independent":
        raise IncompatibleSketches("the least of independent ranks is no rank of the greatest weight")
    if sketch.shape == "bottom_k":
        # each sketch keeps its k+1 smallest ranks, so the k+1 smallest of the union are among them
        rows = sketch.entries.where(F.col("assignment").isin(relevant))
    else:
        bound = sketch.meta.where(F.col("assignment").isin(relevant)).groupBy("run").agg(F.min("rk").alias("tau"))
        rows = sketch.members(relevant).join(F.broadcast(bound), "run").where(F.col("rank") < F.col("tau")).drop("tau")
    least = rows.groupBy("run", "key").agg(F.max("weight").alias("weight"), F.min_by("seed", "rank").alias("seed"), F.min("rank").alias("rank"))
    least = least.withColumn("assignment", F.lit(name)).select(*GROUP, "key", "weight", "seed", "rank")
    if sketch.shape == "bottom_k":
        return bottom_k(least, sketch.k, sketch.family, sketch.joint, sketch.salt)
    tau = bound.withColumn("assignment", F.lit(name))
    return poisson(least, tau, sketch.k, sketch.family, sketch.joint, sketch.salt)


def max_union_kmins(kmins: DataFrame, relevant: list[str], name: str = "max") -> DataFrame:
    rows = kmins.where(F.col("assignment").isin(relevant))
    least = F.min(F.struct("rank", "key", "weight"))
    return rows.groupBy("t").agg(least.alias("m")).select(F.lit(name).alias("assignment"), "t", "m.rank", "m.key", "m.weight")


def combine(*sketches: Sketch) -> Sketch:
    """One summary from sketches of different assignments, made by processes that never met."""
    first = sketches[0]
    if len({s.design() for s in sketches}) > 1:
        raise IncompatibleSketches("sketches differ in shape, ranks or salt")
    entries, meta = first.entries, first.meta
    for s in sketches[1:]:
        entries, meta = entries.unionByName(s.entries), meta.unionByName(s.meta, allowMissingColumns=True)
    return replace(first, entries=entries, meta=meta)


def merge(a: Sketch, b: Sketch) -> Sketch:
    """The bottom-k sketch of the union of two sets of disjoint keys, from the sketches of both."""
    if a.design() != b.design() or a.k != b.k or a.shape != "bottom_k":
        raise IncompatibleSketches("only bottom-k sketches of one design, size and salt merge")
    rows = a.entries.drop(*SAMPLED).unionByName(b.entries.drop(*SAMPLED))
    return bottom_k(rows, a.k, a.family, a.joint, a.salt, a.known_seeds)


def drop_seeds(sketch: Sketch) -> Sketch:
    """The same sample without its seeds, as if another process had drawn them and kept them."""
    return replace(sketch, entries=sketch.entries.withColumn("seed", F.lit(None).cast("double")), known_seeds=False)


def fixed_distinct(ranked: DataFrame, k: int, m: int, family: str = "ipps", joint: str = "shared", salt: str = "v1") -> Sketch:
    """Bottom-l sketches with the largest l for which their union has at most ``m * k`` keys.

    A key enters the union at its best place over the assignments; l follows from a running count of
    those places.  Entries go on to place l+1; ``k`` of the sketch is null and stands in ``meta`` as l.
    """
    budget = m * k
    base = bottom_k(ranked, budget, family, joint, salt).entries.drop("member", "rk", "rk1")
    best = base.groupBy("run", "key").agg(F.min("pos").alias("best"))
    counts = best.groupBy("run", "best").agg(F.count(F.lit(1)).alias("n"))
    running = counts.withColumn("upto", F.sum("n").over(Window.partitionBy("run").orderBy("best")))
    # the first place at which the count exceeds the budget; all sampled places count where none does
    over = running.groupBy("run").agg(F.min(F.when(F.col("upto") > budget, F.col("best"))).alias("over"), F.max("best").alias("most"))
    length = over.select("run", F.least(F.coalesce(F.col("over") - 1, F.col("most")), F.lit(budget)).alias("l"))
    rows = base.join(F.broadcast(length), "run")
    entries = rows.where(F.col("pos") <= F.col("l") + 1).withColumn("member", F.col("pos") <= F.col("l"))
    at = lambda n: F.coalesce(F.max(F.when(F.col("pos") == n, F.col("rank"))), F.lit(INF))
    meta = entries.groupBy(*GROUP).agg(at(F.col("l")).alias("rk"), at(F.col("l") + 1).alias("rk1"), F.count_if("member").alias("size"), F.max("l").alias("l"))
    return Sketch(entries.drop("l"), meta, None, "fixed_distinct", family, joint, salt)


def fixed_expected(vectors: DataFrame, k: int, names: list[str], family: str = "ipps", rounds: int = 40) -> tuple[float, dict[str, float]]:
    """A common size l and Poisson thresholds with ``m * k`` expected distinct keys (shared seeds).

    With ``tau_b`` proportional to l over the sum of b, a key is in the union with the greatest of its
    probabilities; l is found by bisection, in passes that try many values at once.
    """
    m, ways = len(names), 32
    cells = F.transform(F.array(*[F.lit(b) for b in names]), lambda b: F.coalesce(F.col("weights")[b], F.lit(0.0)))
    rows = vectors.select(cells.alias("w"))
    sums = rows.agg(*[F.sum(F.col("w")[j]).alias(f"s{j}") for j in range(m)]).first()
    keys = rows.where(F.array_max("w") > 0).count()
    if keys <= m * k:
        return float("inf"), dict.fromkeys(names, INF)
    lo, hi = 0.0, float(m * k)
    while True:  # past the cap of probabilities the union may need more than m * k
        if _union_sizes(rows, [hi], sums, family)[0] >= m * k:
            break
        hi *= 4
    for _ in range(max(1, rounds // 5)):
        grid = [lo + (hi - lo) * j / ways for j in range(ways + 1)]
        sizes = _union_sizes(rows, grid, sums, family)
        j = max([0, *(j for j in range(ways) if sizes[j] <= m * k)])
        lo, hi = grid[j], grid[j + 1]
    return lo, {b: lo / sums[j] for j, b in enumerate(names)}


def _union_sizes(rows: DataFrame, grid: list[float], sums, family: str) -> list[float]:
    m = len(sums)
    size = lambda l: F.sum(F.greatest(*[R.cdf(family, F.col("w")[j], F.lit(l / sums[j])) for j in range(m)], F.lit(0.0)))
    return list(rows.agg(*[size(l).alias(f"g{i}") for i, l in enumerate(grid)]).first())
