"""Accuracy and size of samples over a grid of sizes and many replications, in one pass over the keys.

Weights lie in flat columns, one for each assignment.  The seeds of all runs are drawn in one pass, which keeps the
keys that can be in a sample of the largest size; thresholds of all sizes and runs come from these and are a small
local table.  A key outside of a sample meets thresholds that do not depend on its rank, so such keys are counted by
their weights and each different vector of weights meets the thresholds once; sampled keys meet them one by one.
Every measure is a sum of column expressions.  Variances are conditional ones, given the ranks of the other keys.
"""

from __future__ import annotations

from functools import reduce
from operator import mul
from weakref import WeakKeyDictionary

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seedrank.functions import ranks as R
from seedrank.functions.draws import kept_draws
from seedrank.operators.metrics import key_variance, l1_variance
from seedrank.operators.sketch import first_rows
from seedrank.sources.store import small_tasks, staged

INF = R.INFINITY
#: Tables made of a table of weights, for the sweeps that need the same ones.
_made: WeakKeyDictionary = WeakKeyDictionary()


def _once(weights: DataFrame, what: tuple, make) -> DataFrame:
    known = _made.setdefault(weights, {})
    if what not in known:
        known[what] = staged(make())
    return known[what]


def flat(long: DataFrame, names: list[str]) -> DataFrame:
    """key, w0, w1, ...: the weights of the named assignments, zero where there is none."""
    rows = long.where(F.col("assignment").isin(names) & (F.col("weight") > 0))
    own = [F.coalesce(F.sum(F.when(F.col("assignment") == b, F.col("weight"))), F.lit(0)).cast("double").alias(f"w{i}") for i, b in enumerate(names)]
    return rows.groupBy("key").agg(*own)


def _most(columns: list[Column]) -> Column:
    return F.greatest(*columns) if len(columns) > 1 else columns[0]


def _least(columns: list[Column]) -> Column:
    return F.least(*columns) if len(columns) > 1 else columns[0]


class Sweep:
    """Samples of sizes ``ks`` in ``runs`` replications; ``weights``: a table of ``flat`` rows that can be read again.

    ``unit`` ranks every positive weight as if it were 1.
    """

    def __init__(self, weights: DataFrame, names: list[str], ks: list[int], family: str = "ipps", joint: str = "shared", runs: int = 25, unit: bool = False, salt: str = "v1"):
        R.check_design(family, joint, "dispersed")
        self.weights, self.names, self.ks, self.family, self.joint, self.runs, self.unit, self.salt = weights, names, sorted(ks), family, joint, runs, unit, salt
        self._thresholds, self._early = None, True

    def _w(self) -> list[str]:
        return [f"w{i}" for i in range(len(self.names))]

    def drawn(self, early: bool = True, slack: int = 4) -> DataFrame:
        """run, key, the weights and the ranks r0, r1, ... of the keys with a small rank in some assignment.

        ``early`` drops keys whose ranks are all larger than almost surely needed; see ``thresholds``.  Both families
        take the same seeds, and no exponential rank is below the seed over the weight, which the filter compares.
        """
        bounds = [INF] * len(self.names)
        if early:
            sums = self.weights.agg(*[F.sum(F.signum(c) if self.unit else F.col(c)).alias(c) for c in self._w()]).first()
            bounds = [slack * (self.ks[-1] + 1) / x if x else INF for x in sums]
        shared = self.joint == "shared"
        schema = "run int, key string, " + ", ".join(f"{c} double" for c in [*self._w(), *[f"u{i}" for i in range(len(self.names))]])
        run = kept_draws(self.names, self.salt, self.runs, shared, self.unit, bounds)
        with small_tasks(self.weights.sparkSession):
            rows = _once(self.weights, ("drawn", *self.names, self.salt, self.runs, shared, self.unit, *bounds), lambda: self.weights.select("key", *self._w()).mapInArrow(run, schema))
        rank = lambda i: R.rank(self.family, F.lit(1.0) if self.unit else F.col(f"w{i}"), F.col(f"u{i}"))
        return rows.select("run", "key", *self._w(), *[F.when(F.col(f"w{i}") > 0, rank(i)).otherwise(F.lit(INF)).alias(f"r{i}") for i in range(len(self.names))])

    def entries(self, early: bool = True) -> DataFrame:
        """run, a (number of the assignment), key, rank, pos: the smallest ranks, one more than the largest size."""
        cells = F.array(*[F.struct(F.lit(i).alias("a"), F.col(f"r{i}").alias("rank")) for i in range(len(self.names))])
        rows = self.drawn(early).select("run", "key", F.inline(cells)).where(F.col("rank") < F.lit(INF))
        return first_rows(rows, ["run", "a"], ["rank", "key"], self.ks[-1] + 1)

    def thresholds(self) -> DataFrame:
        """run, k, lo, hi: the k-th and the next smallest rank of every assignment, infinite where there is none.

        One row for each run and size, so the table is collected and becomes a local one.
        """
        if self._thresholds is not None:
            return self._thresholds
        at = [x for k in self.ks for x in (k, k + 1)]
        found = None
        for early in (True, False):
            rows = self.entries(early).groupBy("run", "a").agg(F.max("pos").alias("n"), *[F.max(F.when(F.col("pos") == p, F.col("rank"))).alias(f"p{p}") for p in dict.fromkeys(at)])
            found, self._early = {(r["run"], r["a"]): r for r in rows.collect()}, early
            if early:
                positive = self.weights.agg(*[F.count_if(F.col(f"w{i}") > 0) for i in range(len(self.names))]).first()
                needed = [min(n, self.ks[-1] + 1) for n in positive]
                if all((r, i) in found and found[r, i]["n"] >= n for r in range(self.runs) for i, n in enumerate(needed) if n):
                    break
        place = lambda r, i, p: INF if (r, i) not in found or found[r, i][f"p{p}"] is None else found[r, i][f"p{p}"]
        m = range(len(self.names))
        table = [(r, k, [place(r, i, k) for i in m], [place(r, i, k + 1) for i in m]) for r in range(self.runs) for k in self.ks]
        self._thresholds = self.weights.sparkSession.createDataFrame(table, "run int, k int, lo array<double>, hi array<double>")
        return self._thresholds

    def cells(self) -> DataFrame:
        """run, k, ``times``, weights, thresholds t0, t1, ... and probabilities e0, e1, ... of every key; keys of equal
        weights that are in no sample of the run and size are one row, and ``times`` says how many."""
        m, th = range(len(self.names)), self.thresholds()
        vectors = _once(self.weights, ("vectors", *self._w()), lambda: self.weights.groupBy(*self._w()).agg(F.count(F.lit(1)).alias("times")))
        inside = F.array_max(F.array(*[F.when(F.col(f"r{i}") < F.col("hi")[i], 1).otherwise(0) for i in m])) > 0 if len(m) > 1 else F.col("r0") < F.col("hi")[0]
        sampled = staged(self.drawn(self._early).join(F.broadcast(th), "run").where(inside))
        counted = sampled.groupBy("run", "k", *self._w()).agg(F.count(F.lit(1)).alias("less"))
        some = sampled.select(*self._w()).distinct()
        # a vector of which some key is sampled in some run is few; the others never meet the sampled ones
        rest = vectors.join(F.broadcast(some), self._w(), "left_anti").crossJoin(F.broadcast(th))
        part = vectors.join(F.broadcast(some), self._w(), "left_semi").crossJoin(F.broadcast(th)).join(counted, ["run", "k", *self._w()], "left")
        part = part.withColumn("times", F.col("times") - F.coalesce("less", F.lit(0))).where("times > 0")
        columns = ["run", "k", "times", *self._w()]
        # the filter keeps all; its plain evaluation keeps so many columns out of one generated method, which the JVM would not compile
        kept = lambda c: F.filter(c, lambda x: x.isNotNull()) if len(self.names) > 3 else F.col(c)
        low = [(kept("lo") if i == 0 else F.col("lo"))[i].alias(f"t{i}") for i in m]
        near = [F.when(F.col(f"r{i}") < (kept("hi") if i == 0 else F.col("hi"))[i], F.col("hi")[i]).otherwise(F.col("lo")[i]).alias(f"t{i}") for i in m]
        rows = rest.select(*columns, *low).unionByName(part.select(*columns, *low)).unionByName(sampled.withColumn("times", F.lit(1).cast("bigint")).select(*columns, *near))
        return rows.select("*", *[R.cdf(self.family, F.col(f"w{i}"), F.col(f"t{i}")).alias(f"e{i}") for i in m])

    def _measure(self, kind: str, names: list[str]) -> tuple[Column, Column]:
        """The function of a key and the variance of its adjusted value."""
        at = [self.names.index(b) for b in names]
        w, t, e = ([F.col(f"{c}{i}") for i in at] for c in "wte")
        high, low, near = _most(w), _least(w), _least(t)
        every = reduce(mul, e) if self.joint == "independent" else _least(e)
        any_ = 1 - reduce(mul, [1 - x for x in e]) if self.joint == "independent" else _most(e)
        cdf = lambda x: R.cdf(self.family, x, near)
        if kind in ("l1_l", "l1_s"):
            return high - low, l1_variance(high, low, cdf(high), every if kind == "l1_l" else cdf(low))
        if kind.startswith(("plain_", "inclusive_")) and kind.rpartition("_")[2].isdigit():
            i = at[int(kind.rpartition("_")[2])]
            f, p = F.col(f"w{i}"), F.col(f"e{i}") if kind.startswith("plain") else any_
        else:
            f, p = {
                "min_l": (low, every), "min_s": (low, cdf(low)), "max": (high, cdf(high)), "inclusive_max": (high, any_),
                "unweighted_max": (high, cdf(F.lit(1.0))), "unweighted_min": (low, cdf(F.lit(1.0))),
            }[kind]
        return f, key_variance(f, p)

    def sums(self, columns: list[tuple[str, list[str]]]) -> DataFrame:
        """k, v0, f0, v1, f1, ...: for each (measure, names) the sum of variances and that of the function, mean over runs."""
        parts = []
        for j, (kind, names) in enumerate(columns):
            f, v = self._measure(kind, names)
            parts += [F.sum(F.col("times") * v).alias(f"v{j}"), F.sum(F.col("times") * f).alias(f"f{j}")]
        per_run = self.cells().groupBy("run", "k").agg(*parts)
        return per_run.groupBy("k").agg(*[F.avg(f"{x}{j}").alias(f"{x}{j}") for j in range(len(columns)) for x in "vf"])

    def sizes(self) -> DataFrame:
        """k, keys: distinct keys over all assignments, mean over runs.

        A key is in the union of size k if its best place is k at most, so one sample serves all sizes.
        """
        self.thresholds()
        best = self.entries(self._early).groupBy("run", "key").agg(F.min("pos").alias("best"))
        counts = best.groupBy("run").agg(*[F.count_if(F.col("best") <= k).alias(f"n{k}") for k in self.ks]).agg(*[F.avg(f"n{k}").alias(f"n{k}") for k in self.ks])
        return counts.select(F.inline(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"n{k}").alias("keys")) for k in self.ks])))
