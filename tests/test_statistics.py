"""Unbiasedness and other laws over many replications, on small data with mild weights."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from seedrank.functions import ranks as R
from seedrank.operators import baselines as B
from seedrank.operators import estimators as E
from seedrank.operators import metrics as M
from seedrank.operators import sketch as S
from seedrank.sources import weights as W

NAMES, RUNS, K = ["a", "b", "c"], 600, 12


@pytest.fixture(scope="module")
def data(spark):
    rng = np.random.default_rng(5)
    rows = [(b, f"k{i}", float(w)) for i, v in enumerate(rng.integers(0, 9, (40, 3))) for b, w in zip(NAMES, v, strict=True)]
    long = spark.createDataFrame(rows, "assignment string, key string, weight double").cache()
    table = np.array([[w for _, k, w in rows if k == f"k{i}"] for i in range(40)])
    return long, W.to_wide(long).cache(), table


def close(estimates, truth):
    """Mean of the totals per run within four standard errors of the truth; runs without a row count as zero."""
    sums = np.array([r["estimate"] for r in estimates.collect()])
    sums = np.concatenate([sums, np.zeros(RUNS - len(sums))])
    assert abs(sums.mean() - truth) <= 4 * sums.std() / RUNS**0.5 + 1e-9, (sums.mean(), truth, sums.std() / RUNS**0.5)


def sketch(long, family="ipps", joint="shared"):
    return S.bottom_k(R.rank_long(long, family, joint, runs=RUNS), K, family, joint)


@pytest.mark.parametrize("family", R.FAMILIES)
def test_dispersed_estimates(data, family):
    long, _, t = data
    s, second = sketch(long, family), np.sort(t, axis=1)[:, -2].sum()
    close(E.total(E.plain(s, "a")), t[:, 0].sum())
    close(E.total(E.maximum(s, NAMES)), t.max(axis=1).sum())
    for kind in "sl":
        close(E.total(E.minimum(s, NAMES, kind)), t.min(axis=1).sum())
        close(E.total(E.lth_largest(s, NAMES, 2, kind)), second)
    differences = E.l1(s, NAMES)
    close(E.total(differences), (t.max(axis=1) - t.min(axis=1)).sum())
    assert differences.agg(F.min("adjusted")).first()[0] >= -1e-9


def test_independent_estimates(data):
    long, _, t = data
    s = sketch(long, joint="independent")
    close(E.total(E.minimum(s, NAMES[:2], "l")), t[:, :2].min(axis=1).sum())
    close(E.total(E.minimum(s, NAMES[:2], "s")), t[:, :2].min(axis=1).sum())
    close(E.total(E.l_set(s, NAMES[:2], 1)), t[:, :2].max(axis=1).sum())


def test_general_functions_and_predicates(data):
    long, _, t = data
    s = sketch(long)
    heavy = lambda c: E.lth_weight(c, 1) > 4
    close(E.total(E.s_set(s, NAMES, 1, d=heavy)), t.max(axis=1)[t.max(axis=1) > 4].sum())
    top = np.sort(t, axis=1)[:, ::-1]
    close(E.total(E.l_set(s, NAMES, 2, f=lambda c: F.aggregate(E.top_weights(c, 2), F.lit(1.0), lambda a, x: a * x))), (top[:, 0] * top[:, 1]).sum())


@pytest.mark.parametrize("family, joint", [("ipps", "shared"), ("exp", "shared"), ("ipps", "independent"), ("exp", "inddiff")])
def test_colocated_estimates(data, family, joint):
    _, wide, t = data
    ranked = R.rank_wide(wide, family, joint, runs=RUNS)
    s = S.bottom_k(R.to_long(ranked), K, family, joint)
    rows = E.colocated_summary(ranked, s, NAMES)
    close(E.total(E.inclusive(rows, E.f_l1, family, joint)), (t.max(axis=1) - t.min(axis=1)).sum())
    close(E.total(E.inclusive(rows, E.f_single("b"), family, joint)), t[:, 1].sum())
    if joint == "inddiff":
        worst = rows.select(F.abs(E.inclusive_p(F.col("cells"), family, joint) - E.inclusive_p_by_events(F.col("cells"))).alias("d")).agg(F.max("d")).first()[0]
        assert worst < 1e-12
        assert R.inconsistent_keys(R.to_long(R.rank_wide(wide, family, joint, runs=20))).count() == 0
    if joint != "independent":
        close(E.total(E.generic_consistent(rows, E.f_max, family, NAMES)), t.max(axis=1).sum())


def test_poisson_estimates(data):
    long, wide, t = data
    tau = S.ipps_tau(long, K)
    s = S.poisson(R.rank_long(long, runs=RUNS), tau, K)
    close(E.total(E.plain(s, "a")), t[:, 0].sum())
    close(E.total(E.maximum(s, NAMES)), t.max(axis=1).sum())
    close(E.total(E.minimum(s, NAMES)), t.min(axis=1).sum())
    ranked = R.rank_wide(wide, runs=RUNS)
    close(E.total(E.inclusive(E.colocated_summary(ranked, S.poisson(R.to_long(ranked), tau, K), NAMES), E.f_l1)), (t.max(axis=1) - t.min(axis=1)).sum())
    sizes = s.members(["a"]).groupBy("run").count().agg(F.avg("count")).first()[0]
    assert abs(sizes - K) < 0.5


def test_fixed_number_of_keys(data):
    _, wide, t = data
    ranked = R.rank_wide(wide, runs=RUNS)
    s = S.fixed_distinct(R.to_long(ranked), 4, 3)
    close(E.total(E.inclusive_fixed(ranked, s, NAMES, 4, E.f_max)), t.max(axis=1).sum())


def test_baselines(data):
    long, wide, t = data
    close(E.total(B.unweighted(B.unweighted_sketch(long, K, runs=RUNS), NAMES, E.f_max)), t.max(axis=1).sum())
    close(E.total(B.primary_function(wide, E.f_max, K, runs=RUNS)), t.max(axis=1).sum())
    ranked = R.rank_wide(wide, runs=RUNS)
    rows = E.colocated_summary(ranked, S.bottom_k(R.to_long(ranked), K), NAMES)
    seen = t[:, 0] > 0
    close(E.total(B.single_primary(rows, "a", E.f_single("b"), "ipps")), t[seen, 1].sum())


def test_kmins(data):
    _, wide, t = data
    k = 400
    totals = {r["assignment"]: r["total"] for r in E.kmins_total(S.k_mins(wide, k), k).collect()}
    assert all(abs(totals[b] / t[:, j].sum() - 1) < 5 / k**0.5 for j, b in enumerate(NAMES))
    exact = np.minimum(t[:, 0], t[:, 1]).sum() / np.maximum(t[:, 0], t[:, 1]).sum()
    found = E.jaccard_kmins(S.k_mins(wide, k, joint="inddiff"), "a", "b").first()[0]
    assert abs(found - exact) < 4 * (exact * (1 - exact) / k) ** 0.5


def test_variances_and_bounds(data):
    long, wide, t = data
    ranked = R.rank_wide(wide, runs=RUNS)
    s = S.bottom_k(R.to_long(ranked), K)
    full = E.full_cells(ranked, s.meta, NAMES)
    primary = S.bottom_k(R.min_rank(R.to_long(ranked), NAMES).withColumn("assignment", F.lit("max")).withColumn("seed", F.lit(None).cast("double")), K)
    assert all(v == 0 for v in M.bound_violations(full, "ipps", primary.meta).first())
    conditional = M.conditional_variance(full, E.f_max, lambda c: E.s_set_p(c, 1, "ipps", "shared")).agg(F.avg("sv")).first()[0]
    exact = wide.sparkSession.createDataFrame([(f"k{i}", float(v)) for i, v in enumerate(t.max(axis=1)) if v > 0], "key string, f double")
    measured = M.sigma_v(E.maximum(sketch(long), NAMES), exact, RUNS).first()
    assert abs(measured["sv"] / conditional - 1) < 0.15
    assert (K - 2) * measured["nsv"] <= 1.05
    low = M.conditional_variance_l1(full, lambda c: E.s_set_p(c, 1, "ipps", "shared"), lambda c: E.l_set_p(c, 3, "ipps", "shared")).agg(F.avg("sv")).first()[0]
    assert low <= conditional * (1 + 1e-9)
    assert M.usable_for_max(sketch(long), NAMES).agg(F.min("keys")).first()[0] >= K - 1
    spread = M.per_key_variance(E.maximum(sketch(long), NAMES), exact, RUNS).agg(F.sum("variance")).first()[0]
    assert abs(spread / measured["sv"] - 1) < 0.05
    pairs = [(f"k{i}", f"k{i + 1}") for i in range(0, 12, 2)]
    scale = (t.max(axis=1) ** 2).mean() * 3
    for r in M.covariance(E.maximum(sketch(long), NAMES), pairs, {f"k{i}": float(v) for i, v in enumerate(t.max(axis=1))}, RUNS).collect():
        assert abs(r["covariance"]) < scale
    assert M.squared_error(E.total(E.maximum(sketch(long), NAMES)), float(t.max(axis=1).sum())).first()["relative_error"] < 0.4


def test_standard_error_matches_the_spread(data):
    long, _, _ = data
    rows = E.std_error(E.maximum(sketch(long), NAMES)).collect()
    spread = np.std([r["estimate"] for r in rows])
    assert 0.7 < np.sqrt(np.mean([r["std_error"] ** 2 for r in rows])) / spread < 1.4


def test_linear_combination(data):
    long, _, t = data
    s = sketch(long)
    both = E.linear_combination([(1, E.maximum(s, NAMES)), (2, E.lth_largest(s, NAMES, 2))])
    close(E.total(both), t.max(axis=1).sum() + 2 * np.sort(t, axis=1)[:, -2].sum())
