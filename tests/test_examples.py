"""Worked examples with known answers."""

import pytest
from pyspark.sql import functions as F

from seedrank.applications import EXAMPLE_SEEDS, EXAMPLE_VECTORS, EXAMPLE_WEIGHTS, example_ranked
from seedrank.functions import ranks as R
from seedrank.operators import estimators as E
from seedrank.operators import exact as X
from seedrank.operators import metrics as M
from seedrank.operators import sketch as S

# ranks of the first example as they are printed; that of i3 is ten times its seed over its weight
PRINTED = {"i1": 0.011, "i2": 0.075, "i3": 0.0583, "i4": 0.046, "i5": 0.055, "i6": 0.037}


def printed(spark):
    rows = [(0, "1", k, float(EXAMPLE_WEIGHTS[k]), EXAMPLE_SEEDS[k], r) for k, r in PRINTED.items()]
    return spark.createDataFrame(rows, "run int, assignment string, key string, weight double, seed double, rank double")


def values(df):
    return {r["key"]: r["adjusted"] for r in df.collect()}


@pytest.mark.parametrize("k, expected", [(1, {"i1": 27.03}), (2, {"i1": 21.74, "i6": 21.74}), (3, {"i1": 20, "i6": 18.18, "i4": 20})])
def test_bottom_k_of_the_printed_ranks(spark, k, expected):
    got = values(E.plain(S.bottom_k(printed(spark), k), "1"))
    assert got.keys() == expected.keys()
    assert all(abs(got[i] - expected[i]) < 0.1 for i in got)


def test_adjusted_weight_is_the_larger_of_weight_and_inverse_threshold(spark):
    got = values(E.plain(S.bottom_k(printed(spark), 3), "1"))
    assert all(abs(a - max(EXAMPLE_WEIGHTS[i], 1 / 0.055)) < 1e-9 for i, a in got.items())


@pytest.mark.parametrize("k, first", [(1, 82.0), (2, 41.0), (3, 20 * 82 / 60)])
def test_poisson_thresholds_and_weights(spark, k, first):
    rows = printed(spark)
    tau = S.ipps_tau(rows, k)
    assert abs(tau.first()["tau"] - k / 82) < 1e-12
    got = values(E.plain(S.poisson(rows, tau, k), "1"))
    assert list(got) == ["i1"] and abs(got["i1"] - first) < 1e-9


def test_ranks_from_the_seeds_put_the_third_key_first(spark):
    rows = example_ranked(spark)
    assert S.bottom_k(rows, 1).members().first()["key"] == "i3"
    assert {r["key"] for r in S.poisson(rows, S.ipps_tau(rows, 1), 1).members().collect()} == {"i1", "i3"}


def long(spark):
    rows = [(str(b + 1), k, w) for k, v in EXAMPLE_VECTORS.items() for b, w in enumerate(v)]
    return spark.createDataFrame(rows, "assignment string, key string, weight long")


def test_exact_functions_of_the_vectors(spark):
    two = {r["key"]: (r["high"], r["low"]) for r in X.per_key(long(spark), ["1", "2"]).collect()}
    assert two == {"i1": (20, 15), "i2": (10, 0), "i3": (12, 10), "i4": (20, 5), "i5": (10, 0), "i6": (10, 10)}
    n = X.norms(long(spark), ["2", "3"]).first()
    assert n["sum_l1"] == 10 + 5 + 3 + 20 + 15 + 0


def test_estimates_of_the_second_example(spark):
    sketch = S.bottom_k(example_ranked(spark, EXAMPLE_VECTORS), 3)
    high = values(E.maximum(sketch, ["1", "2"]))
    assert {k: round(v, 4) for k, v in high.items()} == {"i1": 21.7391, "i3": 21.7391, "i6": 21.7391}
    low_l, low_s = values(E.minimum(sketch, ["1", "2"], "l")), values(E.minimum(sketch, ["1", "2"], "s"))
    assert {k: round(v, 4) for k, v in low_l.items()} == {"i1": 18.1818, "i3": 18.1818, "i6": 21.7391}
    assert round(sum(low_s.values()), 4) == 65.2174
    assert round(sum(values(E.l1(sketch, ["1", "2"])).values()), 4) == 7.1146


def test_inclusive_probabilities_of_the_second_example(spark):
    vectors = spark.createDataFrame([(k, {str(b + 1): float(w) for b, w in enumerate(v)}) for k, v in EXAMPLE_VECTORS.items()], "key string, weights map<string,double>")
    seeds = F.create_map(*[x for k, u in EXAMPLE_SEEDS.items() for x in (F.lit(k), F.lit(u))])
    ranked = R.rank_wide(vectors)
    cells = F.transform("cells", lambda c: F.struct(c["b"].alias("b"), c["w"].alias("w"), seeds[F.col("key")].alias("seed"), (seeds[F.col("key")] / c["w"]).alias("rank")))
    ranked = ranked.withColumn("cells", cells)
    sketch = S.bottom_k(R.to_long(ranked), 3)
    got = {r["key"]: round(r["p"], 4) for r in E.inclusive(E.colocated_summary(ranked, sketch, ["1", "2", "3"]), E.f_max).collect()}
    assert got == {"i1": 0.92, "i3": 0.555, "i5": 0.555, "i6": 0.55}
    assert round(M.sharing_index(sketch, 3, 3).first()[0], 4) == 0.4444
