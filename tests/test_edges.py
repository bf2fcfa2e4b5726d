"""Inputs at the edge: empty, few, zero, equal and bad weights, and refusals."""

import pytest
from pyspark.sql import functions as F

from seedrank.functions import ranks as R
from seedrank.functions import seeds
from seedrank.operators import estimators as E
from seedrank.operators import exact as X
from seedrank.operators import relops
from seedrank.operators import sketch as S
from seedrank.sources import store
from seedrank.sources import weights as W

LONG = "assignment string, key string, weight double"


def frame(spark, rows):
    return spark.createDataFrame(rows, LONG)


def test_empty_input(spark):
    sketch = S.bottom_k(R.rank_long(frame(spark, [])), 5)
    assert sketch.entries.count() == 0
    assert E.l1(sketch, ["a", "b"]).count() == 0


def test_fewer_keys_than_k_gives_exact_answers(spark):
    rows = frame(spark, [("a", "x", 3.0), ("a", "y", 5.0), ("b", "x", 4.0), ("b", "z", 0.0)])
    sketch = S.bottom_k(R.rank_long(rows), 10)
    assert E.total(E.maximum(sketch, ["a", "b"])).first()["estimate"] == 9
    assert E.total(E.minimum(sketch, ["a", "b"])).first()["estimate"] == 3
    assert E.total(E.l1(sketch, ["a", "b"])).first()["estimate"] == 6


def test_zero_weight_has_probability_zero_at_any_threshold(spark):
    got = spark.range(1).select(R.cdf("ipps", F.lit(0.0), F.lit(R.INFINITY)).alias("p"), R.cdf("exp", F.lit(0.0), F.lit(R.INFINITY)).alias("q"), R.rank("ipps", F.lit(0.0), F.lit(0.5)).alias("r")).first()
    assert got["p"] == 0 and got["q"] == 0 and got["r"] == R.INFINITY


@pytest.mark.parametrize("family", R.FAMILIES)
def test_quantile_inverts_the_distribution(spark, family):
    rows = spark.range(1, 100).select((F.col("id") / 100).alias("u"))
    back = rows.select(F.abs(R.cdf(family, F.lit(3.0), R.quantile(family, F.lit(3.0), F.col("u"))) - F.col("u")).alias("d"))
    assert back.agg(F.max("d")).first()[0] < 1e-12


@pytest.mark.parametrize("algo", ["md5", "xxhash64"])
def test_seeds_are_uniform_and_repeatable(spark, algo):
    rows = spark.range(20000).select(seeds.key_seed(F.col("id").cast("string"), "s", algo).alias("u"))
    a, b = rows.agg(F.avg("u"), F.min("u"), F.max("u"), F.stddev("u")).first(), rows.repartition(7).agg(F.avg("u")).first()
    assert abs(a[0] - 0.5) < 0.01 and 0 < a[1] and a[2] < 1 and abs(a[3] - 12**-0.5) < 0.01
    assert abs(a[0] - b[0]) < 1e-12


def test_equal_vectors_share_all_keys_when_coordinated(spark):
    rows = frame(spark, [(b, f"k{i}", float(i % 7 + 1)) for b in "abc" for i in range(200)])
    shared = S.bottom_k(R.rank_long(rows), 20)
    assert shared.members().select("key").distinct().count() == 20
    alone = S.bottom_k(R.rank_long(rows, joint="independent"), 20, joint="independent")
    assert alone.members().select("key").distinct().count() > 40


def test_bad_weights(spark):
    bad = frame(spark, [("a", "x", -1.0), ("a", "y", None), ("a", "z", float("nan")), ("a", "w", 2.0)])
    with pytest.raises(W.BadWeights):
        W.validate(bad)
    assert [r["key"] for r in W.validate(bad, "drop").collect()] == ["w"]
    with pytest.raises(W.BadWeights):
        W.validate(frame(spark, [("a", "x", 1.0), ("a", "x", 2.0)]))


def test_refusals(spark):
    rows = frame(spark, [(b, f"k{i}", float(i + 1)) for b in "ab" for i in range(9)])
    alone = S.bottom_k(R.rank_long(rows, joint="independent"), 3, joint="independent")
    for attempt in (
        lambda: E.maximum(alone, ["a", "b"]),
        lambda: E.l_set(S.drop_seeds(alone), ["a", "b"], 1),
        lambda: E.median(S.bottom_k(R.rank_long(rows), 3), ["a", "b"]),
        lambda: R.check_design("ipps", "inddiff"),
        lambda: R.rank_long(rows, "exp", "inddiff"),
        lambda: S.max_union(alone, ["a", "b"]),
        lambda: S.merge(alone, S.bottom_k(R.rank_long(rows), 3)),
    ):
        with pytest.raises(ValueError):
            attempt()
    E.l_set(alone, ["a", "b"], 1).count()


def test_prefilter_changes_nothing(spark):
    rows = frame(spark, [("a", f"k{i}", float(i % 97 + 1)) for i in range(3000)] + [("b", f"k{i}", 1.0) for i in range(12)])
    ranked = R.rank_long(rows)
    key = lambda s: sorted(tuple(r) for r in s.entries.select("assignment", "key", "pos").collect())
    assert key(S.bottom_k(ranked, 25)) == key(S.bottom_k(ranked, 25, early=True))
    assert S.prefilter(ranked, 25).where("assignment = 'a'").count() < 400


def test_large_k_uses_the_prefilter_without_a_window_limit(spark):
    rows = R.rank_long(frame(spark, [("a", f"k{i}", float(i % 5 + 1)) for i in range(5000)]))
    assert S.bottom_k(rows, 1500, early=True).members().count() == 1500


def test_merge_and_order_do_not_matter(spark):
    ranked = R.rank_long(frame(spark, [("a", f"k{i}", float(i % 31 + 1)) for i in range(2000)]))
    even = F.pmod(F.xxhash64("key"), F.lit(2)) == 0
    key = lambda s: sorted(tuple(r) for r in s.entries.select("key", "pos").collect())
    whole = key(S.bottom_k(ranked, 40))
    assert whole == key(S.merge(S.bottom_k(ranked.where(even), 40), S.bottom_k(ranked.where(~even), 40)))
    assert whole == key(S.bottom_k(ranked.repartition(9, "weight"), 40))


def test_max_union_is_the_sample_of_the_maxima(spark):
    ranked = R.rank_long(frame(spark, [(b, f"k{i}", float((i * (3 + len(b)) + ord(b)) % 41)) for b in "abc" for i in range(800)]))
    direct = R.min_rank(ranked, list("abc")).withColumn("assignment", F.lit("max")).withColumn("seed", F.lit(0.0))
    key = lambda s: sorted(tuple(r) for r in s.entries.select("key", "weight", "pos").collect())
    assert key(S.max_union(S.bottom_k(ranked, 30), list("abc"))) == key(S.bottom_k(direct, 30))


def test_fixed_distinct_fills_its_budget(spark):
    ranked = R.rank_long(frame(spark, [(b, f"k{i}", float((i * ord(b)) % 37 + 1)) for b in "abc" for i in range(500)]))
    sketch = S.fixed_distinct(ranked, 20, 3)
    keys = sketch.members().select("key").distinct().count()
    assert 3 * 19 + 1 <= keys <= 60
    assert sketch.meta.first()["l"] >= 20


def test_fixed_expected_hits_its_budget(spark):
    rows = W.to_wide(frame(spark, [(b, f"k{i}", float((i * ord(b)) % 37 + 1)) for b in "abc" for i in range(500)]))
    size, taus = S.fixed_expected(rows, 20, list("abc"))
    expected = rows.select(F.greatest(*[R.cdf("ipps", F.coalesce(F.col("weights")[b], F.lit(0.0)), F.lit(t)) for b, t in taus.items()]).alias("p")).agg(F.sum("p")).first()[0]
    assert size >= 20 and abs(expected - 60) < 0.01


def test_exact_and_searched_thresholds_agree(spark):
    rows = frame(spark, [("a", f"k{i}", float(i**2 % 101 + (5000 if i < 5 else 1))) for i in range(900)])
    exact = S.ipps_tau(rows, 50).first()["tau"]
    assert abs(S.solve_tau(rows, 50)["a"] / exact - 1) < 1e-9


def test_store_round_trip(spark, tmp_path):
    sketch = S.bottom_k(R.rank_long(frame(spark, [(b, f"k{i}", float(i + 1)) for b in "ab" for i in range(50)])), 5)
    store.save(sketch, str(tmp_path / "s"), "one")
    back = store.load(spark, str(tmp_path / "s"), "one")
    assert back.design() == sketch.design() and back.k == 5
    assert E.total(E.l1(back, ["a", "b"])).first() == E.total(E.l1(sketch, ["a", "b"])).first()
    for kind in ("json", "csv"):
        store.export(sketch, str(tmp_path / kind), kind)
        read = store.import_(spark, str(tmp_path / kind), sketch, kind)
        assert sorted(map(tuple, read.entries.collect())) == sorted(map(tuple, sketch.entries.collect())) and read.meta.dtypes == sketch.meta.dtypes
    store.export(sketch, str(tmp_path / "text"))
    assert spark.read.json(str(tmp_path / "text" / "entries")).count() == 12


def test_keys_of_any_alphabet(spark, duck):
    key = "ключ|é🙂"
    got = spark.createDataFrame([(key,)], "k string").select(seeds.key_seed(F.col("k"), "s").alias("u")).first()["u"]
    sql = "SELECT (CAST('0x' || substr(md5(concat_ws('|', 's', ?)), 1, 13) AS BIGINT) + 0.5) / 4503599627370496.0"
    assert got == duck.execute(sql, [key]).fetchone()[0]


def test_pairs_and_moments(spark):
    rows = frame(spark, [("a", "x", 2.0), ("b", "x", 3.0), ("c", "x", 1.0), ("a", "y", 5.0)])
    assert {(r["a"], r["b"], r["wa"], r["wb"]) for r in relops.pairs(rows).collect()} == {("a", "b", 2, 3), ("a", "c", 2, 1), ("b", "c", 3, 1)}
    m = W.moments(spark.createDataFrame([("u", 2), ("u", 3), ("v", 4)], "k string, x long"), F.col("k"), F.col("x"))
    assert {r["key"]: r["weights"] for r in m.collect()} == {"u": {"x": 5.0, "xx": 13.0}, "v": {"x": 4.0, "xx": 16.0}}


def test_identities_of_exact_norms(spark, sf):
    from seedrank.plans.workloads import long_weights

    rows = long_weights(spark, sf, "part_months")
    n = X.norms(rows, ["m01", "m02"]).first()
    assert (n["keys"], n["sum_min"], n["sum_max"], n["sum_l1"]) == (1979, 3205, 6643, 3438)
    assert n["sum_max"] - n["sum_min"] == n["sum_l1"]
    assert n["sum_max"] + n["sum_min"] == X.sums(rows, F.col("assignment").isin("m01", "m02")).agg(F.sum("total")).first()[0]


def test_least_ranks_of_long_weights_are_those_of_wide_ones(spark):
    rows = frame(spark, [(f"d{d}", f"w{w}", float((d * w + d) % 5)) for d in range(12) for w in range(9)] + [("copy", f"w{w}", float((3 * w + 3) % 5)) for w in range(9)])
    wide = S.k_mins(W.to_wide(rows), 16, joint="inddiff")
    long = S.k_mins_of_long(rows, 16)
    assert sorted(map(tuple, long.collect())) == sorted(tuple(r) for r in wide.collect())
    pairs = sorted(map(tuple, E.jaccard_all_pairs_collapsed(long, 16).collect()))
    assert pairs == sorted(map(tuple, E.jaccard_all_pairs(wide, 16).collect())) and ("copy", "d3", 1.0) in pairs


def test_similarity_is_of_all_english_documents(spark, sf, duck):
    from seedrank.queries import QUERIES

    got = QUERIES["q_w17_document_similarity"](spark, sf).toPandas()
    assert set(got.doc_id) == {str(r[0]) for r in duck.execute("SELECT doc_id FROM documents WHERE lang = 'en' AND regexp_matches(lower(text), '[a-z]')").fetchall()}


@pytest.mark.parametrize("name", ["q_no_estimator_guard", *(f"q_w18_example_{x}" for x in ("max", "min_l", "min_s", "samples"))])
def test_examples_and_refusals_read_a_given_table(spark, sf, name):
    from seedrank.queries import QUERIES

    assert any(f.endswith("lineitem.parquet") for f in QUERIES[name](spark, sf).inputFiles())
