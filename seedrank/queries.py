"""Every query of the sampling engine, and the SQL that states the same results.

``QUERIES[name](spark, sf_dir)`` returns a DataFrame; ``ORACLES[name]`` is DuckDB SQL over the same tables.
Queries without SQL are checked by tests.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seedrank import oracles as O
from seedrank.functions import ranks as R
from seedrank.operators import baselines as B
from seedrank.operators import estimators as E
from seedrank.operators import exact as X
from seedrank.operators import metrics as M
from seedrank.operators import sketch as S
from seedrank.plans.workloads import WORKLOADS, long_weights, wide_weights

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

MONTHS2, MONTHS6 = ["m01", "m02"], [f"m{i:02d}" for i in range(1, 7)]
MONTHS3, DAYS4 = ["m01", "m02", "m03"], [f"d{i:02d}" for i in range(1, 5)]
WORDS = ["src0", "src1", "src2", "src3"]


def query(name: str, sql: str | None = None):
    def add(plan: Query) -> Query:
        QUERIES[name] = plan
        if sql is not None:
            ORACLES[name] = sql
        return plan

    return add


def rounded(adjusted: DataFrame) -> DataFrame:
    return adjusted.select("run", "key", F.round("f", 4).alias("f"), F.round("p", 9).alias("p"), F.round("adjusted", 3).alias("adjusted"))


def ranked_long(spark, sf, workload, names, family="ipps", joint="shared", runs=1) -> DataFrame:
    if joint == "inddiff":
        return R.to_long(R.rank_wide(wide_weights(spark, sf, workload, names), family, joint, runs=runs))
    return R.rank_long(long_weights(spark, sf, workload, names), family, joint, runs=runs)


def bottom(spark, sf, workload, names, k, family="ipps", joint="shared", runs=1, early=None) -> S.Sketch:
    return S.bottom_k(ranked_long(spark, sf, workload, names, family, joint, runs), k, family, joint, early=early)


def full(spark, sf, workload, names, k, family="ipps", joint="shared", runs=1) -> tuple[DataFrame, S.Sketch]:
    """Cells of all keys, and the sketch whose thresholds they are compared with."""
    ranked = R.rank_wide(wide_weights(spark, sf, workload, names), family, joint, runs=runs)
    sketch = S.bottom_k(R.to_long(ranked), k, family, joint)
    return E.full_cells(ranked, sketch.meta, names), sketch


# ---------------------------------------------------------------- randomisation and samples

_RANKED_ROWS = "SELECT assignment, key, round(seed, 12) AS seed, round(rank, 9) AS rank FROM ranked"


def _rank_query(name: str, family: str, joint: str) -> None:
    def plan(spark, sf):
        rows = ranked_long(spark, sf, "part_months", MONTHS3, family, joint)
        return rows.select("assignment", "key", F.round("seed", 12).alias("seed"), F.round("rank", 9).alias("rank"))

    query(name, O.chain(O.ranked("part_months", MONTHS3, family, joint), select=_RANKED_ROWS))(plan)


_rank_query("q_rank_ipps", "ipps", "shared")
_rank_query("q_rank_exp", "exp", "shared")
_rank_query("q_rank_independent", "ipps", "independent")
_rank_query("q_rank_inddiff", "exp", "inddiff")


@query("q_seed_md5", f"SELECT DISTINCT CAST(l_partkey AS VARCHAR) AS key, {O.uniform(chr(39) + 'v1#0' + chr(39), 'CAST(l_partkey AS VARCHAR)')} AS seed FROM lineitem")
def _seed(spark, sf):
    from seedrank.functions.seeds import key_seed
    from seedrank.sources.tables import scan

    keys = scan(spark, sf, "lineitem").select(F.col("l_partkey").cast("string").alias("key")).distinct()
    return keys.withColumn("seed", key_seed(F.col("key"), "v1#0"))


def _inconsistent_sql(joint: str, family: str) -> str:
    """Keys of which a heavier assignment ranks after a lighter one."""
    worse = "a.run = b.run AND a.key = b.key AND a.weight > b.weight AND a.rank > b.rank"
    return O.chain(O.ranked("part_months", MONTHS6, family, joint), select=f"SELECT CAST('{joint}' AS VARCHAR) AS joint, count(DISTINCT a.key) AS bad FROM ranked a JOIN ranked b ON {worse}")


@query("q_consistency_check", " UNION ALL ".join(f"SELECT * FROM ({_inconsistent_sql(j, f)})" for j, f in (("shared", "ipps"), ("inddiff", "exp"), ("independent", "ipps"))))
def _consistency(spark, sf):
    out = None
    for joint, family in (("shared", "ipps"), ("inddiff", "exp"), ("independent", "ipps")):
        rows = R.inconsistent_keys(ranked_long(spark, sf, "part_months", MONTHS6, family, joint))
        one = rows.agg(F.count(F.lit(1)).alias("bad")).select(F.lit(joint).alias("joint"), "bad")
        out = one if out is None else out.unionByName(one)
    return out


@query("q_min_rank_max", O.chain(O.ranked("part_months", MONTHS3), select="SELECT run, key, max(weight) AS weight, round(min(rank), 9) AS rank FROM ranked GROUP BY 1, 2"))
def _min_rank(spark, sf):
    return R.min_rank(ranked_long(spark, sf, "part_months", MONTHS3), MONTHS3).withColumn("rank", F.round("rank", 9))


_ENTRIES = "SELECT run, assignment, key, weight, round(rank * 1e6, 9) AS rank, CAST(pos AS INTEGER) AS pos FROM ent"


def _entries(sketch: S.Sketch) -> DataFrame:
    return sketch.entries.select("run", "assignment", "key", "weight", F.round(F.col("rank") * 1e6, 9).alias("rank"), "pos")


for _joint, _family in (("shared", "ipps"), ("independent", "ipps"), ("inddiff", "exp")):
    query(f"q_bottomk_{_joint}", O.chain(O.ranked("part_months", MONTHS3, _family, _joint), O.bottom_k(100), select=_ENTRIES))(
        lambda spark, sf, j=_joint, f=_family: _entries(bottom(spark, sf, "part_months", MONTHS3, 100, f, j))
    )

_VARYING = {"m01": 50, "m02": 100, "m03": 20}
query("q_bottomk_varying_k", O.chain(O.ranked("part_months", MONTHS3), O.bottom_k(_VARYING), select=_ENTRIES))(lambda spark, sf: _entries(bottom(spark, sf, "part_months", MONTHS3, _VARYING)))
query("q_bottomk_prefiltered", O.chain(O.ranked("part_months", None), O.bottom_k(200), select=_ENTRIES))(lambda spark, sf: _entries(bottom(spark, sf, "part_months", None, 200, early=True)))
query("q_bottomk_words", O.chain(O.ranked("words", WORDS, "exp"), O.bottom_k(300), select=_ENTRIES))(lambda spark, sf: _entries(bottom(spark, sf, "words", WORDS, 300, "exp")))


@query("q_poisson_solve_tau", O.chain(O.ranked("words", WORDS), O.ipps_tau(200), select="SELECT assignment, round(tau * 1e6, 6) AS tau FROM tau"))
def _tau(spark, sf):
    return S.ipps_tau(long_weights(spark, sf, "words", WORDS), 200).withColumn("tau", F.round(F.col("tau") * 1e6, 6))


@query("q_poisson_search_tau")
def _tau_search(spark, sf):
    """Thresholds of exponential ranks by the narrowing search; the expected sizes stand beside them."""
    rows = long_weights(spark, sf, "part_months", MONTHS3)
    found = S.solve_tau(rows, 200, "exp")
    table = F.create_map(*[x for b, t in found.items() for x in (F.lit(b), F.lit(t))])
    return rows.groupBy("assignment").agg(F.round(F.sum(R.cdf("exp", F.col("weight").cast("double"), table[F.col("assignment")])), 3).alias("expected"))


def poisson_words(spark, sf, k=200) -> S.Sketch:
    rows = long_weights(spark, sf, "words", WORDS)
    return S.poisson(R.rank_long(rows), S.ipps_tau(rows, k), k)


query("q_poisson_tau", O.chain(O.ranked("words", WORDS), O.ipps_tau(200), O.poisson(), select="SELECT assignment, key, weight, round(rank * 1e6, 9) AS rank FROM ent"))(
    lambda spark, sf: poisson_words(spark, sf).entries.select("assignment", "key", "weight", F.round(F.col("rank") * 1e6, 9).alias("rank"))
)

_KMINS = """SELECT assignment, CAST(t AS INTEGER) AS t, round(min(rank) * 1e9, 6) AS rank, arg_min(key, rank) AS key, arg_min(weight, rank) AS weight FROM draws GROUP BY 1, 2"""


def _kmins_draws(names, k, joint="shared", salt="v1") -> str:
    if joint == "inddiff":
        body = O.ranked("part_months", names, "exp", "inddiff", salt, k + 1)
        return body + ",\ndraws AS (SELECT run AS t, assignment, key, weight, rank FROM ranked WHERE run > 0)"
    seed = O.uniform(f"'{salt}'", "'draw'", "CAST(t AS VARCHAR)", "key")
    return O.ranked("part_months", names) + f",\ndraws AS (SELECT t, assignment, key, weight, -ln(1.0 - {seed}) / weight AS rank FROM ranked, (SELECT unnest(range(1, {k + 1})) AS t))"


query("q_kmins", O.chain(_kmins_draws(MONTHS2, 40), select=_KMINS))(
    lambda spark, sf: S.k_mins(wide_weights(spark, sf, "part_months", MONTHS2), 40).select("assignment", "t", F.round(F.col("rank") * 1e9, 6).alias("rank"), "key", "weight")
)
query("q_kmins_inddiff", O.chain(_kmins_draws(MONTHS2, 20, "inddiff"), select=_KMINS))(
    lambda spark, sf: S.k_mins(wide_weights(spark, sf, "part_months", MONTHS2), 20, joint="inddiff").select("assignment", "t", F.round(F.col("rank") * 1e9, 6).alias("rank"), "key", "weight")
)
query("q_kmins_total", O.chain(_kmins_draws(MONTHS2, 40), select="SELECT assignment, round(39 / sum(rank), 4) AS total FROM (SELECT assignment, t, min(rank) AS rank FROM draws GROUP BY 1, 2) GROUP BY 1"))(
    lambda spark, sf: E.kmins_total(S.k_mins(wide_weights(spark, sf, "part_months", MONTHS2), 40), 40).withColumn("total", F.round("total", 4))
)

_UNION_OF_KEYS = "SELECT key, max(weight) AS weight, min(rank) AS rank FROM ranked GROUP BY key"
query("q_max_union_bottomk", O.chain(O.ranked("part_months", MONTHS3), select=f"SELECT key, weight, round(rank * 1e6, 9) AS rank, CAST(row_number() OVER (ORDER BY rank, key) AS INTEGER) AS pos FROM ({_UNION_OF_KEYS}) QUALIFY pos <= 101"))(
    lambda spark, sf: S.max_union(bottom(spark, sf, "part_months", MONTHS3, 100), MONTHS3).entries.select("key", "weight", F.round(F.col("rank") * 1e6, 9).alias("rank"), "pos")
)
query("q_max_union_poisson", O.chain(O.ranked("words", WORDS), O.ipps_tau(200), select=f"SELECT key, weight, round(rank * 1e6, 9) AS rank FROM ({_UNION_OF_KEYS}) WHERE rank < (SELECT min(tau) FROM tau)"))(
    lambda spark, sf: S.max_union(poisson_words(spark, sf), WORDS).entries.select("key", "weight", F.round(F.col("rank") * 1e6, 9).alias("rank"))
)
query("q_max_union_kmins", O.chain(_kmins_draws(MONTHS2, 40), select="SELECT CAST(t AS INTEGER) AS t, round(min(rank) * 1e9, 6) AS rank, arg_min(key, rank) AS key FROM draws GROUP BY 1"))(
    lambda spark, sf: S.max_union_kmins(S.k_mins(wide_weights(spark, sf, "part_months", MONTHS2), 40), MONTHS2).select("t", F.round(F.col("rank") * 1e9, 6).alias("rank"), "key")
)


@query("q_sketch_merge", O.chain(O.ranked("part_months", MONTHS3), O.bottom_k(100), select=_ENTRIES))
def _merge(spark, sf):
    rows = ranked_long(spark, sf, "part_months", MONTHS3)
    even = F.pmod(F.xxhash64("key"), F.lit(2)) == 0
    return _entries(S.merge(S.bottom_k(rows.where(even), 100), S.bottom_k(rows.where(~even), 100)))


@query("q_dispersed_summary", O.chain(O.ranked("part_months", MONTHS3), O.bottom_k(100), select="SELECT assignment, key, weight FROM ent WHERE member"))
def _dispersed(spark, sf):
    parts = [S.bottom_k(ranked_long(spark, sf, "part_months", [b]), 100) for b in MONTHS3]
    return S.combine(*parts).members().select("assignment", "key", "weight")


PARTS = list(WORKLOADS["parts"].names)
PAIRS = list(WORKLOADS["pairs"].names)


@query("q_colocated_summary", O.chain(O.ranked("parts", PARTS), O.bottom_k(100), O.full_cells(PARTS), select="SELECT run, key, b, w, inn FROM cells WHERE (run, key) IN (SELECT (run, key) FROM cells WHERE inn)"))
def _colocated(spark, sf):
    rows, _ = full(spark, sf, "parts", PARTS, 100)
    return rows.where(F.exists("cells", lambda c: c["inn"])).select("run", "key", F.explode("cells").alias("c")).select("run", "key", "c.b", "c.w", "c.inn")


_FIXED = (
    "place AS (SELECT *, row_number() OVER (PARTITION BY assignment ORDER BY rank, key) AS pos FROM ranked),\n"
    "best AS (SELECT key, min(pos) AS best FROM place GROUP BY 1),\n"
    "runs_ AS (SELECT best, sum(count(*)) OVER (ORDER BY best) AS upto FROM best GROUP BY best),\n"
    "l AS (SELECT least({budget}, coalesce(min(CASE WHEN upto > {budget} THEN best END) - 1, max(best))) AS l FROM runs_)"
)
query("q_fixed_distinct", O.chain(O.ranked("parts", PARTS), _FIXED.format(budget=200), select="SELECT assignment, key, CAST(pos AS INTEGER) AS pos, CAST(l AS BIGINT) AS l FROM place, l WHERE pos <= l"))(lambda spark, sf: _fixed(spark, sf))


def _fixed(spark, sf):
    ranked = R.rank_wide(wide_weights(spark, sf, "parts", PARTS))
    sketch = S.fixed_distinct(R.to_long(ranked), 50, len(PARTS))
    length = sketch.meta.groupBy("run").agg(F.max("l").cast("bigint").alias("l"))
    return sketch.members().join(F.broadcast(length), "run").select("assignment", "key", "pos", "l")


@query("q_inclusive_fixed_size")
def _fixed_estimate(spark, sf):
    """Sum of one assignment from the sample with a fixed number of distinct keys."""
    ranked = R.rank_wide(wide_weights(spark, sf, "parts", PARTS))
    sketch = S.fixed_distinct(R.to_long(ranked), 50, len(PARTS))
    return E.total(E.inclusive_fixed(ranked, sketch, PARTS, 50, E.f_single("gross"))).withColumn("estimate", F.round("estimate", 2))


@query("q_fixed_expected")
def _fixed_expected(spark, sf):
    vectors = wide_weights(spark, sf, "parts", PARTS)
    size, taus = S.fixed_expected(vectors, 50, PARTS)
    return spark.createDataFrame([(b, float(size), float(t)) for b, t in taus.items()], "assignment string, size double, tau double")


# ---------------------------------------------------------------- estimates, one assignment


def _plain_sql(workload, names, k, family, b):
    sql = f"adj AS (SELECT e.run, key, weight AS f, {O.cdf(family, 'weight', 'rk1')} AS p, weight / {O.cdf(family, 'weight', 'rk1')} AS adjusted FROM ent e JOIN meta m ON e.run = m.run AND e.assignment = m.assignment WHERE member AND e.assignment = '{b}')"
    return O.chain(O.ranked(workload, names, family), O.bottom_k(k), sql, select=O.ROWS)


for _family in R.FAMILIES:
    query(f"q_plain_rc_{_family}", _plain_sql("part_months", MONTHS2, 200, _family, "m01"))(lambda spark, sf, f=_family: rounded(E.plain(bottom(spark, sf, "part_months", MONTHS2, 200, f), "m01")))

_HT = f"adj AS (SELECT e.run, key, weight AS f, {O.cdf('ipps', 'weight', 'rk1')} AS p, weight / {O.cdf('ipps', 'weight', 'rk1')} AS adjusted FROM ent e JOIN meta m ON e.run = m.run AND e.assignment = m.assignment WHERE e.assignment = 'src0')"
query("q_ht_poisson", O.chain(O.ranked("words", WORDS), O.ipps_tau(200), O.poisson(), _HT, select=O.ROWS))(lambda spark, sf: rounded(E.plain(poisson_words(spark, sf), "src0")))
query("q_secondary_h", O.chain(O.ranked("words", WORDS), O.ipps_tau(200), O.poisson(), _HT, select="SELECT round(sum(adjusted * length(key) / f), 3) AS estimate FROM adj"))(
    lambda spark, sf: E.secondary(E.plain(poisson_words(spark, sf), "src0"), F.length("key").cast("double")).agg(F.round(F.sum("adjusted"), 3).alias("estimate"))
)
query("q_std_error", O.chain(O.ranked("words", WORDS), O.ipps_tau(200), O.poisson(), _HT, select="SELECT round(sum(adjusted), 3) AS estimate, round(sqrt(sum(f * f * (1 - p) / (p * p))), 3) AS std_error FROM adj"))(
    lambda spark, sf: E.std_error(E.plain(poisson_words(spark, sf), "src0")).select(F.round("estimate", 3).alias("estimate"), F.round("std_error", 3).alias("std_error"))
)

# ---------------------------------------------------------------- estimates, dispersed


def _dispersed_sql(workload, names, k, estimator: str, family="ipps", joint="shared", select=O.ROWS) -> str:
    return O.chain(O.ranked(workload, names, family, joint), O.bottom_k(k), O.dispersed_cells(names), estimator, select=select)


def _top(name, workload, names, k, ell, kind, family="ipps", joint="shared"):
    sql = O.s_set(ell, family, joint) if kind == "s" else O.l_set(ell, len(names), family, joint)

    def plan(spark, sf):
        sketch = bottom(spark, sf, workload, names, k, family, joint)
        return rounded((E.s_set if kind == "s" else E.l_set)(sketch, names, ell))

    query(name, _dispersed_sql(workload, names, k, sql, family, joint))(plan)


_top("q_sset_max", "part_months", MONTHS3, 200, 1, "s")
_top("q_sset_2nd", "part_months", MONTHS3, 200, 2, "s")
_top("q_sset_min", "part_months", MONTHS3, 200, 3, "s")
_top("q_sset_max_exp", "part_months", MONTHS3, 200, 1, "s", "exp")
_top("q_lset_max", "part_months", MONTHS3, 200, 1, "l")
_top("q_lset_median", "part_months", MONTHS3, 200, 2, "l")
_top("q_lset_min", "part_months", MONTHS3, 200, 3, "l")
_top("q_lset_min_exp", "part_months", MONTHS3, 200, 3, "l", "exp")
_top("q_lset_3rd_of_6", "part_months", MONTHS6, 300, 3, "l")
_top("q_lset_words_min", "words", WORDS, 300, 4, "l")
_top("q_min_ind_s", "part_months", MONTHS2, 300, 2, "s", "ipps", "independent")
_top("q_min_ind_l", "part_months", MONTHS2, 300, 2, "l", "ipps", "independent")
_top("q_lset_ind_known_seeds", "part_months", MONTHS2, 300, 1, "l", "ipps", "independent")
_top("q_sset_max_inddiff", "part_months", MONTHS3, 200, 1, "s", "exp", "inddiff")

_TOP_VARYING = {"m01": 150, "m02": 300, "m03": 200}
query("q_lset_varying_k", _dispersed_sql("part_months", MONTHS3, _TOP_VARYING, O.l_set(3, 3, "ipps", "shared")))(lambda spark, sf: rounded(E.minimum(bottom(spark, sf, "part_months", MONTHS3, _TOP_VARYING), MONTHS3)))
query("q_sset_poisson", O.chain(O.ranked("words", WORDS), O.ipps_tau(200), O.poisson(), O.dispersed_cells(WORDS), O.s_set(1, "ipps", "shared"), select=O.ROWS))(lambda spark, sf: rounded(E.maximum(poisson_words(spark, sf), WORDS)))
query("q_lset_poisson", O.chain(O.ranked("words", WORDS), O.ipps_tau(200), O.poisson(), O.dispersed_cells(WORDS), O.l_set(4, 4, "ipps", "shared"), select=O.ROWS))(lambda spark, sf: rounded(E.minimum(poisson_words(spark, sf), WORDS)))


_POISSON = (O.ranked("words", WORDS), O.ipps_tau(200), O.poisson(), O.dispersed_cells(WORDS))
query("q_sset_poisson_min", O.chain(*_POISSON, O.s_set(4, "ipps", "shared"), select=O.ROWS))(lambda spark, sf: rounded(E.minimum(poisson_words(spark, sf), WORDS, "s")))
for _ell in (2, 3):
    query(f"q_sset_poisson_{_ell}", O.chain(*_POISSON, O.s_set(_ell, "ipps", "shared"), select=O.ROWS))(lambda spark, sf, n=_ell: rounded(E.s_set(poisson_words(spark, sf), WORDS, n)))
    query(f"q_lset_poisson_{_ell}", O.chain(*_POISSON, O.l_set(_ell, 4, "ipps", "shared"), select=O.ROWS))(lambda spark, sf, n=_ell: rounded(E.l_set(poisson_words(spark, sf), WORDS, n)))


def _l1_poisson_sql(kind: str) -> str:
    low = O.s_set(4, "ipps", "shared") if kind == "s" else O.l_set(4, 4, "ipps", "shared")
    low = low.replace("adj AS", "low AS").replace("g AS (", "gl AS (").replace("FROM g ", "FROM gl ")
    return O.chain(*_POISSON, O.s_set(1, "ipps", "shared").replace("adj AS", "high AS"), low, select="SELECT run, key, round(sum(adjusted), 3) + 0.0 AS adjusted FROM (SELECT run, key, adjusted FROM high UNION ALL SELECT run, key, -adjusted FROM low) GROUP BY 1, 2")


for _kind in ("s", "l"):
    query(f"q_l1_poisson_{_kind}", _l1_poisson_sql(_kind))(lambda spark, sf, kind=_kind: E.l1(poisson_words(spark, sf), WORDS, kind).withColumn("adjusted", F.round("adjusted", 3) + F.lit(0.0)))


def _l1_sql(workload, names, k, kind, family="ipps") -> str:
    low = O.s_set(len(names), family, "shared") if kind == "s" else O.l_set(len(names), len(names), family, "shared")
    low = low.replace("adj AS", "low AS").replace("g AS (", "gl AS (").replace("FROM g ", "FROM gl ")
    high = O.s_set(1, family, "shared").replace("adj AS", "high AS")
    both = "SELECT run, key, adjusted FROM high UNION ALL SELECT run, key, -adjusted FROM low"
    return O.chain(O.ranked(workload, names, family), O.bottom_k(k), O.dispersed_cells(names), high, low, select=f"SELECT run, key, round(sum(adjusted), 3) + 0.0 AS adjusted FROM ({both}) GROUP BY 1, 2")


for _kind in ("s", "l"):
    query(f"q_l1_{_kind}", _l1_sql("part_months", MONTHS2, 200, _kind))(
        lambda spark, sf, kind=_kind: E.l1(bottom(spark, sf, "part_months", MONTHS2, 200, early=True), MONTHS2, kind).withColumn("adjusted", F.round("adjusted", 3) + F.lit(0.0))
    )
query("q_l1_days", _l1_sql("event_days", DAYS4, 40, "l"))(lambda spark, sf: E.l1(bottom(spark, sf, "event_days", DAYS4, 40), DAYS4).withColumn("adjusted", F.round("adjusted", 3) + F.lit(0.0)))

query(
    "q_jaccard_ratio",
    O.chain(
        O.ranked("part_months", MONTHS2), O.bottom_k(300), O.dispersed_cells(MONTHS2), O.s_set(1, "ipps", "shared").replace("adj AS", "high AS"),
        O.l_set(2, 2, "ipps", "shared").replace("adj AS", "low AS").replace("g AS (", "gl AS (").replace("FROM g ", "FROM gl "),
        select="SELECT CAST(0 AS INTEGER) AS run, round(coalesce((SELECT sum(adjusted) FROM low), 0) / (SELECT sum(adjusted) FROM high), 9) AS jaccard",
    ),
)(lambda spark, sf: E.jaccard_ratio(bottom(spark, sf, "part_months", MONTHS2, 300), MONTHS2).withColumn("jaccard", F.round("jaccard", 9)))
query("q_jaccard_kmins", O.chain(_kmins_draws(MONTHS2, 100, "inddiff"), select="SELECT avg(CASE WHEN a = b THEN 1.0 ELSE 0.0 END) AS jaccard FROM (SELECT t, min(rank) FILTER (WHERE assignment = 'm01') AS a, min(rank) FILTER (WHERE assignment = 'm02') AS b FROM draws GROUP BY 1)"))(
    lambda spark, sf: E.jaccard_kmins(S.k_mins(wide_weights(spark, sf, "part_months", MONTHS2), 100, joint="inddiff"), "m01", "m02")
)


def _guarded_sql(joint: str) -> str:
    return O.chain(O.ranked("part_months", MONTHS2, joint=joint), O.bottom_k(50), select="SELECT count(DISTINCT key) AS keys FROM ent WHERE member")


@query("q_no_estimator_guard", f"SELECT CAST('refused' AS VARCHAR) AS outcome, CAST(5 AS BIGINT) AS cases, i.keys AS independent_keys, s.keys AS shared_keys FROM ({_guarded_sql('independent')}) i, ({_guarded_sql('shared')}) s")
def _guard(spark, sf):
    """Quantities of two samples that have no non-negative unbiased estimator are refused, whatever the samples hold."""
    sketch, shared = (bottom(spark, sf, "part_months", MONTHS2, 50, joint=j) for j in ("independent", "shared"))
    refused = 0
    attempts = (
        lambda: E.maximum(sketch, MONTHS2), lambda: E.l_set(S.drop_seeds(sketch), MONTHS2, 1), lambda: R.check_design("ipps", "inddiff"),
        lambda: E.s_set(shared, MONTHS2, 1, E.f_l1), lambda: E.l_set(shared, MONTHS2, 2, E.f_l1),
    )
    for attempt in attempts:
        try:
            attempt()
        except ValueError:
            refused += 1
    keys = [x.members().agg(F.count_distinct("key").alias(n)) for x, n in ((sketch, "independent_keys"), (shared, "shared_keys"))]
    return keys[0].crossJoin(F.broadcast(keys[1])).select(F.lit("refused").alias("outcome"), F.lit(refused).cast("bigint").alias("cases"), "independent_keys", "shared_keys")


# ---------------------------------------------------------------- estimates, colocated


def _inclusive(name, workload, names, k, family, joint, f, f_sql, where="any_in"):
    def plan(spark, sf):
        rows, _ = full(spark, sf, workload, names, k, family, joint)
        return rounded(E.inclusive(rows.where(F.exists("cells", lambda c: c["inn"])), f, family, joint))

    query(name, O.chain(O.ranked(workload, names, family, joint), O.bottom_k(k), O.full_cells(names), O.inclusive(family, joint, f_sql), select=O.ROWS))(plan)


for _joint, _family in (("independent", "ipps"), ("shared", "ipps"), ("inddiff", "exp"), ("shared", "exp")):
    _tag = _joint + ("_exp" if (_joint, _family) == ("shared", "exp") else "")
    for _f, _fn, _sql in (("max", E.f_max, "mx"), ("min", E.f_min, "mn"), ("l1", E.f_l1, "mx - mn"), ("single", E.f_single("m01"), "v['m01']")):
        _inclusive(f"q_inclusive_{_tag}_{_f}", "part_months", MONTHS3, 150, _family, _joint, _fn, _sql)
query("q_generic_consistent", O.chain(O.ranked("part_months", MONTHS3), O.bottom_k(150), O.full_cells(MONTHS3), O.generic("ipps", "mx"), select=O.ROWS))(
    lambda spark, sf: rounded(E.generic_consistent((x := full(spark, sf, "part_months", MONTHS3, 150))[0].where(F.exists("cells", lambda c: c["inn"])), E.f_max, "ipps", MONTHS3))
)


@query("q_inclusive_poisson", O.chain(O.ranked("words", WORDS), O.ipps_tau(200), O.poisson(), O.full_cells(WORDS), O.inclusive("ipps", "shared", "mx"), select=O.ROWS))
def _inclusive_poisson(spark, sf):
    long = long_weights(spark, sf, "words", WORDS)
    ranked = R.rank_wide(wide_weights(spark, sf, "words", WORDS))
    sketch = S.poisson(R.to_long(ranked), S.ipps_tau(long, 200), 200)
    return rounded(E.inclusive(E.colocated_summary(ranked, sketch, WORDS), E.f_max))


# ---------------------------------------------------------------- subpopulations chosen after sampling

_PART_SUMS = "JOIN part ON CAST(p_partkey AS VARCHAR) = key"
_L1_ADJ = _l1_sql("part_months", MONTHS2, 200, "l").rpartition("SELECT run, key, round")[0] + "x AS (SELECT run, key, sum(adjusted) AS adjusted FROM (SELECT run, key, adjusted FROM high UNION ALL SELECT run, key, -adjusted FROM low) GROUP BY 1, 2)\n"
_L1_ADJ = _L1_ADJ.replace("\nx AS", ",\nx AS") if "\nx AS" in _L1_ADJ else _L1_ADJ


def l1_parts(spark, sf) -> DataFrame:
    """Adjusted differences of two months by part, with the part's attributes (a join with the sample only)."""
    from seedrank.sources.tables import scan

    part = scan(spark, sf, "part").select(F.col("p_partkey").cast("string").alias("key"), "p_brand", "p_type", "p_size")
    return part.join(F.broadcast(E.l1(bottom(spark, sf, "part_months", MONTHS2, 200), MONTHS2)), "key")


query("q_subpop_brand", _L1_ADJ + f"SELECT p_brand, round(sum(adjusted), 3) AS estimate FROM x {_PART_SUMS} GROUP BY 1")(lambda spark, sf: l1_parts(spark, sf).groupBy("p_brand").agg(F.round(F.sum("adjusted"), 3).alias("estimate")))
query("q_subpop_predicate", _L1_ADJ + f"SELECT round(sum(adjusted), 3) AS estimate, count(*) AS keys FROM x {_PART_SUMS} WHERE p_size BETWEEN 10 AND 30 AND p_brand LIKE '%2'")(
    lambda spark, sf: l1_parts(spark, sf).where(F.col("p_size").between(10, 30) & F.col("p_brand").like("%2")).agg(F.round(F.sum("adjusted"), 3).alias("estimate"), F.count(F.lit(1)).alias("keys"))
)
for _how in ("rollup", "cube"):
    query(f"q_subpop_{_how}", _L1_ADJ + f"SELECT p_brand, p_type, round(sum(adjusted), 3) AS estimate FROM x {_PART_SUMS} GROUP BY {_how} (p_brand, p_type)")(
        lambda spark, sf, how=_how: getattr(l1_parts(spark, sf), how)("p_brand", "p_type").agg(F.round(F.sum("adjusted"), 3).alias("estimate"))
    )

# ---------------------------------------------------------------- exact answers


def _exact_sql(workload, names) -> str:
    m = len(names)
    return (
        f"SELECT count(*) AS keys, CAST(sum(low) AS BIGINT) AS sum_min, CAST(sum(high) AS BIGINT) AS sum_max, CAST(sum(high - low) AS BIGINT) AS sum_l1, round(sum(low) / sum(high), 9) AS jaccard "
        f"FROM (SELECT key, max(weight) AS high, CASE WHEN count(*) = {m} THEN min(weight) ELSE 0 END AS low FROM ({WORKLOADS[workload].sql}) WHERE assignment IN {O._in(names)} AND weight > 0 GROUP BY 1)"
    )


_EXACT = {
    "months_2": ("part_months", MONTHS2), "months_6": ("part_months", MONTHS6), "months_12": ("part_months", list(WORKLOADS["part_months"].names)), "days_2": ("event_days", DAYS4[:2]), "days_4": ("event_days", DAYS4),
    "days_23": ("event_days", list(WORKLOADS["event_days"].names)), "pair_days_4": ("event_pair_days", DAYS4), "high_5": ("event_high", [f"d{i:02d}" for i in range(1, 6)]), "high_23": ("event_high", list(WORKLOADS["event_high"].names)),
    "halves_gross": ("halves_part_gross", ["h1", "h2"]), "halves_suppliers": ("halves_part_suppliers", ["h1", "h2"]), "halves_lines": ("halves_brand_lines", ["h1", "h2"]), "words_2": ("words", WORDS[:2]), "words_4": ("words", WORDS),
    "years_7": ("part_years", list(WORKLOADS["part_years"].names)),
}
for _name, (_w, _r) in _EXACT.items():
    query(f"q_exact_{_name}", _exact_sql(_w, _r))(lambda spark, sf, w=_w, r=_r: X.norms(long_weights(spark, sf, w), r))
query("q_exact_lth", f"SELECT CAST(sum(coalesce(ws[3], 0)) AS BIGINT) AS total FROM (SELECT key, list_reverse_sort(list(weight)) AS ws FROM ({WORKLOADS['part_months'].sql}) WHERE assignment IN {O._in(MONTHS6)} GROUP BY 1)")(
    lambda spark, sf: X.lth_total(long_weights(spark, sf, "part_months"), MONTHS6, 3)
)
query("q_exact_heavier", f"WITH w AS ({WORKLOADS['part_months'].sql}), v AS (SELECT key, sum(weight) FILTER (WHERE assignment = 'm01') AS a, sum(weight) FILTER (WHERE assignment = 'm02') AS b FROM w GROUP BY 1) SELECT count(*) AS keys, CAST(sum(b) AS BIGINT) AS total FROM v WHERE b > coalesce(a, 0)")(
    lambda spark, sf: X.heavier_in(long_weights(spark, sf, "part_months"), "m01", "m02")
)
for _w in WORKLOADS:
    query(f"q_weights_{_w}", f"SELECT assignment, CAST(sum(weight) AS BIGINT) AS total, count(*) AS keys FROM ({WORKLOADS[_w].sql}) GROUP BY 1")(lambda spark, sf, w=_w: X.sums(long_weights(spark, sf, w)))

# ---------------------------------------------------------------- baselines


def _unweighted_sql(names, k, f) -> str:
    cells = O.dispersed_cells(names, "value")
    g = f"g AS (SELECT run, key, max(w) AS mx, min(w) AS mn, max(mt) AS mt, min(rank) AS mr FROM o GROUP BY 1, 2)"
    return O.chain(O.ranked("words", names, unit=True), O.bottom_k(k), cells, g, f"adj AS (SELECT run, key, {f} AS f, least(1.0, mt) AS p, ({f}) / least(1.0, mt) AS adjusted FROM g WHERE mr < mt AND ({f}) <> 0)", select=O.ROWS)


for _f, _fn, _sql in (("max", E.f_max, "mx"), ("min", E.f_min, "mn"), ("l1", E.f_l1, "mx - mn")):
    query(f"q_unweighted_{_f}", _unweighted_sql(WORDS, 300, _sql))(lambda spark, sf, fn=_fn: rounded(B.unweighted(B.unweighted_sketch(long_weights(spark, sf, "words", WORDS), 300), WORDS, fn)))
query(
    "q_single_primary",
    O.chain(O.ranked("part_months", MONTHS3), O.bottom_k(150), O.full_cells(MONTHS3), "g AS (SELECT run, key, max(w) AS mx, bool_or(inn AND b = 'm01') AS mine, max(CASE WHEN b = 'm01' THEN " + O.cdf("ipps", "w", "theta") + " END) AS p FROM o GROUP BY 1, 2)", "adj AS (SELECT run, key, mx AS f, p, mx / p AS adjusted FROM g WHERE mine)", select=O.ROWS),
)(lambda spark, sf: rounded(B.single_primary(full(spark, sf, "part_months", MONTHS3, 150)[0], "m01", E.f_max, "ipps")))
query(
    "q_primary_max",
    "WITH w AS (SELECT key, max(weight) AS weight FROM (" + WORKLOADS["part_months"].sql + f") WHERE assignment IN {O._in(MONTHS3)} GROUP BY 1), ranked AS (SELECT 0 AS run, 'f' AS assignment, key, CAST(weight AS DOUBLE) AS weight, {O.uniform(chr(39) + 'v1#0' + chr(39), 'key')} / weight AS rank FROM w),\n"
    + O.bottom_k(150) + f",\nadj AS (SELECT e.run, key, weight AS f, {O.cdf('ipps', 'weight', 'rk1')} AS p, weight / {O.cdf('ipps', 'weight', 'rk1')} AS adjusted FROM ent e, meta WHERE member)\n" + O.ROWS,
)(lambda spark, sf: rounded(B.primary_function(wide_weights(spark, sf, "part_months", MONTHS3), E.f_max, 150)))


@query("q_sample_uniform", f"SELECT assignment, CAST(10 * sum(weight) AS BIGINT) AS estimate FROM (SELECT * FROM ({WORKLOADS['part_months'].sql}) WHERE assignment IN {O._in(MONTHS2)}) WHERE {O.uniform(chr(39) + 'uniform' + chr(39), 'key')} < 0.1 GROUP BY 1")
def _sample_uniform(spark, sf):
    """A tenth of all keys by hash, whatever their weights: the same rows in any partitioning."""
    from seedrank.functions.seeds import uniform

    rows = long_weights(spark, sf, "part_months", MONTHS2).where(uniform("uniform", F.col("key")) < 0.1)
    return rows.groupBy("assignment").agg((F.sum("weight") * 10).alias("estimate"))

# ---------------------------------------------------------------- accuracy and size

RUNS = 5


def _cv_sql(workload, names, k, p: str, f: str, family="ipps", joint="shared", unit=False) -> str:
    tables = [O.ranked(workload, names, family, joint, runs=RUNS), O.bottom_k(k), O.full_cells(names)]
    each = O.cdf(family, "w", "theta")
    g = f"g AS (SELECT run, key, max(w) AS mx, min(w) AS mn, max(mt) AS mt, min({each}) AS p_min, product({each}) AS p_prod, max({each}) AS p_max, 1 - product(1 - {each}) AS p_any FROM o GROUP BY 1, 2)"
    return O.chain(*tables, g, select=f"SELECT round(log10(avg(sv)), 6) AS log_sv FROM (SELECT run, sum(({f}) * ({f}) * (1 / ({p}) - 1)) AS sv FROM g WHERE ({f}) > 0 GROUP BY 1)")


def log_sv(per_run: DataFrame, name: str = "log_sv") -> DataFrame:
    return per_run.agg(F.round(F.log10(F.avg("sv")), 6).alias(name))


def variance(spark, sf, workload, names, k, f, p, family="ipps", joint="shared", runs=RUNS) -> DataFrame:
    return M.conditional_variance(full(spark, sf, workload, names, k, family, joint, runs)[0], f, p)


P_MIN_L = lambda m, family="ipps", joint="shared": lambda c: E.l_set_p(c, m, family, joint)
P_MIN_S = lambda m, family="ipps", joint="shared": lambda c: E.s_set_p(c, m, family, joint)
P_MAX = lambda family="ipps": lambda c: E.s_set_p(c, 1, family, "shared")

query("q_sv_min_shared", _cv_sql("part_months", MONTHS2, 200, "p_min", "mn"))(lambda spark, sf: log_sv(variance(spark, sf, "part_months", MONTHS2, 200, E.f_min, P_MIN_L(2))))
query("q_sv_min_independent", _cv_sql("part_months", MONTHS2, 200, "p_prod", "mn", joint="independent"))(lambda spark, sf: log_sv(variance(spark, sf, "part_months", MONTHS2, 200, E.f_min, P_MIN_L(2, joint="independent"), joint="independent")))
query("q_sv_min_s", _cv_sql("part_months", MONTHS2, 200, O.cdf("ipps", "mn", "mt"), "mn"))(lambda spark, sf: log_sv(variance(spark, sf, "part_months", MONTHS2, 200, E.f_min, P_MIN_S(2))))
query("q_sv_max", _cv_sql("part_months", MONTHS2, 200, O.cdf("ipps", "mx", "mt"), "mx"))(lambda spark, sf: log_sv(variance(spark, sf, "part_months", MONTHS2, 200, E.f_max, P_MAX())))
query("q_sv_max_exp", _cv_sql("part_months", MONTHS2, 200, O.cdf("exp", "mx", "mt"), "mx", "exp"))(lambda spark, sf: log_sv(variance(spark, sf, "part_months", MONTHS2, 200, E.f_max, P_MAX("exp"), "exp")))
query("q_sv_inclusive_shared", _cv_sql("parts", PARTS, 100, "p_max", "mx"))(lambda spark, sf: log_sv(variance(spark, sf, "parts", PARTS, 100, E.f_max, lambda c: E.inclusive_p(c, "ipps", "shared"))))
query("q_sv_inclusive_independent", _cv_sql("parts", PARTS, 100, "p_any", "mx", joint="independent"))(lambda spark, sf: log_sv(variance(spark, sf, "parts", PARTS, 100, E.f_max, lambda c: E.inclusive_p(c, "ipps", "independent"), joint="independent")))

_SHARE = "SELECT round(avg(n / {km}), 9) AS sharing_index FROM (SELECT run, count(DISTINCT key) AS n FROM ent WHERE member GROUP BY 1)"
for _w, _names in (("parts", PARTS), ("pairs", PAIRS), ("money", list(WORKLOADS["money"].names)), ("ohlc", list(WORKLOADS["ohlc"].names)), ("event_day3", list(WORKLOADS["event_day3"].names))):
    for _joint in ("shared", "independent"):
        _k = 20 if _w in ("ohlc", "event_day3") else 100
        query(f"q_sharing_{_w}_{_joint}", O.chain(O.ranked(_w, _names, joint=_joint, runs=RUNS), O.bottom_k(_k), select=_SHARE.format(km=float(_k * len(_names)))))(
            lambda spark, sf, w=_w, n=_names, j=_joint, k=_k: M.sharing_index(bottom(spark, sf, w, n, k, joint=j, runs=RUNS), k, len(n)).withColumn("sharing_index", F.round("sharing_index", 9))
        )
query("q_combined_size", O.chain(O.ranked("parts", PARTS, runs=RUNS), O.bottom_k(100), select="SELECT run, count(DISTINCT key) AS keys FROM ent WHERE member GROUP BY 1"))(lambda spark, sf: M.combined_size(bottom(spark, sf, "parts", PARTS, 100, runs=RUNS)))
query(
    "q_usable_for_max", O.chain(O.ranked("part_months", MONTHS3, runs=RUNS), O.bottom_k(100), O.dispersed_cells(MONTHS3), O.s_set(1, "ipps", "shared"), select="SELECT run, count(*) AS keys FROM adj GROUP BY 1")
)(lambda spark, sf: M.usable_for_max(bottom(spark, sf, "part_months", MONTHS3, 100, runs=RUNS), MONTHS3))


@query("q_sigma_v")
def _sigma(spark, sf):
    """Squared errors of the estimated maxima over runs, absolute, normalised and against the bound."""
    sketch, k, runs = bottom(spark, sf, "part_months", MONTHS2, 100, runs=20), 100, 20
    exact = X.per_key(long_weights(spark, sf, "part_months"), MONTHS2).select("key", F.col("high").alias("f"))
    return M.sigma_v(E.maximum(sketch, MONTHS2), exact, runs).withColumn("bound", (k - 2) * F.col("nsv"))


_BOUND_NAMES, _BOUND_K = MONTHS3, 100
_LESS = " + 1e-9 * (1 + abs({0}))"
_BOUND_SQL = O.chain(
    O.ranked("part_months", _BOUND_NAMES, runs=3), O.bottom_k(_BOUND_K), O.full_cells(_BOUND_NAMES),
    f"tops AS (SELECT run, key, max(weight) AS weight, min(rank) AS rank FROM ranked GROUP BY 1, 2)",
    f"tp AS (SELECT *, row_number() OVER (PARTITION BY run ORDER BY rank, key) AS pos FROM tops)",
    f"tt AS (SELECT run, max(CASE WHEN pos = {_BOUND_K} THEN rank END) AS a, max(CASE WHEN pos = {_BOUND_K} + 1 THEN rank END) AS b FROM tp GROUP BY 1)",
    f"g AS (SELECT run, key, max(w) AS h, min(w) AS l, min(theta) AS mt, min({O.cdf('ipps', 'w', 'theta')}) AS pl, max({O.cdf('ipps', 'w', 'theta')}) AS incl, {O.cdf('ipps', 'max(w)', 'min(theta)')} AS ph, {O.cdf('ipps', 'min(w)', 'min(theta)')} AS ps FROM o GROUP BY 1, 2)",
    f"x AS (SELECT g.*, {O.cdf('ipps', 'h', 'CASE WHEN p.rank < b THEN b ELSE a END')} AS pt FROM g JOIN tp p USING (run, key) JOIN tt USING (run))",
    "v AS (SELECT *, h * h * (1 / ph - 1) AS vh, CASE WHEN l > 0 THEN l * l * (1 / pl - 1) ELSE 0 END AS vl, h * h * (1 / pt - 1) AS vt, h * h * (1 / incl - 1) AS vc, (h - l) * (h - l) * (1 / incl - 1) AS vr, CASE WHEN l > 0 THEN pl ELSE 0 END AS bo, h / ph AS ah, CASE WHEN l > 0 THEN l / pl ELSE 0 END AS al FROM x)",
    "y AS (SELECT *, bo * (ah - al) * (ah - al) + (ph - bo) * ah * ah - (h - l) * (h - l) AS vd FROM v)",
    select=(
        "SELECT (SELECT count(*) FROM (SELECT run, key, max(" + O.cdf("ipps", "w", "theta") + ") AS p FROM o GROUP BY 1, 2) a JOIN y USING (run, key) WHERE a.p > incl + 1e-12) AS plain_above_inclusive, "
        "count(*) FILTER (WHERE ph > incl + 1e-12) AS generic_above_inclusive, count(*) FILTER (WHERE ps > pl + 1e-12) AS s_above_l, count(*) FILTER (WHERE ps > ph + 1e-12) AS min_above_max, "
        f"count(*) FILTER (WHERE vh > vt{_LESS.format('vt')}) AS max_above_primary, count(*) FILTER (WHERE vc > vh{_LESS.format('vh')}) AS colocated_above_dispersed, "
        f"count(*) FILTER (WHERE vr > vc{_LESS.format('vc')}) AS colocated_l1_above_max, count(*) FILTER (WHERE vd > vh + vl{_LESS.format('vh + vl')}) AS l1_above_sum, "
        "count(*) FILTER (WHERE al > ah * (1 + 1e-9)) AS l1_negative FROM y"
    ),
)


@query("q_bounds", _BOUND_SQL)
def _bounds(spark, sf):
    """Keys and runs that break what theory says of probabilities and variances: none."""
    rows, _ = full(spark, sf, "part_months", _BOUND_NAMES, _BOUND_K, runs=3)
    primary = S.bottom_k(R.min_rank(ranked_long(spark, sf, "part_months", _BOUND_NAMES, runs=3), _BOUND_NAMES).withColumn("assignment", F.lit("max")).withColumn("seed", F.lit(None).cast("double")), _BOUND_K)
    return M.bound_violations(rows, "ipps", primary.meta)


# Poisson samples of the same expected size beside bottom-k ones, by the sum of variances of one assignment
_SAME_KS = (25, 50, 100, 200, 400)


def _same_size_sql(k: int) -> str:
    pois = O.chain(O.ranked("words", WORDS[:1]), O.ipps_tau(k), select=f"SELECT sum(weight * weight * (1 / {O.cdf('ipps', 'weight', 'tau')} - 1)) AS v FROM w JOIN tau USING (assignment) WHERE weight > 0")
    return f"SELECT CAST({k} AS INTEGER) AS k, round(log10(a.v) - log10(b.v0), 5) AS log_ratio FROM ({pois}) a, (SELECT v0 FROM cs WHERE k = {k}) b"


@query("q_d9_poisson_over_bottomk", O.chain(*O.sweep("c", "words", WORDS[:1], _SAME_KS), O.sweep_sums("c", WORDS[:1], [("plain_0", WORDS[:1])]), select="\nUNION ALL ".join(_same_size_sql(k) for k in _SAME_KS)))
def _same_size(spark, sf):
    from seedrank.operators.sweeps import Sweep, flat
    from seedrank.sources.store import staged

    weights = staged(flat(long_weights(spark, sf, "words", WORDS[:1]), WORDS[:1]))
    long = weights.select(F.lit(WORDS[0]).alias("assignment"), "key", F.col("w0").alias("weight"))
    own = Sweep(weights, WORDS[:1], list(_SAME_KS)).sums([("plain_0", WORDS[:1])])
    tau = None
    for k in _SAME_KS:
        one = S.ipps_tau(long, k).select(F.lit(k).alias("k"), "tau")
        tau = one if tau is None else tau.unionByName(one)
    pois = weights.crossJoin(F.broadcast(tau)).groupBy("k").agg(F.sum(M.key_variance(F.col("w0"), R.cdf("ipps", F.col("w0"), F.col("tau")))).alias("v"))
    return pois.join(F.broadcast(own), "k").select("k", F.round(F.log10("v") - F.log10("v0"), 5).alias("log_ratio"))


# functions outside the template: their parts are estimated by themselves
query(
    "q_linear_combination",
    O.chain(O.ranked("part_months", MONTHS2), O.bottom_k(200), O.dispersed_cells(MONTHS2), O.s_set(1, "ipps", "shared").replace("adj AS", "high AS"), O.l_set(2, 2, "ipps", "shared").replace("adj AS", "low AS").replace("g AS (", "gl AS (").replace("FROM g ", "FROM gl "),
            select="SELECT round(2 * (SELECT sum(adjusted) FROM high) + 3 * (SELECT sum(adjusted) FROM low), 3) AS estimate"),
)(lambda spark, sf: E.linear_combination([(2, E.maximum(s := bottom(spark, sf, "part_months", MONTHS2, 200), MONTHS2)), (3, E.minimum(s, MONTHS2))]).agg(F.round(F.sum("adjusted"), 3).alias("estimate")))
query("q_support_check", f"SELECT count(*) AS keys FROM (SELECT key, max(weight) AS w FROM ({WORKLOADS['parts'].sql}) GROUP BY 1) WHERE CAST(key AS BIGINT) > 0 AND w <= 0")(
    lambda spark, sf: spark.range(1).select(F.lit(E.check_support(wide_weights(spark, sf, "parts"), F.col("key").cast("bigint"))).cast("bigint").alias("keys"))
)


# the experiments, applications and the relational and streaming surface register theirs as well
from seedrank import applications, experiments  # noqa: E402, F401
