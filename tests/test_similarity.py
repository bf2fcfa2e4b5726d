"""Similarity of all pairs in NumPy against the plain plans, and the rows that it hands on."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from seedrank.operators import estimators as E
from seedrank.operators import relops, similarity
from seedrank.operators import sketch as S


@pytest.fixture(scope="module")
def weights(spark):
    """40 unlike assignments, and 30 equal ones."""
    rows = [(f"d{d}", f"w{w}", (d * w + d + w // 3) % 5) for d in range(40) for w in range(12)] + [(f"copy{c}", f"w{w}", w % 3) for c in range(30) for w in range(12)]
    return spark.createDataFrame(rows, "assignment string, key string, weight long").cache()


def _pairs(weights, k):
    rows = E.jaccard_all_pairs(S.k_mins_of_long(weights, k), k).collect()
    return {(r["a"], r["b"]): round(r["jaccard"] * k) for r in rows}


@pytest.fixture
def small(monkeypatch):
    """Several tiles, chunks and rounds for few rows."""
    for name, value in (("BLOCK", 16), ("SMALL_BLOCK", 8), ("CHUNK", 32), ("KEPT", 8), ("HELD", 64)):
        monkeypatch.setattr(similarity, name, value)


def test_least_ranks_are_those_of_the_plain_plan(weights, small):
    got = {(r["assignment"], r["t"]): r["rank"] for r in similarity.k_mins_rows(similarity.least_ranks(weights, 8)).collect()}
    plain = {(r["assignment"], r["t"]): r["rank"] for r in S.k_mins_of_long(weights, 8).collect()}
    assert got.keys() == plain.keys() and all(np.isclose(got[x], plain[x], rtol=1e-14) for x in got)


def test_links_of_all_pairs_are_counted_without_making_them(weights, small):
    k, pairs = 8, _pairs(weights, 8)
    got = {r["assignment"]: (r["n_links"], r["similarity"]) for r in similarity.link_counts(similarity.least_ranks(weights, k).cache(), k).collect()}
    mine = lambda x: [n for p, n in pairs.items() if x in p]
    assert got == {x: (len(mine(x)), sum(mine(x)) / k) for x in got} and len(got) == 70


@pytest.mark.parametrize("need", [1, 3, 4, 7, 8])
def test_pairs_of_so_many_draws_are_found_with_exact_sums(weights, small, need):
    k = 8
    expected = {p: n for p, n in _pairs(weights, k).items() if n >= need}
    found = similarity.close_pairs(similarity.least_ranks(weights, k).cache(), k, need).cache()
    got = similarity.exact_similarity(found, weights).collect()
    assert {(r["a"], r["b"]): r["draws"] for r in got} == expected and len(got) == len(expected)
    low = {(r["a"], r["b"]): r["low"] for r in relops.pairs(weights).groupBy("a", "b").agg(F.sum(F.least("wa", "wb")).alias("low")).collect()}
    assert all(r["low"] == low[r["a"], r["b"]] for r in got)


@pytest.mark.parametrize("square", [3000, 1])
def test_sums_of_minima_are_those_of_all_pairs(weights, small, monkeypatch, square):
    monkeypatch.setattr(similarity, "SQUARE", square)
    got = {(r["a"], r["b"]): r["low"] for r in similarity.sums_of_minima(weights).collect()}
    plain = relops.pairs(weights).groupBy("a", "b").agg(F.sum(F.least("wa", "wb")).alias("low"))
    assert got == {(r["a"], r["b"]): r["low"] for r in plain.collect()}


def test_equal_assignments_stand_for_each_other(weights):
    got = {r["assignment"]: r["rep"] for r in similarity.equal_assignments(weights).collect()}
    assert all(got[f"copy{c}"] == "copy0" for c in range(30)) and got["d1"] == "d1"


def test_document_queries_have_a_row_for_each_document_or_copy(spark, sf):
    from seedrank.queries import QUERIES

    assert QUERIES["q_w17_document_similarity"](spark, sf).columns == ["doc_id", "class_id", "n_links", "similarity"]
    got = QUERIES["q_w17_similar_documents"](spark, sf).toPandas()
    copies = set(got.b[got.equal])
    assert len(copies) == got.equal.sum() > 0 and not copies & (set(got.a) | set(got.b[~got.equal]))
