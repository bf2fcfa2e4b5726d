"""Seeds of whole columns, and sweeps that count the keys outside of samples by their weights."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from seedrank.functions import draws, seeds


def test_seeds_of_columns_are_those_of_rows(spark):
    keys = ["", "a", "12|7", "é€", "x" * 50, "y" * 55, "z" * 300, *[f"key {i}" for i in range(500)]] * 20
    for prefix in ("v1#0|", "v1#24|m01|", "p" * 54 + "|", "q" * 70 + "|"):
        rows = spark.createDataFrame([(k,) for k in keys], "key string").select(seeds.uniform(F.lit(prefix[:-1]), F.col("key")).alias("u"))
        assert np.array_equal(draws.Keys(pa.array(keys)[0:]).uniform(prefix.encode()), rows.toPandas().u.to_numpy())
    assert np.array_equal(draws.Keys(pa.array(keys)[3:9]).uniform(b"v|"), draws.Keys(pa.array(keys[3:9])).uniform(b"v|"))


@pytest.mark.parametrize("joint", ["shared", "independent"])
def test_keys_of_equal_weights_meet_the_thresholds_once(spark, joint):
    from seedrank.operators.sweeps import Sweep, flat
    from seedrank.sources.store import staged

    long = spark.range(5000).select(F.explode(F.array(F.lit("a"), F.lit("b"))).alias("assignment"), F.concat(F.lit("k"), F.col("id")).alias("key"), (F.col("id") % 7 + 1).alias("weight"))
    sweep = Sweep(staged(flat(long, ["a", "b"])), ["a", "b"], [5, 10], "ipps", joint, 2)
    cells = sweep.cells().groupBy("run", "k").agg(F.sum("times").alias("keys"), F.count(F.lit(1)).alias("rows")).collect()
    assert len(cells) == 4 and all(r["keys"] == 5000 and r["rows"] <= 7 + 2 * r["k"] for r in cells)


@pytest.mark.parametrize("shared", [True, False])
@pytest.mark.parametrize("bound", [1e-4, 0.3, np.inf])
def test_kept_draws_are_all_below_a_bound_and_few_are_digested_whole(monkeypatch, shared, bound):
    monkeypatch.setattr(draws, "STEP", 700)
    whole = []
    monkeypatch.setattr(draws, "_two_words", lambda words, n, f=draws._two_words: whole.append(n) or f(words, n))
    keys, names = [*[f"{i}|{i % 7}" for i in range(5000)], "y" * 55, "z" * 300], ["a", "b"]
    weights = [np.arange(len(keys)) % 5 / 4.0, np.ones(len(keys))]
    rows = pa.RecordBatch.from_arrays([pa.array(keys), *map(pa.array, weights)], ["key", "w0", "w1"])
    found = pa.Table.from_batches(draws.kept_draws(names, "v1", 3, shared, False, [bound, bound])(rows.slice(i, 999) for i in range(0, len(keys), 999))).to_pandas()
    assert bool(whole) == (bound > 1e-3)
    u = {(r, b): draws.Keys(pa.array(keys)).uniform(f"v1#{r}|{'' if shared else b + '|'}".encode()) for r in range(3) for b in names}
    expected = [(r, keys[i], u[r, "a"][i], u[r, "b"][i]) for r in range(3) for i in range(len(keys)) if any(w[i] > 0 and u[r, b][i] < bound * w[i] for b, w in zip(names, weights, strict=True))]
    assert sorted(found[["run", "key", "u0", "u1"]].itertuples(index=False, name=None)) == sorted(expected)


def test_a_large_table_is_drawn_in_small_tasks(spark, monkeypatch):
    from seedrank.sources import store

    monkeypatch.setattr(store, "FILE_ROWS", 100)
    rows = store.staged(spark.range(0, 4000, 1, 1))
    with store.small_tasks(spark):
        inside = rows.where("id >= 0").rdd.getNumPartitions()
    assert inside >= 8 > 0 and spark.conf.get("spark.sql.files.minPartitionNum", None) is None
