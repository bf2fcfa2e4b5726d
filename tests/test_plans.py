"""What the physical plans must and must not hold, and that streams agree with batches."""

import io
from contextlib import redirect_stdout

import pytest
from pyspark.sql import functions as F

from seedrank.operators import estimators as E
from seedrank.queries import MONTHS2, bottom
from seedrank.streaming import windows


def plan(df) -> str:
    out = io.StringIO()
    with redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def test_sampling_prunes_before_the_shuffle(spark, sf):
    text = plan(bottom(spark, sf, "part_months", MONTHS2, 200).entries)
    assert "WindowGroupLimit" in text
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text
    assert "ReadSchema: struct<l_partkey:bigint,l_shipdate:timestamp_ntz>" in text


def test_estimates_read_the_data_once_and_join_nothing(spark, sf):
    text = plan(E.l1(bottom(spark, sf, "part_months", MONTHS2, 200), MONTHS2))
    assert "Join" not in text and text.count("Location: InMemoryFileIndex") == 1
    assert "Python" not in text and "Pandas" not in text and "Arrow" not in text


@pytest.mark.parametrize("k", [200, 2000])
def test_no_task_sorts_a_whole_assignment(spark, sf, k):
    """Up to the limit of Spark's pruning by the window limit, beyond it by parts of each assignment."""
    from seedrank.functions.ranks import rank_long
    from seedrank.operators import sketch as S
    from seedrank.plans.workloads import long_weights

    weights = long_weights(spark, sf, "part_months")
    for rows in (S.bottom_k(rank_long(weights), k).entries, S.ipps_tau(weights, k), S.fixed_distinct(rank_long(weights), k // 4, 4).entries):
        text = plan(rows)
        assert ("WindowGroupLimit" in text) if k < 1000 else ("part_" in text and "WindowGroupLimit" not in text)


@pytest.mark.parametrize("early", [None, False, True])
def test_large_samples_are_those_of_a_sort(spark, early):
    from seedrank.functions.ranks import rank_long
    from seedrank.operators.sketch import bottom_k

    rows = spark.range(6000).selectExpr("CASE WHEN id % 3 = 0 THEN 'a' ELSE 'b' END AS assignment", "CAST(id AS STRING) AS key", "CAST(1 + id % 7 AS DOUBLE) AS weight")
    ranked = rank_long(rows)
    got = {(r["assignment"], r["key"], r["pos"]) for r in bottom_k(ranked, 1500, early=early).entries.collect()}
    frame = ranked.toPandas().sort_values(["assignment", "rank", "key"])
    frame["pos"] = frame.groupby("assignment").cumcount() + 1
    assert got == {(r.assignment, r.key, r.pos) for r in frame[frame.pos <= 1501].itertuples()}


def test_an_experiment_reads_its_data_once(spark, sf):
    from seedrank.experiments import weights_of
    from seedrank.operators.sweeps import Sweep
    from seedrank.plans.workloads import long_weights

    names = ["m01", "m02"]
    assert plan(long_weights(spark, sf, "part_months", names)).count("lineitem") == plan(long_weights(spark, sf, "part_months", names)).count("Location: InMemoryFileIndex")
    text = plan(Sweep(weights_of(spark, sf, "part_months", names), names, [10, 50], runs=3).sums([("min_l", names), ("max", names)]))
    assert "lineitem" not in text and text.count("Location: InMemoryFileIndex") == 1 and "BroadcastHashJoin" in text


def test_filters_reach_the_scan(spark, sf):
    from seedrank.plans.workloads import long_weights

    assert "GreaterThanOrEqual(ts" in plan(long_weights(spark, sf, "event_days"))


@pytest.mark.parametrize("pieces", [1, 4])
def test_stream_of_several_files_equals_the_batch(spark, sf, tmp_path, pieces):
    events = spark.read.parquet(f"{sf}/events.parquet")
    for i in range(pieces):  # in order of time, so that nothing is late
        lo, hi = 1 + i * 30 // pieces, 1 + (i + 1) * 30 // pieces
        part = events.where((F.dayofmonth("ts") >= lo) & (F.dayofmonth("ts") < (hi if i < pieces - 1 else 99)))
        part.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = windows.window_weights(windows.event_stream(spark, str(tmp_path / "in"), "*.parquet", "1 hour"))
    windows.run_to_end(stream, windows.TableSink(str(tmp_path / "rows")), str(tmp_path / "cp"))
    got = {tuple(r) for r in spark.read.parquet(str(tmp_path / "rows")).select("assignment", "key", "weight").collect()}
    whole = windows.window_weights(events.withColumn("at", F.col("ts").cast("timestamp")))
    expected = {tuple(r) for r in whole.collect()}
    assert got <= expected
    assert {a for a, _, _ in expected} - {a for a, _, _ in got} <= {max(a for a, _, _ in expected)}


def test_late_rows_are_dropped_and_counted(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    late = events.where(F.dayofmonth("ts") == 2).limit(7)
    # a batch drops what was late already when the batch before it began
    for i, part in enumerate((events.where(F.dayofmonth("ts") >= 20), events.where(F.dayofmonth("ts") >= 28).limit(3), late)):
        part.coalesce(1).write.parquet(str(tmp_path / "in" / f"p={i}"))
    stream = windows.window_weights(windows.event_stream(spark, str(tmp_path / "in" / "*"), "*.parquet", "1 hour", per_batch=1))
    done = windows.run_to_end(stream, windows.TableSink(str(tmp_path / "rows")), str(tmp_path / "cp"))
    assert done.rows == events.where(F.dayofmonth("ts") >= 20).count() + 10 and done.late == 7
    assert spark.read.parquet(str(tmp_path / "rows")).where("assignment < '2024-01-20'").count() == 0


def test_a_replay_closes_every_window_by_itself(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet")
    got = windows.replay_windows(spark, sf)
    assert "events.parquet" not in plan(got) and got.count() == events.select(F.to_date("ts"), "user_id").distinct().count()


def test_repeated_events_count_once(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet").limit(500)
    events.unionByName(events).coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = windows.without_repeats(windows.event_stream(spark, str(tmp_path / "in"), "*.parquet", "40 days"))
    windows.run_to_end(stream.select("event_id"), windows.TableSink(str(tmp_path / "rows")), str(tmp_path / "cp"))
    assert spark.read.parquet(str(tmp_path / "rows")).count() == events.select("event_id").distinct().count()


def test_state_of_a_stream_holds_the_sample(spark, tmp_path):
    from seedrank.functions.ranks import rank_long
    from seedrank.operators.sketch import bottom_k
    from seedrank.streaming import state

    rows = spark.createDataFrame([(b, f"k{i}", float((i * ord(b)) % 29 + 1)) for b in "ab" for i in range(300)], "assignment string, key string, weight double")
    for part in range(3):
        rows.where(F.pmod(F.crc32(F.col("key").cast("binary")), F.lit(3)) == part).coalesce(1).write.parquet(str(tmp_path / "in" / f"p={part}"))
    source = spark.readStream.schema("assignment string, key string, weight double").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in" / "*"))
    query = state.maintained(source, 20).writeStream.outputMode("update").foreachBatch(windows.TableSink(str(tmp_path / "rows"))).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    query.awaitTermination()
    got = {(r["assignment"], r["pos"], r["key"]) for r in state.latest(spark.read.parquet(str(tmp_path / "rows"))).collect()}
    assert got == {(r["assignment"], r["pos"], r["key"]) for r in bottom_k(rank_long(rows), 20).entries.collect()}
