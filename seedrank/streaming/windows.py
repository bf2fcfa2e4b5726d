"""Samples of event streams: windows are assignments, and final sums of a window are sampled.

Ranks need the final weight of a key, so sums come first and leave the stream once the watermark has
passed their window.  Seeds are hashes of keys; windows of different streams are coordinated all the same.
A replay of a bounded table ends with an event far in the future, so that the stream itself closes every
window.  Rows that come after the watermark has passed are dropped, and counted.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seedrank.functions import ranks as R
from seedrank.operators import sketch as S
from seedrank.sources.store import new_folder
from seedrank.sources.tables import cents

#: A time after all events, at which a bounded replay ends.
END_OF_TIME = "9000-01-01 00:00:00"


def event_stream(spark: SparkSession, path: str, glob: str = "events.parquet", delay: str = "1 hour", last: str | None = None, per_batch: int | None = None) -> DataFrame:
    """Events with a watermark.  Times without a zone are read as UTC, since a watermark needs instants.

    ``last``: a folder with further events, such as ``closing_event`` writes; ``per_batch``: files that a batch takes.
    """
    schema = spark.read.option("pathGlobFilter", glob).parquet(path).schema
    reader = spark.readStream.schema(schema)
    rows = (reader if per_batch is None else reader.option("maxFilesPerTrigger", per_batch)).option("pathGlobFilter", glob).parquet(path)
    if last is not None:
        rows = rows.unionByName(spark.readStream.schema(schema).parquet(last))
    return rows.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", delay)


def closing_event(spark: SparkSession, path: str, folder: str, glob: str = "events.parquet") -> str:
    """A folder with one event at the end of time: the watermark that follows it closes all windows but its own."""
    schema = spark.read.option("pathGlobFilter", glob).parquet(path).schema
    row = spark.range(1).select(*[(F.lit(END_OF_TIME) if f.name == "ts" else F.lit(None)).cast(f.dataType).alias(f.name) for f in schema])
    row.write.parquet(f"{folder}/closing")
    return f"{folder}/closing"


def without_repeats(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def window_weights(events: DataFrame, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """(assignment, key, weight): sums of a window, emitted once when it is over."""
    window = F.window("at", length, slide) if slide else F.window("at", length)
    sums = events.groupBy(window.alias("w"), F.col("user_id").cast("string").alias("key")).agg(F.sum(cents(F.col("value"))).alias("weight"))
    return sums.select(F.date_format("w.start", "yyyy-MM-dd").alias("assignment"), "key", "weight")


def session_weights(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """(assignment, key, weight): sums of each user's sessions; the day that a session begins is its assignment."""
    sums = events.groupBy(F.session_window("at", gap).alias("w"), F.col("user_id").cast("string").alias("key")).agg(F.sum(cents(F.col("value"))).alias("weight"))
    return sums.select(F.date_format("w.start", "yyyy-MM-dd").alias("assignment"), F.concat_ws("|", "key", F.unix_timestamp("w.start").cast("string")).alias("key"), "weight")


def with_attributes(weights: DataFrame, static: DataFrame) -> DataFrame:
    """A stream joined with a static table of attributes by key."""
    return weights.join(static, "key", "left")


@dataclass(frozen=True)
class Replay:
    """What a finished stream has read, and how many rows it dropped because they came too late."""

    rows: int
    late: int


def run_to_end(stream: DataFrame, each: Callable[[DataFrame, int], None], checkpoint: str) -> Replay:
    """Everything that is there now, in batches, and then stop; ``each`` gets a batch once (repeats have its number)."""
    query = stream.writeStream.outputMode("append").foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    done = query.recentProgress
    return Replay(sum(p["numInputRows"] for p in done), sum(op.get("numRowsDroppedByWatermark", 0) for p in done for op in p["stateOperators"]))


class SketchSink:
    """Keeps a bottom-k sample of every window: each batch's candidates are written under its number, and
    a read takes the k+1 least of all batches.  A repeated batch overwrites itself, so nothing counts twice."""

    def __init__(self, spark: SparkSession, path: str, k: int, family: str = "ipps", salt: str = "v1"):
        self.spark, self.path, self.k, self.family, self.salt = spark, path, k, family, salt

    def __call__(self, batch: DataFrame, number: int) -> None:
        kept = S.bottom_k(R.rank_long(batch, self.family, "shared", self.salt), self.k, self.family, "shared", self.salt).entries
        kept.drop(*S.SAMPLED).write.mode("overwrite").parquet(f"{self.path}/batch={number}")

    def sketch(self) -> S.Sketch:
        rows = self.spark.read.parquet(self.path).drop("batch")
        return S.bottom_k(rows, self.k, self.family, "shared", self.salt)


class TableSink:
    """Appends final rows, batch by batch."""

    def __init__(self, path: str):
        self.path = path

    def __call__(self, batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{self.path}/batch={number}")


def _replayed(spark: SparkSession, weights: Callable[[DataFrame], DataFrame], sf_dir: str, sink, folder: str, where=None) -> None:
    """Run the events table through the stream to its end; nothing of it is late."""
    events = event_stream(spark, sf_dir, delay="0 seconds", last=closing_event(spark, sf_dir, folder))
    if where is not None:
        events = events.where(where | (F.col("at") >= F.lit(END_OF_TIME).cast("timestamp")))
    run_to_end(weights(events), sink, f"{folder}/checkpoint")


def _read(spark: SparkSession, folder: str, schema: str = "assignment string, key string, weight bigint") -> DataFrame:
    return spark.read.schema(schema).parquet(f"{folder}/rows").select(*[c.split()[0] for c in schema.split(", ")])


def replay_windows(spark: SparkSession, sf_dir: str, length: str = "1 day", slide: str | None = None) -> DataFrame:
    folder = new_folder(spark, "streams")
    _replayed(spark, lambda e: window_weights(e, length, slide), sf_dir, TableSink(f"{folder}/rows"), folder)
    return _read(spark, folder).select(F.col("assignment").alias("day"), "key", "weight")


def replay_sessions(spark: SparkSession, sf_dir: str, gap: str = "6 hours") -> DataFrame:
    folder = new_folder(spark, "streams")
    _replayed(spark, lambda e: session_weights(e, gap), sf_dir, TableSink(f"{folder}/rows"), folder)
    return _read(spark, folder)


def replay_with_attributes(spark: SparkSession, sf_dir: str, static: DataFrame) -> DataFrame:
    """Daily sums with the columns of a static table by key, joined inside the stream."""
    folder = new_folder(spark, "streams")
    _replayed(spark, lambda e: with_attributes(window_weights(e), static), sf_dir, TableSink(f"{folder}/rows"), folder)
    more = "".join(f", {f.name} {f.dataType.simpleString()}" for f in static.schema if f.name != "key")
    return _read(spark, folder, "assignment string, key string, weight bigint" + more)


def replay_sketch(spark: SparkSession, sf_dir: str, k: int, where=None) -> S.Sketch:
    """Samples of the days; ``where`` keeps to some events, as a stream of its own would have them."""
    folder = new_folder(spark, "streams")
    sink = SketchSink(spark, f"{folder}/sketch", k)
    _replayed(spark, window_weights, sf_dir, sink, folder, where)
    return sink.sketch()
