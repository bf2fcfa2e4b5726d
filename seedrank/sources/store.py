"""Saving and loading samples, their exchange as JSON or CSV, and intermediate tables."""

from __future__ import annotations

import atexit
import contextlib
import json
import shutil
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

from seedrank.operators.sketch import Sketch


def save(sketch: Sketch, path: str, summary_id: str) -> None:
    """Entries and thresholds as Parquet by summary, with the design beside them."""
    from pyspark.sql import functions as F

    tag = F.lit(summary_id).alias("summary_id")
    sketch.entries.select("*", tag).write.mode("append").partitionBy("summary_id").parquet(f"{path}/entries")
    sketch.meta.select("*", tag).write.mode("append").partitionBy("summary_id").parquet(f"{path}/meta")
    design = json.dumps({"k": sketch.k, "shape": sketch.shape, "family": sketch.family, "joint": sketch.joint, "salt": sketch.salt, "known_seeds": sketch.known_seeds})
    spark = sketch.entries.sparkSession
    spark.createDataFrame([(design, summary_id)], "design string, summary_id string").write.mode("append").partitionBy("summary_id").parquet(f"{path}/design")


def load(spark: SparkSession, path: str, summary_id: str) -> Sketch:
    part = lambda n: spark.read.parquet(f"{path}/{n}").where(f"summary_id = '{summary_id}'").drop("summary_id")
    design = json.loads(part("design").first()[0])
    return Sketch(part("entries"), part("meta"), **design)


def export(sketch: Sketch, path: str, kind: str = "json") -> None:
    """Entries and thresholds as text, for other programs."""
    for name, rows in (("entries", sketch.entries), ("meta", sketch.meta)):
        writer = rows.write.mode("overwrite")
        (writer.json if kind == "json" else lambda p: writer.csv(p, header=True))(f"{path}/{name}")


def import_(spark: SparkSession, path: str, design: Sketch, kind: str = "json") -> Sketch:
    """What ``export`` wrote, read with the columns of ``design``, a sketch of the same shape."""
    from dataclasses import replace

    from pyspark.sql import functions as F

    def rows(name: str, like: DataFrame) -> DataFrame:
        reader = spark.read.schema(", ".join(f"`{c}` string" for c in like.columns))
        found = (reader.json if kind == "json" else lambda p: reader.csv(p, header=True))(f"{path}/{name}")
        return found.select(*[F.col(f"`{f.name}`").cast(f.dataType).alias(f.name) for f in like.schema])

    return replace(design, entries=rows("entries", design.entries), meta=rows("meta", design.meta))


def new_folder(spark: SparkSession, kind: str) -> str:
    """A new folder where all executors can write: beside the checkpoints, or else the warehouse, of the session.

    Only a session of a single process without a checkpoint folder gets a temporary one.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    master = spark.sparkContext.master
    if not base and master.startswith("local") and not master.startswith("local-cluster"):
        base = tempfile.mkdtemp(prefix="samples-")
        atexit.register(shutil.rmtree, base, ignore_errors=True)
    return f"{(base or spark.conf.get('spark.sql.warehouse.dir')).rstrip('/')}/{kind}/{uuid.uuid4().hex}"


#: Rows of a file of an intermediate table; a file is the least that a task reads.
FILE_ROWS = 1 << 18


@contextlib.contextmanager
def small_tasks(spark: SparkSession, each: int = 8) -> Iterator[None]:
    """For plans that are run inside: files are dealt to ``each`` tasks for a core or so, where there are as many, so that
    long tasks end together."""
    name = "spark.sql.files.minPartitionNum"
    before = spark.conf.get(name, None)
    spark.conf.set(name, str(each * spark.sparkContext.defaultParallelism))
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def staged(rows: DataFrame) -> DataFrame:
    """``rows`` written once and read from there, for plans that need them more than once."""
    path = new_folder(rows.sparkSession, "staged")
    rows.write.option("maxRecordsPerFile", FILE_ROWS).parquet(path)
    return rows.sparkSession.read.schema(rows.schema).parquet(path)
