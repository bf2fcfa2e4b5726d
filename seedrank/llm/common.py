"""Helpers that the corpus operators share: tables, word arrays, row keys and written intermediates."""

from __future__ import annotations

import atexit
import contextlib
import os
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

#: White space of the word rule (code points 20 and 09-0D), as a set of characters and as a regex class.
SPACE_CHARS = " \t\n\x0b\x0c\r"
SPACE_RUN = "[\\x20\\x09-\\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that every executor sees: ``spark.checkpoint.dir`` where the session names one.

    Only a single-process session without that setting gets a temporary folder; a cluster
    without it gets a folder beside the warehouse, never one on a machine's own disk.
    """
    known = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if known:
        return known.rstrip("/")
    master = spark.sparkContext.master
    if master.startswith("local") and not master.startswith("local-cluster"):
        known = tempfile.mkdtemp(prefix="corpus-checkpoint-")
        atexit.register(shutil.rmtree, known, ignore_errors=True)
    else:
        known = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_intermediate"
    spark.sparkContext.setCheckpointDir(known)
    return known


_written: dict[str, list[str]] = {}


def n_written(spark: SparkSession) -> int:
    """How many intermediate tables of this application there are."""
    return len(_written.get(spark.sparkContext.applicationId, []))


def release(spark: SparkSession, first: int | None = None, start: int = 0) -> None:
    """Delete ``first`` intermediate tables of this application (all of them without it), from the ``start``-th on.

    For when the results that read them have been written, or do not read them.
    """
    paths = _written.get(spark.sparkContext.applicationId, [])
    gone = paths[start:] if first is None else paths[start : start + first]
    del paths[start : start + len(gone)]
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for path in gone:
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(conf).delete(at, True)


def forget_shuffles(spark: SparkSession) -> None:
    """Have Spark delete the shuffles of plans that are done with, which it does once the JVM has collected these."""
    spark.sparkContext._jvm.System.gc()


def _release_at_exit() -> None:
    """What an application that is still up at its end has not released."""
    spark = SparkSession.getActiveSession()
    if spark is not None and spark.sparkContext._jsc is not None:
        with contextlib.suppress(Exception):  # the other side may be gone before
            release(spark)


def written(df: DataFrame, *partition_by: str) -> DataFrame:
    """``df`` written once as Parquet into the shared folder and read again: a cut of the lineage
    that a lost executor cannot undo.  ``checkpoint()`` would run the plan twice."""
    path = f"{shared_dir(df.sparkSession)}/tables/{uuid.uuid4().hex}"
    out = df.write
    if partition_by:
        out = out.partitionBy(*partition_by)
    out.parquet(path)
    if not _written:
        atexit.register(_release_at_exit)
    _written.setdefault(df.sparkSession.sparkContext.applicationId, []).append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package to the executors' Python workers, once for each Spark application."""
    context = spark.sparkContext
    if context.applicationId in _shipped:
        return
    package = Path(__file__).resolve().parent.parent
    with tempfile.TemporaryDirectory() as folder:
        staged = Path(folder, "src", package.name)
        shutil.copytree(package, staged, ignore=shutil.ignore_patterns("__pycache__"))
        made = tempfile.mkdtemp(prefix="package-")
        atexit.register(shutil.rmtree, made, ignore_errors=True)
        name = shutil.make_archive(os.path.join(made, package.name), "zip", staged.parent)
    context.addPyFile(name)
    _shipped.add(context.applicationId)


#: Rows up to which a table of row keys (some 40 bytes each, 100 in memory) is broadcast.
BROADCAST_ROWS = 250_000


#: Rows of one key beyond which a join spreads them over several tasks.
HUB_ROWS = 20_000


def spread_join(many: DataFrame, few: DataFrame, key: str, spread_by: str | list[str], size: str = "n") -> DataFrame:
    """``many`` joined with ``few`` (one row for each key, ``size``: how many rows ``many`` has of it).

    Keys of more than ``HUB_ROWS`` rows get a salt: their rows in ``few`` are copied once for each
    ``HUB_ROWS``, and those of ``many`` are dealt to the copies by ``spread_by``.  ``few`` is read
    twice and should be a written table; there is at most one hub for each ``HUB_ROWS`` rows of ``many``.
    """
    salts = F.ceil(F.col(size) / HUB_ROWS).cast("int")
    hubs = few.where(F.col(size) > HUB_ROWS).select(key, salts.alias("_salts"))
    if hubs.isEmpty():
        return many.join(few, key)
    many = many.join(sized(hubs), key, "left").withColumn("_salt", F.pmod(F.xxhash64(*([spread_by] if isinstance(spread_by, str) else spread_by)), F.coalesce("_salts", F.lit(1))).cast("int"))
    few = few.withColumn("_salt", F.explode(F.sequence(F.lit(0), salts - 1)))
    return many.drop("_salts").join(few, [key, "_salt"]).drop("_salt")


def sized(keys: DataFrame, limit: int | None = None) -> DataFrame:
    """``keys``, to be broadcast if they are few enough; a join with more of them is shuffled."""
    return F.broadcast(keys) if keys.count() <= (BROADCAST_ROWS if limit is None else limit) else keys


def named(name: str) -> Column:
    """The column of that very name, dots and all."""
    return F.col("`" + name.replace("`", "``") + "`")


def fresh(docs: DataFrame, *names: str) -> list[str]:
    """Names like ``names`` that ``docs`` has no column of, whatever the case of letters."""
    taken, out = {c.lower() for c in docs.columns}, []
    for name in names:
        made = f"_{name}"
        while made.lower() in taken:
            made = "_" + made
        taken.add(made.lower())
        out.append(made)
    return out


def map_batches(df: DataFrame, run: Callable, schema: StructType) -> DataFrame:
    """``mapInArrow`` for columns of any names, which it takes by names that are not quoted."""
    names = [f"c{i}" for i in range(len(schema))]

    def renamed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in run(batches):
            yield pa.RecordBatch.from_arrays(batch.columns, names)

    plain = StructType([StructField(n, f.dataType, True) for n, f in zip(names, schema, strict=True)])
    return df.toDF(*[f"i{i}" for i in range(len(df.columns))]).mapInArrow(renamed, plain).toDF(*schema.names)


def same_value(a: Column, b: Column) -> Column:
    """Equal values; null equals null and nothing else."""
    return a.eqNullSafe(b)


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` applied to ``value``, which is evaluated once however often the body uses it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words_of(text: Column) -> Column:
    """Array of the maximal runs without white space; empty for null, empty or blank text."""
    trimmed = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACE_CHARS))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE_RUN, -1))


def hashed_words(text: Column) -> Column:
    """The words of ``words_of`` as 64-bit hashes."""
    return F.transform(words_of(text), lambda w: F.xxhash64(w))


def text_key(text: Column) -> tuple[Column, Column]:
    """Two independent 64-bit hashes that stand for a whole text (both null for a null text)."""
    return (
        F.when(text.isNotNull(), F.xxhash64(text)),
        F.when(text.isNotNull(), F.xxhash64(F.lit("second"), text)),
    )


def sha256_text(value: Column) -> Column:
    return F.sha2(F.encode(value, "UTF-8"), 256)
