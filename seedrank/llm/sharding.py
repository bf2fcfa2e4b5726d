"""Sharding by longest processing time: groups that must stay together, largest first, each to the
shard with the least load so far.

Groups of one size are alike to the rule, so the heap needs no more than the number of groups of
each size; how many of them each shard takes follows at once, however many there are.  As the sizes are
whole numbers, the list of distinct sizes that the driver sees has at most the square root of twice all bytes
entries.  Groups are then ranked inside their size, and the rank gives the shard.  Ranks and slots are numbered in
cells of bounded size, and a cell starts where those before it end.

Defined results: a null text has size 1 and checksum 0, and null texts form one group; repeated rows
are rows of one group with a slot each; a group larger than a shard's share makes that shard large, since it
must stay together; an empty table gives no rows; a text of any length is one item; other columns are ignored.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seedrank.llm.common import named, sized, spread_join, table, written

SHARDS = 16
#: Ranks and slots are numbered in cells of about this share of all groups or rows.
CELLS = 4096


def longest_first(sizes: np.ndarray, shards: int) -> np.ndarray:
    """The shard of each item, item by item."""
    out = np.zeros(len(sizes), np.int32)
    loads = [(0, s) for s in range(shards)]
    for i in np.argsort(-sizes, kind="stable").tolist():
        load, shard = loads[0]
        out[i] = shard
        heapq.heapreplace(loads, (load + int(sizes[i]), shard))
    return out


def _spread(loads: list[int], size: int, count: int) -> list[int]:
    """How many of ``count`` items of one size each shard takes: the least loads, step by step, all at once."""

    def below(level: int) -> int:
        return sum(max(0, -(-(level - x) // size)) for x in loads)

    # the items stand at the loads they meet; the level is the least load that not all items stand below
    low = min(loads)
    high = low + count * size + 1
    while high - low > 1:
        middle = (low + high) // 2
        low, high = (middle, high) if below(middle) <= count else (low, middle)
    taken = [max(0, -(-(low - x) // size)) for x in loads]
    left = count - sum(taken)
    for s, x in enumerate(loads):
        if left and x <= low and (low - x) % size == 0:
            taken[s], left = taken[s] + 1, left - 1
    return taken


def longest_first_by_size(sizes: list[int], counts: list[int], shards: int) -> list[list[tuple[int, int]]]:
    """For each size (descending, with the number of its groups): (shard, groups that it takes)."""
    loads, out = [(0, s) for s in range(shards)], []
    for size, count in zip(sizes, counts, strict=True):
        if count <= 4 * shards:
            taken: dict[int, int] = {}
            for _ in range(count):
                load, shard = loads[0]
                taken[shard] = taken.get(shard, 0) + 1
                heapq.heapreplace(loads, (load + size, shard))
        else:
            by_shard = [x for x, _ in sorted(loads, key=lambda x: x[1])]
            taken = dict(enumerate(_spread(by_shard, size, count)))
            loads = [(by_shard[s] + n * size, s) for s, n in taken.items()]
            heapq.heapify(loads)
        out.append(sorted((s, n) for s, n in taken.items() if n))
    return out


def _starts(rows: DataFrame, by: str, cell: list[str], weight: Column) -> DataFrame:
    """``cell`` and ``start``: the weight of the cells before it among those of equal ``by``.

    The cells go to the driver, so their number must have a bound.
    """
    cells = rows.groupBy(by, *cell).agg(weight.cast("long").alias("weight")).toPandas().sort_values([by, *cell])
    cells["start"] = cells.groupby(by)["weight"].cumsum() - cells["weight"]
    columns = list(dict.fromkeys([by, *cell]))
    schema = ", ".join(f"{c} {rows.schema[c].dataType.simpleString()}" for c in columns) + ", start long"
    return rows.sparkSession.createDataFrame(pa.Table.from_pandas(cells[[*columns, "start"]], preserve_index=False), schema)


def shard_groups(rows: DataFrame, group: str, size: str, order: list[str], shards: int = SHARDS, cells: int = CELLS) -> DataFrame:
    """``rows`` with shard and slot; rows of equal ``group`` (a long) share a shard.

    ``rows`` is read several times and should be a written table.  ``order`` settles the slots.
    """
    spark = rows.sparkSession
    kept = [named(c) for c in rows.columns]
    # names of its own for everything that is added
    work = rows.select(F.struct(*kept).alias("row"), named(group).alias("g"), named(size).cast("long").alias("bytes"), F.xxhash64(*[named(c) for c in order]).alias("o"))
    groups = written(work.groupBy("g").agg(F.sum("bytes").alias("bytes"), F.count(F.lit(1)).alias("n")))
    counted = groups.groupBy("bytes").agg(F.count(F.lit(1)).alias("c"), F.sum("n").alias("n")).toPandas().sort_values("bytes", ascending=False)
    n_groups, n_rows = int(counted["c"].sum()), int(counted["n"].sum())
    # rank inside the size: groups of a frequent size are ranked in several cells
    dealt = longest_first_by_size(counted["bytes"].tolist(), counted["c"].tolist(), shards)
    ends = np.cumsum([0, *map(len, dealt)])
    flat = [x for d in dealt for x in d]
    upto = np.concatenate([np.cumsum([n for _, n in d]) for d in dealt]) if dealt else np.empty(0, np.int64)
    salts = -(-counted["c"].to_numpy() // max(1, -(-n_groups // cells)))
    plan = pa.table(
        {
            "bytes": pa.array(counted["bytes"], pa.int64()), "c": pa.array(counted["c"], pa.int64()), "salts": pa.array(salts, pa.int64()),
            "upto": pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(upto, pa.int64())),
            "to": pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array([s for s, _ in flat], pa.int32())),
        }
    )
    plan = written(spark.createDataFrame(plan, "bytes long, c long, salts long, upto array<long>, to array<int>"))
    few = sized(plan, 50_000)
    ranked = groups.join(few, "bytes") if few is not plan else spread_join(groups, plan, "bytes", "g", size="c")
    ranked = ranked.withColumn("salt", F.pmod(F.xxhash64("g"), F.col("salts")).cast("int"))
    many = written(ranked.where("salts > 1").select("bytes", "salt"))  # of frequent sizes only, cells and a few
    starts = F.broadcast(_starts(many, "bytes", ["salt"], F.count(F.lit(1))))
    place = F.row_number().over(Window.partitionBy("bytes", "salt").orderBy("g")) - 1
    ranked = ranked.withColumn("place", place).join(starts, ["bytes", "salt"], "left")
    rank = F.col("place") + F.coalesce("start", F.lit(0))
    shard = F.element_at("to", (F.size(F.filter("upto", lambda u: u <= rank)) + 1).cast("int"))
    placed = written(ranked.select("g", "n", shard.alias("shard")))
    # first slot of each group: a running sum inside cells of each shard
    placed = placed.withColumn("cell", F.pmod(F.xxhash64(F.lit("slots"), "g"), F.lit(max(1, cells // shards))).cast("int"))
    starts = F.broadcast(_starts(placed, "shard", ["cell"], F.sum("n")))
    before = F.sum("n").over(Window.partitionBy("shard", "cell").orderBy("g").rowsBetween(Window.unboundedPreceding, -1))
    placed = placed.withColumn("before", F.coalesce(before, F.lit(0))).join(starts, ["shard", "cell"])
    # rows of a large group are numbered in several cells as well
    heap = max(1, -(-n_rows // cells))
    placed = written(placed.select("g", "n", "shard", (F.col("start") + F.col("before")).alias("first"), F.ceil(F.col("n") / heap).cast("int").alias("salts")))
    joined = spread_join(work, placed, "g", "o").withColumn("salt", F.pmod("o", "salts").cast("int"))
    inside = written(joined.where("salts > 1").select("g", "salt"))
    starts = F.broadcast(_starts(inside, "g", ["salt"], F.count(F.lit(1))))  # two for each cell at most
    number = F.row_number().over(Window.partitionBy("g", "salt").orderBy(*[F.col("row").getField(c) for c in order])) - 1
    out = joined.withColumn("number", number).join(starts, ["g", "salt"], "left")
    slot = F.col("first") + F.coalesce("start", F.lit(0)) + F.col("number")
    return out.select(*[F.col("row").getField(c).alias(c) for c in rows.columns], "shard", slot.cast("long").alias("slot"))


def shard_documents(docs: DataFrame, shards: int = SHARDS, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, shard and slot of every document; equal texts share a shard."""
    content = named(text)
    rows = docs.select(
        named(doc_id).alias("doc_id"),
        (F.coalesce(F.octet_length(content), F.lit(0)) + 1).cast("long").alias("size"),
        F.coalesce(F.crc32(content.cast("binary")), F.lit(0)).cast("long").alias("text_crc32"),
        F.xxhash64(content.isNull(), content).alias("group"),
    )
    return shard_groups(written(rows), "group", "size", ["doc_id", "group"], shards).drop("group")


def op3_sharding(spark, sf_dir: str) -> DataFrame:
    out = shard_documents(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
