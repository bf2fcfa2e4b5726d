"""Best-fit packing of token pieces into sequences of fixed capacity, by hierarchical residuals.

Documents are tokenised once and cut where they are longer than a sequence.  Pieces are dealt to
nodes; each node packs best-fit (largest item first, into the fullest bin that still takes it),
emits the bins that are full or nearly so, and hands the others on.  On the next level the
underfull bins are items themselves, dealt to fewer nodes and packed again, until one node has
seen the rest or a level no longer saves bins.  No node gets more than ``node_items`` items on
average, whatever the size of the input, and the bins that no partner exists for do not gather.

Defined results: a null or empty text is one piece that holds only the end token; repeated rows
are packed one by one; an empty table gives no rows; a text of any length is tokenised whole, in memory
in proportion to its length; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedrank.llm.arrow import byte_bpe_encoder
from seedrank.llm.common import named, ship, table, written

CAPACITY = 2048
END_ID = 0
NODE_ITEMS = 50_000
#: A bin with at most this much room left is emitted at once.
SLACK = 4

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def cut_points(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of ``n`` ids; where they do not divide, the first is shorter."""
    if n <= capacity:
        return [(0, n)]
    first = n % capacity
    cuts = [(0, first)] if first else []
    return cuts + [(s, capacity) for s in range(first, n, capacity)]


def pieces(docs: DataFrame, capacity: int = CAPACITY, doc_id: str = "doc_id", text: str = "text", vocabulary: str | None = None, with_ids: bool = False) -> DataFrame:
    """The pieces of every document: ids by the byte-level BPE, then one end id."""
    ship(docs.sparkSession)
    schema = PIECES + (", ids array<int>" if with_ids else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = byte_bpe_encoder(vocabulary)
        for batch in batches:
            names = batch.schema.names
            docs_, texts = batch.column(names.index("doc_id")), batch.column(names.index("text"))
            out: dict[str, list] = {c.split()[0]: [] for c in schema.split(", ")}
            for d, t in zip(docs_.to_pylist(), texts, strict=True):
                ids = np.array([*(encode(t.as_py()) if t.is_valid else ()), END_ID], dtype="<u4")
                for i, (start, length) in enumerate(cut_points(len(ids), capacity)):
                    part = ids[start : start + length]
                    for c, v in zip(out, (d, i, start, length, zlib.crc32(part.tobytes())), strict=False):
                        out[c].append(v)
                    if with_ids:
                        out["ids"].append(part.astype("i4"))
            types = {"doc_id": pa.int64(), "piece": pa.int32(), "ids": pa.list_(pa.int32())}
            yield pa.RecordBatch.from_pydict({c: pa.array(v, types.get(c, pa.int64())) for c, v in out.items()})

    return docs.select(named(doc_id).cast("long").alias("doc_id"), named(text).alias("text")).mapInArrow(run, schema)


def best_fit(sizes: np.ndarray, capacity: int) -> list[list[int]]:
    """Bins as lists of item positions.  Bins are kept by the room they have left; a bit set over
    the rooms in use gives the tightest bin that takes an item in one step."""
    bins: list[list[int]] = []
    by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    used = 0
    for i in np.argsort(-sizes, kind="stable").tolist():
        size = int(sizes[i])
        fitting = used >> size
        if fitting:
            room = size + (fitting & -fitting).bit_length() - 1
            b = by_room[room].pop()
            if not by_room[room]:
                used ^= 1 << room
            bins[b].append(i)
        else:
            room, b = capacity, len(bins)
            bins.append([i])
        left = room - size
        if left:
            if not by_room[left]:
                used |= 1 << left
            by_room[left].append(b)
    return bins


#: A bin on its way up: its members in order with their places in it, how full it is, and the sequence number once emitted.
_MEMBER = "struct<doc_id:long,piece:int,start:long,length:long,ids_crc32:long,offset:long>"
_BINS = f"fill long, members array<{_MEMBER}>, sequence_id long, tie long"


def _pack_node(capacity: int, slack: int, level: int):
    def run(bins: pa.Table) -> pa.Table:
        node = bins.column("node")[0].as_py()
        # the order of arrival differs between attempts; that of ties must not
        bins = bins.sort_by([("fill", "descending"), ("tie", "ascending")]).combine_chunks()
        members = bins.column("members").chunk(0) if bins.num_rows else None
        fills = bins.column("fill").to_numpy()
        packed = best_fit(fills, capacity)
        offsets = members.offsets.to_numpy().astype(np.int64)
        order = np.concatenate([np.arange(offsets[i], offsets[i + 1]) for b in packed for i in b])
        counts = [int(sum(offsets[i + 1] - offsets[i] for i in b)) for b in packed]
        flat = members.values.take(pa.array(order))
        lengths = flat.field("length").to_numpy()
        ends, heads = np.cumsum(lengths), np.cumsum(counts) - counts
        place = ends - lengths - np.repeat((ends - lengths)[heads], counts)
        flat = pa.StructArray.from_arrays([*flat.flatten()[:-1], pa.array(place)], names=[f.name for f in flat.type])
        grown = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]), pa.int32()), flat)
        fill = np.array([int(fills[b].sum()) for b in packed], np.int64)
        number = (np.int64(level) << 56) | (np.int64(node) << 28) | np.arange(len(packed), dtype=np.int64)
        done = fill >= capacity - slack
        tie = bins.column("tie").to_numpy()[[b[0] for b in packed]]
        return pa.table({"fill": fill, "members": grown, "sequence_id": pa.array(number, mask=~done), "tie": tie})

    return run


def pack(piece_rows: DataFrame, capacity: int = CAPACITY, node_items: int = NODE_ITEMS, slack: int = SLACK) -> DataFrame:
    """``piece_rows`` (a table that can be read again) with sequence_id and offset."""
    ship(piece_rows.sparkSession)
    member = F.struct(*[c.split()[0] for c in PIECES.split(", ")], F.lit(0).cast("long").alias("offset"))
    tie = F.xxhash64("doc_id", "piece", "start", "ids_crc32")
    bins = piece_rows.select(F.col("length").alias("fill"), F.array(member).alias("members"), F.lit(None).cast("long").alias("sequence_id"), tie.alias("tie"))
    # a piece that fills its sequence needs no partner; its number lies in a range of its own
    whole = F.col("fill") >= capacity
    alone = bins.where(whole).withColumn("sequence_id", F.monotonically_increasing_id() + F.lit(1 << 62))
    parts, open_, level, before = [alone], bins.where(~whole), 1, None
    while True:
        n = open_.count()
        if n == 0:
            break
        nodes = -(-n // node_items)
        if before is not None and (before[0] == 1 or n > 0.995 * before[1]):
            # one node has seen all that is left, or a level has saved next to nothing
            parts.append(open_.withColumn("sequence_id", F.monotonically_increasing_id() + F.lit(1 << 61)))
            break
        dealt = open_.withColumn("node", F.pmod(F.xxhash64("tie", F.lit(level)), F.lit(nodes)).cast("int"))
        packed = written(dealt.groupBy("node").applyInArrow(_pack_node(capacity, slack, level), _BINS))
        parts.append(packed.where(F.col("sequence_id").isNotNull()))
        open_, before, level = packed.where(F.col("sequence_id").isNull()), (nodes, n), level + 1
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.select("sequence_id", F.explode("members").alias("m")).select(*[F.col(f"m.{c.split()[0]}") for c in PIECES.split(", ")], "sequence_id", "m.offset")


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, **options) -> DataFrame:
    return pack(written(pieces(docs, capacity)), capacity, **options)


def op5_packing(spark, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))
