"""Similarity of all pairs of many assignments: least ranks, exact sums of minima and links, in NumPy on whole columns.

Ranks are the independent differences of ``sketch.k_mins_of_long``.  Links of all pairs are found tile by tile: two blocks of
assignments meet in one task, where each draw is a bit for each pair, and a pair counts if enough of its bits are
set.  So a pair costs some bits, whatever its weights, and no list of pairs is made but of those asked for.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedrank.functions.draws import Keys

# executors get these functions with the task, wherever the package lies
cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Rows that are taken at once, at least; a key's rows are never parted.
CHUNK = 1 << 18
#: Assignments of which a task keeps least ranks before it hands them on.
KEPT = 1 << 19
#: Partitions by key at most: each hands on a row for every assignment.
KEY_PARTS = 12
#: Assignments in a block at most (about), and those of a small block, of which up to four are made.
BLOCK, SMALL_BLOCK = 1 << 15, 1 << 12
#: Pairs that are held at once.
HELD = 1 << 22
#: Assignments up to which sums of all pairs lie in one square.
SQUARE = 3000


def _whole(batches: Iterator[pa.RecordBatch], column: str, least: int) -> Iterator[pa.Table]:
    """Tables of ``least`` rows or more, in which all rows of each value of the sorted ``column`` are together."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        if sum(b.num_rows for b in held) < least:
            continue
        table = pa.Table.from_batches(held).combine_chunks()
        last = table[column][-1].as_py()
        cut = int(np.argmax(np.asarray(pc.equal(table[column], last))))
        if cut:
            yield table.slice(0, cut).combine_chunks()
        held = table.slice(cut).combine_chunks().to_batches()
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _array(table: pa.Table, column: str) -> pa.Array:
    chunks = table[column].chunks
    return chunks[0] if len(chunks) == 1 else pa.concat_arrays(chunks)


def _starts(keys: pa.Array) -> np.ndarray:
    """Whether a row has another key than the row before."""
    codes = keys.dictionary_encode().indices.to_numpy()
    return np.concatenate([[True], codes[1:] != codes[:-1]])


def _level_ranks(keys: pa.Array, weight: np.ndarray, k: int, salt: str) -> tuple[np.ndarray, np.ndarray]:
    """For rows in order of key and weight: the number of each row's level, and k ranks of every level.

    A level is a weight that a key has; its rank is the least draw of the key's gaps up to that weight.
    """
    first = _starts(keys)
    new = first | np.concatenate([[True], weight[1:] != weight[:-1]])
    at = np.flatnonzero(new)
    begin = np.maximum.accumulate(np.where(first, np.arange(len(first)), 0))[at]
    lowest = first[at]
    gap = weight[at] - np.where(lowest, 0.0, np.concatenate([[0.0], weight[at][:-1]]))
    texts = pc.binary_join_element_wise(pa.array(at - begin).cast(pa.string()), keys.take(pa.array(at)).cast(pa.string()), "|")
    seeds = Keys(texts)
    ranks = np.empty((len(at), k))
    for t in range(k):
        ranks[:, t] = -np.log1p(-seeds.uniform(f"{salt}#{t + 1}|gap|".encode())) / gap
    nth = np.arange(len(at)) - np.maximum.accumulate(np.where(lowest, np.arange(len(at)), 0))
    order = np.argsort(nth, kind="stable")
    edges = np.searchsorted(nth[order], np.arange(1, nth.max() + 2))
    for a, b in zip(edges[:-1], edges[1:], strict=True):
        rows = order[a:b]
        ranks[rows] = np.minimum(ranks[rows], ranks[rows - 1])
    return np.cumsum(new) - 1, ranks


def _least_of(code: np.ndarray, ranks: np.ndarray, level: np.ndarray, out: np.ndarray) -> None:
    """Lower ``out`` to the ranks of the rows, of which ``code`` says where."""
    order = np.argsort(code, kind="stable")
    for i in range(0, len(order), 1 << 15):
        rows = order[i : i + (1 << 15)]
        c = code[rows]
        at = np.flatnonzero(np.concatenate([[True], c[1:] != c[:-1]]))
        out[c[at]] = np.minimum(out[c[at]], np.minimum.reduceat(ranks[level[rows]], at, axis=0))


class _Least:
    """Least ranks and sums of weights of the assignments met so far."""

    def __init__(self, k: int):
        self.k, self.codes = k, {}
        self.ranks, self.total = np.full((1024, k), np.inf), np.zeros(1024)

    def add(self, names: pa.Array, weight: np.ndarray, level: np.ndarray, ranks: np.ndarray) -> None:
        coded = names.dictionary_encode()
        codes = np.array([self.codes.setdefault(x, len(self.codes)) for x in coded.dictionary.to_pylist()], np.int64)
        while len(self.codes) > len(self.total):
            self.ranks, self.total = np.concatenate([self.ranks, np.full_like(self.ranks, np.inf)]), np.concatenate([self.total, np.zeros_like(self.total)])
        code = codes[coded.indices.to_numpy()]
        _least_of(code, ranks, level, self.ranks)
        self.total += np.bincount(code, weights=weight, minlength=len(self.total))

    def rows(self) -> Iterator[pa.RecordBatch]:
        names = list(self.codes)
        for i in range(0, len(names), 4096):
            part = names[i : i + 4096]
            ranks = self.ranks[i : i + len(part)]
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, ranks.size + 1, self.k, dtype=np.int32)), pa.array(ranks.ravel()))
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.string()), pa.array(self.total[i : i + len(part)]), lists], ["assignment", "total", "ranks"])


def _matrix(lists: pa.Array, k: int) -> np.ndarray:
    return lists.flatten().to_numpy().reshape(-1, k)


def least_ranks(weights: DataFrame, k: int, salt: str = "v1") -> DataFrame:
    """assignment, total (its weights), ranks (the least of each of k draws); ``weights``: a table that can be read again."""
    rows = weights.where("weight > 0").select("assignment", "key", F.col("weight").cast("double").alias("weight"))
    parts = min(KEY_PARTS, -(-rows.count() // (4 * CHUNK)) or 1)

    def drawn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = _Least(k)
        for table in _whole(batches, "key", CHUNK):
            weight = _array(table, "weight").to_numpy()
            found.add(_array(table, "assignment"), weight, *_level_ranks(_array(table, "key"), weight, k, salt))
            if len(found.codes) > KEPT:
                yield from found.rows()
                found = _Least(k)
        yield from found.rows()

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _whole(batches, "assignment", 1 << 14):
            found, n = _Least(k), table.num_rows
            found.add(_array(table, "assignment"), _array(table, "total").to_numpy(), np.arange(n), _matrix(_array(table, "ranks"), k))
            yield from found.rows()

    schema = "assignment string, total double, ranks array<double>"
    # by number, so that a session which makes more partitions leaves these empty
    rows = rows.withColumn("part", F.pmod(F.xxhash64("key"), F.lit(parts)))
    some = rows.repartition(4 * parts, "part").drop("part").sortWithinPartitions("key", "weight").mapInArrow(drawn, schema)
    return some.repartition("assignment").sortWithinPartitions("assignment").mapInArrow(merged, schema)


def k_mins_rows(least: DataFrame) -> DataFrame:
    """assignment, t, rank: a row for each draw of ``least_ranks``."""
    rows = least.select("assignment", F.posexplode("ranks").alias("t", "rank"))
    return rows.select("assignment", (F.col("t") + 1).alias("t"), "rank")


# ---------------------------------------------------------------- exact sums of minima of all pairs with a common key


def _pair_sums(key: np.ndarray, code: np.ndarray, weight: np.ndarray, n: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(lower code, higher code, sum of minima) of the pairs of rows of one key; ``code`` is below ``n``."""
    order = np.lexsort((code, key))
    key, code, weight = key[order], code[order], weight[order]
    ends = np.append(np.flatnonzero(key[1:] != key[:-1]) + 1, len(key))
    later = np.repeat(ends, np.diff(np.concatenate([[0], ends]))) - np.arange(len(key)) - 1
    edges = np.concatenate([[0], np.cumsum(later)])
    square = np.zeros(n * n) if n <= SQUARE else None
    i = 0
    while i < len(key):
        j = max(i + 1, int(np.searchsorted(edges, edges[i] + HELD, side="right")) - 1)
        p = np.repeat(np.arange(i, j), later[i:j])
        q = np.arange(len(p)) - np.repeat(edges[i:j] - edges[i], later[i:j]) + p + 1
        cell, low = code[p] * n + code[q], np.minimum(weight[p], weight[q])
        if square is not None:
            square += np.bincount(cell, weights=low, minlength=n * n)
        elif len(cell):
            by = np.argsort(cell)
            cell = cell[by]
            at = np.flatnonzero(np.concatenate([[True], cell[1:] != cell[:-1]]))
            yield cell[at] // n, cell[at] % n, np.add.reduceat(low[by], at)
        i = j
    if square is not None:
        cell = np.flatnonzero(square)
        yield cell // n, cell % n, square[cell]


def sums_of_minima(weights: DataFrame) -> DataFrame:
    """a, b, low: the sum of minima of each pair with a common key, for whole weights; ``weights``: a table that can be read again.

    Keys that are near in order mostly have the same assignments, so pairs are summed over a range of keys before they
    leave a task.
    """
    rows = weights.where("weight > 0").select("assignment", "key", F.col("weight").cast("double").alias("weight"))
    parts = -(-rows.count() // (4 * CHUNK)) or 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _whole(batches, "key", 5 * CHUNK):
            coded = _array(table, "assignment").dictionary_encode()
            # codes in the order of names
            order = pc.array_sort_indices(coded.dictionary).to_numpy()
            place = np.empty(len(order), np.int64)
            place[order] = np.arange(len(order))
            names = coded.dictionary.take(pa.array(order))
            for a, b, low in _pair_sums(np.cumsum(_starts(_array(table, "key"))), place[coded.indices.to_numpy()], _array(table, "weight").to_numpy(), len(order)):
                for i in range(0, len(a), 1 << 16):
                    s = slice(i, i + (1 << 16))
                    yield pa.RecordBatch.from_arrays([names.take(pa.array(a[s])), names.take(pa.array(b[s])), pa.array(low[s])], ["a", "b", "low"])

    found = rows.repartitionByRange(parts, "key").sortWithinPartitions("key").mapInArrow(run, "a string, b string, low double")
    return found.groupBy("a", "b").agg(F.sum("low").alias("low"))


# ---------------------------------------------------------------- links of all pairs by their least ranks


def tiled(least: DataFrame) -> DataFrame:
    """``least`` (assignment, ranks; a table that can be read again) once for every tile: tile, side, assignment, ranks.

    A tile holds two blocks, of sides 0 and 1, or one block of side 2, and every two assignments meet in one tile.
    """
    n = least.count()
    blocks = max(1, -(-n // BLOCK), min(4, -(-n // SMALL_BLOCK)))
    own = F.pmod(F.xxhash64("assignment"), F.lit(blocks)).cast("int")
    rows = least.select("assignment", "ranks", own.alias("own"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other"))
    side = F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1).cast("byte")
    return rows.select((F.least("own", "other") * blocks + F.greatest("own", "other")).alias("tile"), side.alias("side"), "assignment", "ranks")


def _planes(ranks: np.ndarray, others: np.ndarray) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each draw: the row of bits of every assignment (0: none has its rank), those rows, and how many bits each has."""
    out, m = [], len(others)
    for t in range(ranks.shape[1]):
        values = np.intersect1d(ranks[:, t], others[:, t])
        mine, theirs = np.searchsorted(values, ranks[:, t]), np.searchsorted(values, others[:, t])
        known = np.append(values, np.inf)
        mine, theirs = np.where(known[mine] == ranks[:, t], mine + 1, 0), np.where(known[theirs] == others[:, t], theirs + 1, 0)
        bits = np.zeros((len(values) + 1, -(-m // 64) * 8), np.uint8)
        for r in range(8):  # one byte of a row is met once in each turn
            at = np.arange(r, m, 8)
            bits[theirs[at], at >> 3] |= np.uint8(1 << r)
        bits[0] = 0
        count = np.bincount(theirs, minlength=len(values) + 1)
        count[0] = 0
        out.append((mine, bits.view(np.uint64), count))
    return out


def _at_least(draws: Iterator[np.ndarray], need: int) -> np.ndarray:
    """The bits that are set in ``need`` of the draws: all pairs are counted at once, a plane for each binary digit."""
    if need == 1:
        found = next(draws)
        for x in draws:
            found |= x
        return found
    digits: list[np.ndarray] = []
    waiting: list[np.ndarray | None] = []

    def add(i: int, x: np.ndarray) -> None:
        if i == len(digits):
            digits.append(np.zeros_like(x))
            waiting.append(None)
        if waiting[i] is None:
            waiting[i] = x
            return
        y, waiting[i] = waiting[i], None
        carry = digits[i] & x
        digits[i] ^= x
        carry |= digits[i] & y
        digits[i] ^= y
        add(i + 1, carry)

    for x in draws:
        add(0, x)
    i = 0
    while i < len(digits):
        if waiting[i] is not None:
            x, waiting[i] = waiting[i], None
            carry = digits[i] & x
            digits[i] ^= x
            if carry.any():
                add(i + 1, carry)
        i += 1
    more, same = np.zeros_like(digits[0]), np.full_like(digits[0], 0xFFFFFFFFFFFFFFFF)
    for i in range(max(len(digits), need.bit_length()) - 1, -1, -1):
        digit = digits[i] if i < len(digits) else np.zeros_like(more)
        if need >> i & 1:
            same &= digit
        else:
            more |= same & digit
            same &= ~digit
    return more | same


def _sides(table: pa.Table, k: int) -> tuple[bool, tuple[pa.Array, np.ndarray], tuple[pa.Array, np.ndarray]]:
    side, names, ranks = _array(table, "side").to_numpy(), _array(table, "assignment"), _matrix(_array(table, "ranks"), k)
    whole = bool((side == 2).any())
    part = lambda s: (names.filter(pa.array(side == s)), ranks[side == s])
    return whole, part(2 if whole else 0), part(2 if whole else 1)


def _rows_at_once(m: int) -> int:
    return max(1, (1 << 17) // max(1, m // 64))


def link_counts(least: DataFrame, k: int) -> DataFrame:
    """assignment, n_links (how many others share a least rank with it), similarity (the sum of the shares of draws in
    which they do)."""

    def run(table: pa.Table) -> pa.Table:
        whole, (an, a), (bn, b) = _sides(table, k)
        links, times, theirs, other = np.zeros(len(a), np.int64), np.zeros(len(a), np.int64), np.zeros(len(b), np.int64), np.zeros(len(b), np.int64)
        if len(a) and len(b):
            planes = _planes(a, b)
            step = _rows_at_once(len(b))
            for i in range(0, len(a), step):
                met = _at_least((bits[mine[i : i + step]] for mine, bits, _ in planes), 1)
                links[i : i + step] = np.bitwise_count(met).sum(axis=1, dtype=np.int64)
                if not whole:
                    for j in range(0, len(met), 256):
                        theirs += np.unpackbits(met[j : j + 256].view(np.uint8), axis=1, count=len(b), bitorder="little").sum(axis=0, dtype=np.int64)
            for mine, _, count in planes:
                times += count[mine]
            if not whole:
                for t in range(k):
                    values, counts = np.unique(a[:, t], return_counts=True)
                    at = np.minimum(np.searchsorted(values, b[:, t]), len(values) - 1)
                    other += np.where(values[at] == b[:, t], counts[at], 0)
        if whole:  # all but the pair with itself
            return pa.table([an, pa.array(links - 1), pa.array(times - k)], ["assignment", "links", "times"])
        return pa.table([pa.concat_arrays([an, bn]), pa.array(np.append(links, theirs)), pa.array(np.append(times, other))], ["assignment", "links", "times"])

    found = tiled(least).groupBy("tile").applyInArrow(run, "assignment string, links long, times long")
    return found.groupBy("assignment").agg(F.sum("links").alias("n_links"), (F.sum("times") / F.lit(float(k))).alias("similarity"))


def close_pairs(least: DataFrame, k: int, need: int) -> DataFrame:
    """tile, a, b, draws: the pairs that share the least rank in ``need`` of k draws or more."""

    def run(table: pa.Table) -> pa.Table:
        whole, (an, a), (bn, b) = _sides(table, k)
        tile, found = _array(table, "tile")[:1], [(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int32))]
        if len(a) and len(b):
            planes = _planes(a, b)
            step = _rows_at_once(len(b))
            for i in range(0, len(a), step):
                met = _at_least((bits[mine[i : i + step]] for mine, bits, _ in planes), need).view(np.uint8)
                p, byte = np.nonzero(met)
                row, bit = np.nonzero(np.unpackbits(met[p, byte][:, None], axis=1, bitorder="little"))
                p, q = p[row] + i, byte[row] * 8 + bit
                if whole:
                    p, q = p[p < q], q[p < q]
                for j in range(0, len(p), 1 << 16):
                    s = slice(j, j + (1 << 16))
                    found.append((p[s], q[s], (a[p[s]] == b[q[s]]).sum(axis=1, dtype=np.int32)))
        p, q, n = (np.concatenate(x) for x in zip(*found, strict=True))
        x, y = an.take(pa.array(p)), bn.take(pa.array(q))
        low = pc.less(x, y)
        return pa.table([pa.array(np.full(len(p), tile[0].as_py(), np.int32)), pc.if_else(low, x, y), pc.if_else(low, y, x), pa.array(n)], ["tile", "a", "b", "draws"])

    return tiled(least).groupBy("tile").applyInArrow(run, "tile int, a string, b string, draws int")


def exact_similarity(pairs: DataFrame, weights: DataFrame) -> DataFrame:
    """a, b, draws, low, ta, tb: sum of minima and both sums of weights of each of ``pairs`` (tile, a, b, draws); an assignment's
    weights are sent once to each tile in which it has a pair."""
    bags = weights.where("weight > 0").groupBy("assignment").agg(F.collect_list(F.struct(F.xxhash64("key").alias("h"), F.col("weight").cast("double").alias("w"))).alias("xs"))
    bags = bags.select("assignment", F.col("xs.h").alias("h"), F.col("xs.w").alias("w"))
    needed = pairs.select("tile", F.explode(F.array("a", "b")).alias("assignment")).distinct().join(bags, "assignment").select(F.col("tile").alias("into"), "assignment", "h", "w")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        names = _array(right, "assignment")
        a, b = (pc.index_in(_array(left, c), names).to_numpy() for c in "ab")
        sizes = pc.list_value_length(_array(right, "h")).to_numpy()
        edges = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64)
        _, word = np.unique(_array(right, "h").flatten().to_numpy(), return_inverse=True)
        w = _array(right, "w").flatten().to_numpy()
        total = np.add.reduceat(w, edges[:-1]) if len(w) else np.zeros(len(names))
        low, mine = np.zeros(len(a)), np.zeros(int(word.max()) + 1 if len(word) else 0)
        order = np.argsort(a, kind="stable")
        cuts = np.append(np.flatnonzero(np.concatenate([[True], a[order][1:] != a[order][:-1]])), len(order)) if len(order) else [0]
        for i, j in zip(cuts[:-1], cuts[1:], strict=True):
            one = slice(edges[a[order[i]]], edges[a[order[i]] + 1])
            mine[word[one]] = w[one]
            for x in range(i, j, 4096):
                rows = order[x : min(j, x + 4096)]
                n = sizes[b[rows]]
                begin = np.concatenate([[0], np.cumsum(n)])
                at = np.arange(begin[-1]) + np.repeat(edges[b[rows]] - begin[:-1], n)
                low[rows] = np.add.reduceat(np.minimum(mine[word[at]], w[at]), begin[:-1])
            mine[word[one]] = 0
        return pa.table([_array(left, "a"), _array(left, "b"), _array(left, "draws"), pa.array(low), pa.array(total[a]), pa.array(total[b])], ["a", "b", "draws", "low", "ta", "tb"])

    return pairs.groupBy("tile").cogroup(needed.groupBy("into")).applyInArrow(run, "a string, b string, draws int, low double, ta double, tb double")


def equal_assignments(weights: DataFrame) -> DataFrame:
    """assignment, rep: the least name among the assignments of the same keys and weights."""
    same = lambda *parts: F.bit_xor(F.xxhash64(*parts, F.col("key"), F.col("weight")))
    one = weights.where("weight > 0").groupBy("assignment").agg(same().alias("h1"), same(F.lit("second")).alias("h2"), F.count(F.lit(1)).alias("n"))
    reps = one.groupBy("h1", "h2", "n").agg(F.min("assignment").alias("rep"))
    return one.join(reps, ["h1", "h2", "n"]).select("assignment", "rep")
