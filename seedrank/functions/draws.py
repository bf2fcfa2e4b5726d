"""The seeds of ``seeds.uniform`` for whole columns of keys in NumPy, many times cheaper than one expression a row.

The digest is MD5 of one block, computed for all rows at once; keys that do not fit a block are hashed singly.
"""

from __future__ import annotations

import hashlib
import math
import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle

# executors get these functions with the task, wherever the package lies
cloudpickle.register_pickle_by_value(sys.modules[__name__])

_SINES = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
_TURNS = [x for r in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for x in r * 4]
_ORDER = [i for r in range(4) for i in ([j for j in range(16)], [(5 * j + 1) % 16 for j in range(16)], [(3 * j + 5) % 16 for j in range(16)], [7 * j % 16 for j in range(16)])[r]]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: Rows that are digested at once; fewer cost more in calls than the arrays save by staying in a core's cache.
STEP = 32768
#: Draws are digested up to the word that a bound is compared with where one in so many is expected to be kept.
FEW = 64
#: Bytes of a message that leave room for its end mark and length in one block.
ROOM = 55


_SHIFTS = [(np.array(x, np.uint32), np.array(32 - x, np.uint32)) for x in _TURNS]


def _mixed(words: list, n: int, steps: int) -> list:
    """The four words of state after the first ``steps`` of the 64; ``words``: sixteen columns, or numbers where all rows are equal."""
    state, i = list(_START), 0
    while i < 16 and isinstance(words[i], int):  # all rows are alike so far
        a, b, c, d = state
        f = ((((c ^ d) & b) ^ d) + a + _SINES[i] + words[i]) & 0xFFFFFFFF
        state, i = [d, ((f << _TURNS[i] | f >> 32 - _TURNS[i]) + b) & 0xFFFFFFFF, b, c], i + 1
    a, b, c, d = (np.full(n, x, np.uint32) for x in state)
    f, t, both = np.empty(n, np.uint32), np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(i, steps):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
        elif i < 48:
            if i % 2 == 0:
                np.bitwise_xor(b, c, out=both)
                np.bitwise_xor(both, d, out=f)
            else:
                np.bitwise_xor(b, both, out=f)  # b and c of the step before are c and d now
        else:
            np.invert(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        np.add(f, a, out=f)
        word, more = words[_ORDER[i]], _SINES[i]
        if isinstance(word, int):
            more = (more + word) & 0xFFFFFFFF
        else:
            np.add(f, word, out=f)
        np.add(f, np.array(more, np.uint32), out=f)
        left, right = _SHIFTS[i]
        np.left_shift(f, left, out=t)
        np.right_shift(f, right, out=f)
        np.bitwise_or(f, t, out=f)
        np.add(f, b, out=a)  # the old a is done with
        a, b, c, d = d, a, b, c
    return [a, b, c, d]


def _two_words(words: list, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first two words of the digest of ``n`` blocks."""
    a, b, _, _ = _mixed(words, n, 64)
    return a + np.uint32(_START[0]), b + np.uint32(_START[1])


def _one_word(words: list, n: int) -> np.ndarray:
    """The first word of the digest of ``n`` blocks, which three steps before the end no later one changes."""
    return _mixed(words, n, 61)[1] + np.uint32(_START[0])


def _number(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    return first.byteswap().astype(np.uint64) << np.uint64(20) | (second.byteswap() >> np.uint32(12)).astype(np.uint64)


class Keys:
    """The bytes of a column of strings, laid out for digests of many prefixes."""

    def __init__(self, column: pa.Array):
        column = column.cast(pa.binary())
        at = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
        data = np.frombuffer(column.buffers()[2] or b"", np.uint8)
        self.n, self.size = len(column), np.diff(at)
        self.parts = []  # rows of one length, and their bytes
        for size in np.unique(self.size):
            rows = np.flatnonzero(self.size == size)
            self.parts.append((int(size), rows, data[at[rows][:, None] + np.arange(size)]))
        self.laid: dict[int, list] = {}

    def _layout(self, room: int) -> list[list]:
        """The sixteen words of every block, ``room`` bytes left for a prefix, some rows at a time."""
        if room not in self.laid:
            block = np.zeros((self.n, 64), np.uint8)
            for size, rows, data in self.parts:
                if room + size <= ROOM:
                    block[rows, room : room + size] = data
                    block[rows, room + size] = 0x80
                    block[rows, 56:58] = np.frombuffer((8 * (room + size)).to_bytes(2, "little"), np.uint8)
            words = np.ascontiguousarray(block.view("<u4").T)
            self.laid[room] = [[w[i : i + STEP] if w.any() else 0 for w in words] for i in range(0, self.n, STEP)]
        return self.laid[room]

    def _digests(self, prefix: bytes) -> Iterator[tuple[list, int]]:
        """The words of the blocks of the prefix followed by each key, and the number of rows, some rows at a time."""
        head, at = np.frombuffer(prefix + bytes(64 - len(prefix)), "<u4").tolist(), 0
        for part in self._layout(len(prefix)):
            n = min(STEP, self.n - at)
            yield [w | np.uint32(h) if h and not isinstance(w, int) else (w or h if isinstance(w, int) else w) for w, h in zip(part, head, strict=True)], n
            at += n

    def _long(self, room: int) -> Iterator[tuple[int, bytes]]:
        """The rows that do not fit a block, and their keys."""
        for size, rows, data in self.parts:
            if room + size > ROOM:
                yield from ((int(row), x.tobytes()) for row, x in zip(rows, data, strict=True))

    def uniform(self, prefix: bytes) -> np.ndarray:
        """A number in (0, 1) for the prefix followed by each key, as ``seeds.uniform`` gives it."""
        room, numbers = len(prefix), []
        if room > ROOM:
            numbers.append(np.zeros(self.n, np.uint64))
        else:
            numbers += [_number(*_two_words(words, n)) for words, n in self._digests(prefix)]
        number = np.concatenate([np.empty(0, np.uint64), *numbers])
        for row, key in self._long(room):
            number[row] = _single(prefix + key)
        return _fraction(number)

    def maybe_below(self, prefix: bytes, most: np.ndarray) -> np.ndarray:
        """Rows, among them all of which the number is at most its first 32 bits, ``most``, let it be."""
        room = len(prefix)
        if room > ROOM:
            return np.arange(self.n)
        found, at = [np.empty(0, np.int64)], 0
        for words, n in self._digests(prefix):
            found.append(at + np.flatnonzero(_one_word(words, n).byteswap() <= most[at : at + n]))
            at += n
        long = [rows for size, rows, _ in self.parts if room + size > ROOM]
        return np.unique(np.concatenate([*found, *long])) if long else np.concatenate(found)


def _single(message: bytes) -> int:
    return int(hashlib.md5(message).hexdigest()[:13], 16)


def _fraction(number: np.ndarray) -> np.ndarray:
    return (number.astype(np.float64) + 0.5) / float(2**52)


def _first_bits(most: np.ndarray) -> np.ndarray:
    """The greatest first 32 bits of a number that is below ``most``."""
    return (np.clip(most, 0.0, 1.0) * float(2**32)).clip(0, 2**32 - 1).astype(np.uint32)


def _gathered(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """The batches put together, so that all but the last have so many rows at least."""
    held, n = [], 0
    for batch in batches:
        held, n = [*held, batch], n + batch.num_rows
        if n >= rows:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def kept_draws(names: list[str], salt: str, runs: int, shared: bool, unit: bool, bounds: list[float]):
    """For ``mapInArrow`` over key, w0, w1, ...: run, key, the weights and seeds u0, u1, ... of the keys of which the seed
    over the weight is below the bound in some assignment."""
    m = range(len(names))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _gathered(batches, 2 * STEP):
            keys, w = Keys(batch.column(0)), [batch.column(1 + i).to_numpy() for i in m]
            most = [np.where(x > 0, b * (np.ones(len(x)) if unit else x), -1.0) if b < np.inf else np.where(x > 0, 2.0, -1.0) for x, b in zip(w, bounds, strict=True)]
            # a shared seed is below some bound if it is below the greatest
            first = [_first_bits(np.max(most, axis=0))] if shared else [_first_bits(x) for x in most]
            few = sum(float(np.clip(x, 0.0, 1.0).sum()) for x in most) < len(batch) / FEW
            found: list[tuple] = []
            for r in range(runs):
                prefixes = [f"{salt}#{r}|".encode()] if shared else [f"{salt}#{r}|{b}|".encode() for b in names]
                if few:
                    some = np.unique(np.concatenate([keys.maybe_below(p, x) for p, x in zip(prefixes, first, strict=True)]))
                    texts = [str(k).encode() for k in batch.column(0).take(pa.array(some))]
                    u = [_fraction(np.array([_single(p + t) for t in texts], np.uint64)) for p in prefixes]
                else:
                    some, u = np.arange(len(batch)), [keys.uniform(p) for p in prefixes]
                u = u * len(names) if shared else u
                at = np.flatnonzero(np.any([x < y[some] for x, y in zip(u, most, strict=True)], axis=0))
                found.append((np.full(len(at), r, np.int32), some[at], *[x[at] for x in u]))
            columns = [np.concatenate(x) for x in zip(*found, strict=True)]
            rows = pa.array(columns[1])
            yield pa.RecordBatch.from_arrays([pa.array(columns[0]), *[c.take(rows) for c in batch.columns], *map(pa.array, columns[2:])], ["run", "key", *[f"w{i}" for i in m], *[f"u{i}" for i in m]])

    return run
