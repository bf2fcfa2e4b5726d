"""Stupid-backoff language-model scores, with n-gram counts from all documents.

``S(w | u) = c(uw) / c(u)`` where the corpus has the n-gram ``uw``, else ``BACKOFF`` times the
score with the context shortened by its first word; a single word scores ``c(w) / N``.  A document is
part of the corpus that it is scored by; so that its n-grams do not vouch for themselves, ``c`` of n-grams of
two words and more, and of their contexts, leaves out the document's own ones (``leave_out``).

The relation of n-grams is kept in blocks.  A block is a bounded number of whole documents, one after
the other.  It sends each distinct n-gram with its count once, dealt to partitions by hash; there the
counts are summed into the n-gram table and the sums joined back to every block that asked.  The block
then scores the n-grams of its documents, and the scores are summed for each document.  A frequent
n-gram is thus one entry a block, not one a document, and no partition gets more than a bounded number of
entries on average.

The documents are read twice, once to ask and once to score, as that is cheaper than to keep their
blocks on disk meanwhile.  Both readings must cut the same blocks, which a scan of files does; any other
input is written first.  Answers carry a checksum of the n-grams they are for, so a block cut otherwise raises an error.

Defined results: null, empty and blank texts have no words and score 0; a text's first words have
shorter contexts; repeated rows are documents of their own, count each time and get a row each; a text of any length
is in one block, whose memory grows with it; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedrank.llm.arrow import list_parts, mix64, window_hashes
from seedrank.llm.common import hashed_words, named, ship, table, words_of, written

ORDER = 3
BACKOFF = 0.4
#: Least and greatest number of words in a block and of entries in a bucket, and the entries of a block that
#: a bucket should get at least.
LEAST_WORDS, MOST_WORDS = 2_000_000, 16_000_000
SHARED_ENTRIES = 64


#: Words looked at in one go, and the longest n-grams that blocks are cut for.
_PART = 1 << 18
ORDER_LIMIT = 8


def _places(known: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Where each value stands in ``known`` (ascending, with all of them); sorted values are found in passing."""
    order = np.argsort(values)
    out = np.empty(len(values), np.int64)
    out[order] = np.searchsorted(known, values[order])
    return out


class _Block:
    """Some documents: their ids, numbers of words, and words in a row."""

    def __init__(self, ids: pa.Array, sizes: np.ndarray, words: np.ndarray):
        self.ids, self.sizes, self.words = ids, sizes, words
        self.starts = np.cumsum(sizes) - sizes
        # how many words of the same document stand before each word, as far as it matters
        self.before = np.full(len(words), 127, np.int8)
        for i in range(127):
            longer = self.starts[sizes > i] + i
            if i >= ORDER_LIMIT or not len(longer):
                break
            self.before[longer] = i

    def grams(self, n: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """The n-grams, part by part: hashes, and the positions of their last words."""
        for a in range(n - 1, len(self.words), _PART):
            b = min(a + _PART, len(self.words))
            inside = self.before[a:b] >= n - 1
            yield window_hashes(self.words[a - n + 1 : b], n)[inside], np.flatnonzero(inside) + a

    def whole(self, n: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """The n-grams, whole documents at a time: hashes, positions of last words, numbers of documents."""
        cuts = np.searchsorted(self.starts + self.sizes, np.arange(_PART, len(self.words) + _PART, _PART))
        first = 0
        for last in np.unique(np.minimum(cuts + 1, len(self.sizes))).tolist():
            a, b = self.starts[first], self.starts[last - 1] + self.sizes[last - 1]
            if b - a >= n:
                inside = self.before[a + n - 1 : b] >= n - 1
                at = np.flatnonzero(inside) + a + n - 1
                yield window_hashes(self.words[a:b], n)[inside], at, np.searchsorted(self.starts[first:last], at, "right") + first
            first = last

    def distinct(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """The distinct n-grams in ascending order, with their numbers."""
        parts = [h for h, _ in self.grams(n)]
        hashes = np.concatenate(parts) if parts else np.empty(0, np.uint64)
        del parts
        hashes.sort()
        first = np.flatnonzero(np.concatenate([[True], hashes[1:] != hashes[:-1]])) if len(hashes) else np.empty(0, np.int64)
        return hashes[first], np.diff(np.append(first, len(hashes))).astype("<u4")


def _cut(batches: Iterator[pa.RecordBatch], block_words: int) -> Iterator[tuple[int, _Block]]:
    """The blocks of one partition, with numbers that no other partition has."""
    from pyspark import TaskContext

    number = TaskContext.get().partitionId() << 32
    ids, words, sizes, held = [], [], [], 0

    def block() -> _Block:
        return _Block(pa.concat_arrays(ids), np.concatenate(sizes).astype(np.int64), np.concatenate(words))

    for batch in batches:
        if batch.num_rows:
            offsets, values = list_parts(batch.column(1))
            ids.append(batch.column(0))
            words.append(values[offsets[0] : offsets[-1]].copy())
            sizes.append(np.diff(offsets))
            held += len(words[-1])
        if held >= block_words:
            yield number, block()
            number, ids, words, sizes, held = number + 1, [], [], [], 0
    if ids:
        yield number, block()


def _pack(values: np.ndarray) -> bytes:
    """An array by planes of byte significance, compressed: ascending or small values leave little."""
    planes = np.ascontiguousarray(values.view(np.uint8).reshape(len(values), values.itemsize).T)
    return zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def _unpack(data: bytes, kind: str) -> np.ndarray:
    width = np.dtype(kind).itemsize
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8).reshape(width, -1)
    return np.ascontiguousarray(planes.T).reshape(-1).view(kind)


def _occurrences(hashes: np.ndarray, documents: np.ndarray) -> np.ndarray:
    """How often each n-gram stands in its own document."""
    pairs = mix64(hashes + documents.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    order = np.argsort(pairs)
    pairs = pairs[order]
    first = np.flatnonzero(np.concatenate([[True], pairs[1:] != pairs[:-1]]))
    counts = np.diff(np.append(first, len(pairs)))
    out = np.empty(len(pairs), np.int64)
    out[order] = np.repeat(counts, counts)
    return out


def _bucket_edges(hashes: np.ndarray, buckets: int) -> np.ndarray:
    edges = np.array([(b << 64) // buckets for b in range(1, buckets)], dtype=np.uint64)
    return np.concatenate([[0], np.searchsorted(hashes, edges), [len(hashes)]])


_REQUEST = "bucket int, block long, n int, entries int, check long, grams binary, counts binary"
_BLOCK = "block long, ids array<long>, sizes array<int>, dictionary binary, codes binary"
_ANSWER = "block long, n int, bucket int, check long, totals binary"
_SCORE = "doc_id long, n_words long, score double"


def _check(grams: np.ndarray) -> int:
    """A checksum of the n-grams of one request."""
    return int(grams.sum(dtype=np.uint64).view(np.int64))


def _asked(buckets: int, order: int, block_words: int):
    """Distinct n-grams of each block with counts, in the order of their hashes, cut into buckets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [c.split()[0] for c in _REQUEST.split(", ")]
        kinds = [pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary()]
        for number, block in _cut(batches, block_words):
            for n in range(1, order + 1):
                grams, counts = block.distinct(n)
                cuts = _bucket_edges(grams, buckets)
                rows = []
                for b in np.flatnonzero(np.diff(cuts)).tolist():
                    part = grams[cuts[b] : cuts[b + 1]]
                    steps = np.concatenate([part[:1], np.diff(part)])
                    rows.append((b, number, n, len(part), _check(part), _pack(steps), _pack(counts[cuts[b] : cuts[b + 1]])))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    return run


def _answered(rows: pa.Table) -> pa.Table:
    """Corpus counts of the n-grams of one bucket, handed to each request in its own order."""
    rows = rows.combine_chunks()
    sizes, orders = rows.column("entries").to_numpy(), rows.column("n").to_numpy()
    totals: list[bytes] = [b""] * len(sizes)
    for n in np.unique(orders).tolist():  # hashes of unlike orders never meet
        mine = np.flatnonzero(orders == n).tolist()
        grams = np.concatenate([np.cumsum(_unpack(rows.column("grams")[i].as_py(), "<u8"), dtype=np.uint64) for i in mine])
        counts = np.concatenate([_unpack(rows.column("counts")[i].as_py(), "<u4") for i in mine])
        which = np.unique(grams, return_inverse=True)[1]
        total = np.bincount(which, counts)[which].astype("<i8")
        at = 0
        for i in mine:
            totals[i] = _pack(total[at : at + sizes[i]])
            at += int(sizes[i])
    return pa.table({"block": rows.column("block"), "n": rows.column("n"), "bucket": rows.column("bucket"), "check": rows.column("check"), "totals": pa.array(totals, pa.binary())})


def _coded(block_words: int):
    """Each block as one row: words as codes into its own dictionary, small codes for frequent words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for number, block in _cut(batches, block_words):
            known, counts = np.unique(block.words, return_counts=True)
            order = np.argsort(-counts, kind="stable")
            place = np.empty(len(order), "<u4")
            place[order] = np.arange(len(order), dtype="<u4")
            codes = np.empty(len(block.words), "<u4")
            for a in range(0, len(codes), _PART):
                codes[a : a + _PART] = place[_places(known, block.words[a : a + _PART])]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([number], pa.int64()),
                    pa.ListArray.from_arrays(pa.array([0, len(block.ids)], pa.int32()), block.ids),
                    pa.ListArray.from_arrays(pa.array([0, len(block.ids)], pa.int32()), pa.array(block.sizes, pa.int32())),
                    pa.array([_pack(known[order])], pa.binary()),
                    pa.array([_pack(codes)], pa.binary()),
                ],
                ["block", "ids", "sizes", "dictionary", "codes"],
            )

    return run


def _scored(buckets: int, order: int, backoff: float, min_count: int, corpus_words: int, leave_out: bool):
    def run(rows: pa.Table, answers: pa.Table) -> pa.Table:
        row = rows.combine_chunks()
        known, codes = _unpack(row.column("dictionary")[0].as_py(), "<i8"), _unpack(row.column("codes")[0].as_py(), "<u4")
        block = _Block(row.column("ids")[0].values, row.column("sizes")[0].values.to_numpy().astype(np.int64), known[codes] if len(codes) else np.empty(0, np.int64))
        del known, codes
        words = len(block.words)
        parts = {(n, b): (c, t) for n, b, c, t in zip(*(answers.column(x).to_pylist() for x in ("n", "bucket", "check", "totals")), strict=True)}
        # log score of each word by the longest context that the corpus knows, from the shortest up
        log_score, context = np.zeros(words), np.full(words + 1, float(corpus_words))
        for n in range(1, order + 1):
            distinct = block.distinct(n)[0]
            total = np.empty(len(distinct), np.int64)
            cuts = _bucket_edges(distinct, buckets)
            for b in np.flatnonzero(np.diff(cuts)).tolist():
                check, packed = parts.pop((n, b), (None, None))
                if check != _check(distinct[cuts[b] : cuts[b + 1]]):
                    raise RuntimeError("the documents were cut into other blocks when they were read again")
                total[cuts[b] : cuts[b + 1]] = _unpack(packed, "<i8")
            longer = np.ones(words + 1)
            for hashes, at, documents in block.whole(n):
                count = total[_places(distinct, hashes)]
                rest = count.astype(np.float64)
                if leave_out:
                    # what the corpus has once is the document's own
                    rest[count == 1] = 0
                    more = np.flatnonzero(count > 1)
                    rest[more] -= _occurrences(hashes[more], documents[more]) if len(more) else 0
                if n == 1:
                    log_score[at] = np.log(count) - np.log(context[at])
                else:
                    seen = rest >= min_count
                    fresh = np.log(np.where(seen, rest, 1.0)) - np.log(np.where(seen, context[at], 1.0))
                    log_score[at] = np.where(seen, fresh, np.log(backoff) + log_score[at])
                # the count of this n-gram is that of the context of the word after it
                longer[at + 1] = rest
            context = longer
        ends = np.concatenate([[0], np.cumsum(log_score)])
        score = ends[block.starts + block.sizes] - ends[block.starts]
        return pa.table({"doc_id": block.ids, "n_words": pa.array(block.sizes), "score": pa.array(score)})

    return run


def block_size(words: int) -> int:
    """Words in a block, and entries in a bucket, for a corpus of so many words.

    A block's share of a bucket is its entries over the number of buckets; both sizes grow with the root
    of the corpus, so that this share does not fall below ``SHARED_ENTRIES`` before memory ends it.
    """
    return int(min(MOST_WORDS, max(LEAST_WORDS, (SHARED_ENTRIES * words) ** 0.5)))


def score_documents(
    docs: DataFrame, order: int = ORDER, backoff: float = BACKOFF, min_count: int = 1, leave_out: bool = True, doc_id: str = "doc_id", text: str = "text",
    block_words: int | None = None, bucket_entries: int | None = None, plain_scan: bool = False,
) -> DataFrame:
    """doc_id, n_words and score (the sum of the natural logarithms of S over the words) of every document.

    ``min_count``: n-grams of two words and more that are counted fewer times back off.  ``plain_scan``
    says that ``docs`` is a scan of files, which comes in the same rows and partitions whenever it is read.
    """
    if order > ORDER_LIMIT:
        raise ValueError(f"n-grams of more than {ORDER_LIMIT} words")
    ship(docs.sparkSession)
    source = docs.select(named(doc_id).cast("long").alias("doc_id"), named(text).alias("text"))
    source = source if plain_scan else written(source)
    total = source.agg(F.sum(F.size(words_of(F.col("text"))))).first()[0] or 0
    block_words, bucket_entries = block_words or block_size(total), bucket_entries or block_size(total)
    buckets = max(1, -(-total * order // bucket_entries))
    rows = source.select("doc_id", hashed_words(F.col("text")).alias("words"))
    answers = rows.mapInArrow(_asked(buckets, order, block_words), _REQUEST).groupBy("bucket").applyInArrow(_answered, _ANSWER)
    blocks = rows.mapInArrow(_coded(block_words), _BLOCK)
    return blocks.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(_scored(buckets, order, backoff, min_count, total, leave_out), _SCORE)


def op10_lm(spark, sf_dir: str) -> DataFrame:
    out = score_documents(table(spark, sf_dir, "documents"), plain_scan=True)
    mean = F.when(F.col("n_words") > 0, F.col("score") / F.col("n_words")).otherwise(0.0)
    return out.select("doc_id", "n_words", F.round("score", 3).alias("lm_score"), F.round(mean, 5).alias("lm_mean"))


OP10_SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
p AS (SELECT doc_id, ws, unnest(range(1, len(ws) + 1)) AS i FROM d),
g AS (
  SELECT doc_id, i, ws[i] AS w, CASE WHEN i >= 2 THEN ws[i-1] || ' ' || ws[i] END AS g2,
         CASE WHEN i >= 3 THEN ws[i-2] || ' ' || ws[i-1] || ' ' || ws[i] END AS g3,
         CASE WHEN i >= 2 THEN ws[i-1] END AS u1, CASE WHEN i >= 3 THEN ws[i-2] || ' ' || ws[i-1] END AS u2
  FROM p),
o AS (
  SELECT doc_id, w AS k, count(*) AS c FROM g GROUP BY 1, 2
  UNION ALL SELECT doc_id, g2, count(*) FROM g WHERE g2 IS NOT NULL GROUP BY 1, 2
  UNION ALL SELECT doc_id, g3, count(*) FROM g WHERE g3 IS NOT NULL GROUP BY 1, 2),
t AS (SELECT k, sum(c) AS c FROM o GROUP BY 1),
r AS (SELECT o.doc_id, o.k, t.c AS every, t.c - o.c AS c FROM o JOIN t USING (k)),
s AS (
  SELECT g.doc_id,
    CASE WHEN c3.c >= 1 THEN ln(c3.c) - ln(cu2.c)
         WHEN c2.c >= 1 THEN ln(c2.c) - ln(cu1.c) + CASE WHEN g3 IS NULL THEN 0 ELSE ln(0.4) END
         ELSE ln(c1.every) - ln((SELECT count(*) FROM g)) + CASE WHEN g2 IS NULL THEN 0 ELSE ln(0.4) END + CASE WHEN g3 IS NULL THEN 0 ELSE ln(0.4) END
    END AS x
  FROM g JOIN r c1 ON c1.k = g.w AND c1.doc_id = g.doc_id
  LEFT JOIN r c2 ON c2.k = g.g2 AND c2.doc_id = g.doc_id LEFT JOIN r c3 ON c3.k = g.g3 AND c3.doc_id = g.doc_id
  LEFT JOIN r cu1 ON cu1.k = g.u1 AND cu1.doc_id = g.doc_id LEFT JOIN r cu2 ON cu2.k = g.u2 AND cu2.doc_id = g.doc_id),
a AS (SELECT doc_id, sum(x) AS score FROM s GROUP BY doc_id)
SELECT d.doc_id, CAST(len(ws) AS BIGINT) AS n_words, round(coalesce(score, 0), 3) AS lm_score,
       CASE WHEN len(ws) > 0 THEN round(score / len(ws), 5) ELSE 0 END AS lm_mean
FROM d LEFT JOIN a USING (doc_id)
"""
