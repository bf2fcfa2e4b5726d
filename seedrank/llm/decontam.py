"""Benchmark decontamination by winnowing, in DataFrame functions only.

A document and a benchmark item are cut into the same word k-grams.  In every run of ``span`` words
the k-gram of least hash is a fingerprint, and it depends on those words alone; so two texts that
share ``span`` words in a row share a fingerprint inside them.  Fingerprints are joined, and each
hit is extended word by word to the shared run; runs of ``span`` words or more count.  The words
themselves are compared, so equal hashes of unlike words do no harm.

An item of fewer than ``span`` words counts as one window of its own length and is matched whole.

Defined results: null, empty or wordless texts have no words and no hits, and such items match
nothing; an item without an id hits words as others do, and is in no list of items; repeated rows give a
row each; an empty benchmark leaves every document clean; texts of any length are matched whole; other columns of
the tables, whatever their names, are ignored by the search and kept by ``decontaminate``.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seedrank.llm.common import fresh, let, named, sha256_text, sized, table, text_key, written

SPAN = 10
GRAM = 5
#: Fingerprint rows up to which the benchmark is broadcast (some 200 bytes each).
BROADCAST_ROWS = 200_000

NOT_WORD = "[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"


def ascii_lower(text: Column) -> Column:
    """``text`` with A-Z in lower case and all else as it is.

    ``lower`` is several times faster than ``translate`` and does the same where no other
    upper-case letter stands in the text.
    """
    other = text.rlike("[\\p{IsUppercase}\\p{Lt}&&[^A-Z]]")
    return F.when(other, F.translate(text, string.ascii_uppercase, string.ascii_lowercase)).otherwise(F.lower(text))


def match_words(text: Column) -> Column:
    return F.array_remove(F.split(ascii_lower(F.coalesce(text, F.lit(""))), NOT_WORD, -1), "")


def _grams(words: Column, k: int) -> Column:
    """Hashes of the k-grams of ``words`` by position."""
    size = F.greatest(F.size(words) - (k - 1), F.lit(0))
    shifted = [F.slice(words, i + 1, size).alias(f"w{i}") for i in range(k)]
    return F.transform(F.arrays_zip(*shifted), lambda z: F.xxhash64(z))


def _bound(body, step: int):
    def of(a: Column) -> Column:
        return body(step, a)

    return of


def _window_minima(grams: Column, window: int) -> Column:
    """Distinct least hashes of every ``window`` neighbours; minima over powers of two are combined."""

    def narrowed(step: int, a: Column) -> Column:
        size = F.greatest(F.size(a) - step, F.lit(0))
        return F.zip_with(F.slice(a, 1, size), F.slice(a, step + 1, size), lambda x, y: F.least(x, y))

    out, reach = grams, 1
    while reach < window:
        step = min(reach, window - reach)
        out = let(out, _bound(narrowed, step))
        reach += step
    return F.array_distinct(out)


def _around(words: Column, at: Column, k: int, pad: int) -> Column:
    """The k-gram at 0-based position ``at`` with ``pad`` words on either side; null beyond the text."""
    return F.transform(F.sequence(at - pad, at + (k + pad - 1)), lambda j: F.when(j >= 0, F.get(words, j)))


def fingerprints(benchmark: DataFrame, span: int = SPAN, k: int = GRAM, item: str = "item_id", text: str = "text") -> DataFrame:
    """(hash, item_id, m, ctx): ``m`` is 0 for a fingerprint of a long item, else a short item's length."""
    items = benchmark.select(named(item).alias("item_id"), match_words(named(text)).alias("words"))
    items = items.where(F.size("words") > 0)
    long = items.where(F.size("words") >= span).withColumn("grams", _grams(F.col("words"), k))
    long = long.withColumn("minima", _window_minima(F.col("grams"), span - k + 1))
    long = long.select("item_id", "words", "minima", F.posexplode("grams").alias("q", "hash"))
    long = long.where(F.array_contains("minima", F.col("hash")))
    long = long.select("hash", "item_id", F.lit(0).alias("m"), _around(F.col("words"), F.col("q"), k, span - k).alias("ctx"))
    short = items.where(F.size("words") < span)
    short = short.select(_short_hash(F.col("words")).alias("hash"), "item_id", F.size("words").alias("m"), F.col("words").alias("ctx"))
    return long.unionByName(short).distinct()


def _short_hash(words: Column) -> Column:
    return F.xxhash64(F.lit("whole"), words)


def _short_probes(words: Column, lengths: list[int]) -> list[Column]:
    def of(m: int) -> Column:
        starts = F.when(F.size(words) >= m, F.sequence(F.lit(1), F.size(words) - (m - 1))).otherwise(F.array().cast("array<int>"))
        return F.array_distinct(F.transform(starts, lambda i: _short_hash(F.slice(words, i, m))))

    return [of(m) for m in lengths]


def _shared_runs(words: Column, grams: Column, hash_: Column, ctx: Column, m: Column, span: int, k: int) -> Column:
    """Array of (first, last) word positions at which the document holds windows of the item."""
    pad = span - k

    def run_of(at: Column) -> Column:
        same = F.transform(F.zip_with(_around(words, at, k, pad), ctx, lambda a, b: a == b), lambda x: F.coalesce(x, F.lit(False)))

        def extend(eq: Column) -> Column:
            left = F.array_position(F.reverse(F.slice(eq, 1, pad)), False)
            right = F.array_position(F.slice(eq, pad + k + 1, pad), False)
            left = F.when(left == 0, F.lit(pad)).otherwise(left - 1).cast("int")
            right = F.when(right == 0, F.lit(pad)).otherwise(right - 1).cast("int")
            core = ~F.array_contains(F.slice(eq, pad + 1, k), False)
            return F.when(core & (left + right + k >= span), F.struct((at - left).alias("first"), (at + (k - 1) + right).alias("last")))

        return let(same, extend)

    places = F.filter(F.transform(grams, lambda g, i: F.when(g == hash_, i)), lambda i: i.isNotNull())
    long = F.filter(F.transform(places, run_of), lambda r: r.isNotNull())
    starts = F.sequence(F.lit(0), F.greatest(F.size(words) - m, F.lit(0)))
    whole = F.filter(starts, lambda i: F.slice(words, i + 1, m) == ctx)
    short = F.transform(whole, lambda i: F.struct(i.cast("int").alias("first"), (i + m - 1).cast("int").alias("last")))
    return F.when(m == 0, long).otherwise(short)


def _covered(runs: Column) -> Column:
    """Number of positions in the union of (first, last) runs."""
    start = F.struct(F.lit(0).alias("n"), F.lit(-1).alias("upto"))

    def step(acc: Column, r: Column) -> Column:
        new = F.greatest(F.lit(0), r["last"] - F.greatest(r["first"] - 1, acc["upto"]))
        return F.struct((acc["n"] + new).alias("n"), F.greatest(acc["upto"], r["last"]).alias("upto"))

    return F.aggregate(F.array_sort(runs), start, step, lambda acc: acc["n"])


def contamination(docs: DataFrame, benchmark: DataFrame, span: int = SPAN, k: int = GRAM, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each document: doc_id, its text's two hashes, n_words, n_hit, item_ids."""
    prints = fingerprints(benchmark, span, k)
    known = prints.agg(F.count(F.lit(1)), F.collect_set(F.when(F.col("m") > 0, F.col("m")))).first()
    lengths = sorted(known[1])
    k1, k2 = text_key(named(text))
    source = docs.select(named(doc_id).alias("doc_id"), k1.alias("k1"), k2.alias("k2"), match_words(named(text)).alias("words"))
    staged = source.withColumn("grams", F.when(F.size("words") >= span, _grams(F.col("words"), k)))
    probes = F.when(F.size("words") >= span, _window_minima(F.col("grams"), span - k + 1)).otherwise(F.array().cast("array<bigint>"))
    probes = F.concat(probes, *_short_probes(F.col("words"), lengths))
    key = ["doc_id", "k1", "k2"]
    # one more probe for each document, which meets a row of its own, carries the word count through
    # the join; an inner join drops the rest before any row with its words is copied
    bare = F.xxhash64(F.lit("every document"))
    probed = staged.withColumn("hash", F.explode(F.array_append(probes, bare)))
    runs = _shared_runs(F.col("words"), F.col("grams"), F.col("hash"), F.col("ctx"), F.col("m"), span, k)
    if known[0] <= BROADCAST_ROWS:
        own = prints.sparkSession.range(1).select(bare.alias("hash"), F.lit(None).cast(prints.schema["item_id"].dataType).alias("item_id"), F.lit(-1).alias("m"), F.lit(None).cast("array<string>").alias("ctx"))
        met = probed.join(F.broadcast(prints.unionByName(own)), "hash")
    else:  # the words stay out of the shuffle by hash; a second one by text brings them to the matches
        pairs = probed.where(F.col("hash") != bare).select(*key, "hash").distinct().join(prints, "hash")
        same = [F.col(f"p.{c}").eqNullSafe(F.col(f"d.{c}")) for c in key]
        hits = staged.alias("d").join(pairs.alias("p"), on=same).select(*[f"d.{c}" for c in key], "words", "grams", "hash", "item_id", "m", "ctx")
        own = staged.select(*key, "words", "grams", bare.alias("hash"), F.lit(None).cast(prints.schema["item_id"].dataType).alias("item_id"), F.lit(-1).alias("m"), F.lit(None).cast("array<string>").alias("ctx"))
        met = hits.unionByName(own)
    met = met.withColumn("runs", F.when(F.col("m") >= 0, runs)).where((F.col("m") < 0) | (F.size("runs") > 0))
    found = met.select(*key, "item_id", "runs", (F.col("m") < 0).alias("bare"), F.size("words").cast("long").alias("n_words"))
    per_doc = found.groupBy(*key).agg(
        F.max("n_words").alias("n_words"),
        F.count_if("bare").alias("copies"),
        F.flatten(F.collect_set("runs")).alias("runs"),
        F.collect_set("item_id").alias("item_ids"),
    )
    out = per_doc.select(*key, "n_words", _covered(F.array_distinct("runs")).cast("long").alias("n_hit"), "item_ids", F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int"))).alias("_copy"))
    return out.drop("_copy")


def decontaminate(docs: DataFrame, benchmark: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` without the documents that hold a window of the benchmark; columns as they were."""
    hit = contamination(docs.select(F.lit(0).alias("doc_id"), named(text).alias("text")), benchmark)
    own = fresh(docs, "k1", "k2")
    hit = hit.where(F.col("n_hit") > 0).select(F.col("k1").alias(own[0]), F.col("k2").alias(own[1])).distinct()
    hit = sized(written(hit))
    return docs.join(hit, on=[key == F.col(name) for key, name in zip(text_key(named(text)), own, strict=True)], how="left_anti")


def op6_decontam(spark, sf_dir: str) -> DataFrame:
    found = contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    ids = F.array_join(F.array_sort(F.transform("item_ids", lambda x: x.cast("string"))), ",")
    return found.select(
        "doc_id", "n_words", "n_hit",
        F.size("item_ids").cast("long").alias("n_items"),
        sha256_text(ids).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
    )


OP6_SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                                    '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
i AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                                     '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
iw AS (
  SELECT DISTINCT item_id, least(10, len(ws)) AS m, array_to_string(ws[p:p + least(10, len(ws)) - 1], ' ') AS gram
  FROM (SELECT item_id, ws, unnest(range(1, greatest(len(ws) - 9, 1) + 1)) AS p FROM i WHERE len(ws) > 0)),
dw AS (
  SELECT doc_id, m, p, array_to_string(ws[p:p + m - 1], ' ') AS gram
  FROM (SELECT doc_id, ws, m, unnest(range(1, len(ws) - m + 2)) AS p
        FROM d, (SELECT DISTINCT m FROM iw) WHERE len(ws) >= m)),
hit AS (SELECT doc_id, item_id, dw.m AS m, p FROM dw JOIN iw ON dw.gram = iw.gram AND dw.m = iw.m),
words AS (
  SELECT doc_id, count(DISTINCT pos) AS n_hit
  FROM (SELECT doc_id, unnest(range(p, p + m)) AS pos FROM hit) GROUP BY doc_id),
items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS ids
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM hit) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)
"""
