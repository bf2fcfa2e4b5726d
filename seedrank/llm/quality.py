"""Quality rules as a short-circuit cascade, in DataFrame functions only.

Each rule is a rejecting predicate over metrics of a text.  On a small sample the operator
measures what a rule costs and how much it rejects, orders the rules by rejection per cost and
evaluates them as one lazy ``CASE``: a document that an early rule rejects never reaches the later
ones.  The verdict does not depend on the order; only the time and the named reason do.

Defined results: null, empty and blank texts have no words and are rejected by ``few_words``;
repeated rows are judged one by one; a text of any length is judged whole; an empty table gives no
rows; extra columns pass through, and a column of the input that has the name of a result is replaced
by the result.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Mapping
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seedrank.llm.common import SPACE_CHARS, fresh, let, named, words_of

REPEAT_WINDOW = 5


def _repeated_words(words: Column, k: int = REPEAT_WINDOW) -> Column:
    """Words that lie in a window of ``k`` words which the text has twice or more.

    Windows are compared by hash.  The usual text has none twice, which a hash set shows in
    linear time; only others are sorted, so that equal windows stand side by side.
    """
    count = F.size(words) - (k - 1)

    def grams(ws: Column) -> Column:
        shifted = [F.slice(ws, i + 1, F.greatest(F.size(ws) - (k - 1), F.lit(0))).alias(f"w{i}") for i in range(k)]
        return F.transform(F.arrays_zip(*shifted), lambda z: F.xxhash64(z))

    def covered(hashes: Column) -> Column:
        ordered = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("p"))))

        def positions(s: Column) -> Column:
            same = F.filter(s, lambda e, i: (e["h"] == F.get(s, i - 1)["h"]) | (e["h"] == F.get(s, i + 1)["h"]))
            return F.array_sort(F.transform(same, lambda e: e["p"]))

        def total(p: Column) -> Column:
            steps = F.zip_with(p, F.slice(p, 2, F.size(p)), lambda a, b: F.least(F.lit(k), F.coalesce(b - a, F.lit(k))))
            return F.aggregate(steps, F.lit(0), lambda acc, x: acc + x)

        return let(let(ordered, positions), total)

    def counted(hashes: Column) -> Column:
        return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), F.lit(0)).otherwise(covered(hashes))

    return F.when(count < 2, F.lit(0)).otherwise(let(grams(words), counted)).cast("long")


def _duplicate_lines(text: Column) -> Column:
    lines = F.filter(F.split(F.coalesce(text, F.lit("")), "\n", -1), lambda l: F.btrim(l, F.lit(SPACE_CHARS)) != "")
    return let(lines, lambda ls: F.size(ls) - F.size(F.array_distinct(ls))).cast("long")


#: Metric name -> expression over (text, array of its words).
METRICS: dict[str, Callable[[Column, Column], Column]] = {
    "n_words": lambda text, words: F.size(words).cast("long"),
    "word_chars": lambda text, words: F.length(F.array_join(words, "")).cast("long"),
    "n_symbols": lambda text, words: F.coalesce(F.regexp_count(text, F.lit("[#*$%&|<>]")), F.lit(0)).cast("long"),
    "n_dup_lines": lambda text, words: _duplicate_lines(text),
    "n_repeat_words": lambda text, words: _repeated_words(words),
    "n_exclaims": lambda text, words: F.coalesce(F.regexp_count(text, F.lit("!!")), F.lit(0)).cast("long"),
}
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


@dataclass(frozen=True)
class Rule:
    """``rejects`` gets a mapping from metric name to Column and returns true for a bad document;
    ``metrics`` names those that it reads."""

    name: str
    rejects: Callable[[Mapping[str, Column]], Column]
    metrics: tuple[str, ...] = ()


RULES: tuple[Rule, ...] = (
    Rule("few_words", lambda m: m["n_words"] < 10, ("n_words",)),
    Rule("repeated_windows", lambda m: 100 * m["n_repeat_words"] > 20 * m["n_words"], ("n_repeat_words", "n_words")),
    Rule("symbols", lambda m: 10 * m["n_symbols"] > 2 * m["n_words"], ("n_symbols", "n_words")),
    Rule("exclaims", lambda m: 10 * m["n_exclaims"] > 2 * m["n_words"], ("n_exclaims", "n_words")),
    Rule("word_length", lambda m: (m["word_chars"] < 2 * m["n_words"]) | (m["word_chars"] > 20 * m["n_words"]), ("word_chars", "n_words")),
    Rule("duplicate_lines", lambda m: 10 * m["n_dup_lines"] > 3 * m["n_words"], ("n_dup_lines", "n_words")),
)
BASE_RULES = ("few_words", "repeated_windows")


class _Metrics(dict):
    """Metrics over the columns at hand; those not computed yet are built on demand."""

    def __init__(self, ready: Mapping[str, Column], text: Column, words: Column):
        super().__init__(ready)
        self._text, self._words = text, words

    def __missing__(self, name: str) -> Column:
        self[name] = METRICS[name](self._text, self._words)
        return self[name]


def measured_order(docs: DataFrame, rules=RULES, text: str = "text", sample_rows: int = 256, fraction: float = 0.2, ready: tuple[str, ...] = ()) -> list[tuple[str, float, float]]:
    """(rule, seconds a document, share rejected) on a sample, best rejection per cost first.

    A rule whose metrics are all ``ready``, as they are asked for anyway, costs nothing more.
    The sample is at most ``sample_rows`` texts, taken from the first partitions that yield them.
    It sets the order of the rules and nothing else; costs are times, so two runs may order rules of
    like worth differently, and name different reasons for a document that several rules reject.
    """
    spark = docs.sparkSession
    rows = [(r[0],) for r in docs.select(named(text)).sample(fraction=fraction, seed=11).take(sample_rows)]
    if not rows:
        return [(r.name, 0.0, 0.0) for r in rules]
    sample = spark.createDataFrame(rows, "text string").coalesce(1).withColumn("words", words_of(F.col("text"))).persist()
    total, found = sample.count(), []
    for rule in rules:
        probe = sample.agg(F.count_if(rule.rejects(_Metrics({}, F.col("text"), F.col("words")))).alias("n"))
        spent, hit = [], 0
        for _ in range(2):  # the first run pays for compilation
            began = time.perf_counter()
            hit = probe.collect()[0][0]
            spent.append(time.perf_counter() - began)
        free = bool(rule.metrics) and set(rule.metrics) <= set(ready)
        found.append((rule.name, 0.0 if free else min(spent) / total, hit / total))
    sample.unpersist()
    return sorted(found, key=lambda x: (-x[2] / max(x[1], 1e-9), x[0]))


def cascade(ready: Mapping[str, Column], rules, order: list[str], text: Column, words: Column) -> Column:
    """Name of the first rule, in ``order``, that rejects the document; null if none does."""
    by_name, metrics = {r.name: r for r in rules}, _Metrics(ready, text, words)
    out = None
    for name in order:
        test = by_name[name].rejects(metrics)
        out = F.when(test, F.lit(name)) if out is None else out.when(test, F.lit(name))
    return out if out is not None else F.lit(None).cast("string")


def quality_rules(docs: DataFrame, rules=RULES, text: str = "text", order: list[str] | None = None, metrics: tuple[str, ...] = ()) -> DataFrame:
    """``docs`` with ``rejected_by`` (null: kept), ``kept`` and the asked ``metrics`` as columns.

    ``order`` skips the measuring.  Metrics that are not asked for are computed only where the
    cascade comes to a rule that needs them.
    """
    order = order or [x[0] for x in measured_order(docs, rules, text, ready=metrics)]
    (words,), content = fresh(docs, "words"), named(text)
    kept = [named(c) for c in docs.columns if c.lower() not in ("rejected_by", "kept", *metrics)]
    # the text keeps a name of its own too, as a result may take that of the text
    source, = fresh(docs, "source")
    staged = docs.select(*kept, content.alias(source), words_of(content).alias(words))
    staged = staged.select(*kept, source, words, *[METRICS[m](F.col(source), F.col(words)).alias(m) for m in metrics])
    # the words stand in the verdict once, so a filter on it that moves below this step makes them once
    verdict = let(F.col(words), lambda ws: cascade({m: F.col(m) for m in metrics}, rules, order, F.col(source), ws))
    judged = staged.select(*kept, *metrics, verdict.alias("rejected_by"))
    return judged.withColumn("kept", F.col("rejected_by").isNull())


def good_documents(docs: DataFrame, rules=RULES, text: str = "text", order: list[str] | None = None) -> DataFrame:
    """The documents that no rule rejects, columns as they were."""
    order = order or [x[0] for x in measured_order(docs, rules, text)]
    return docs.where(let(words_of(named(text)), lambda words: cascade({}, rules, order, named(text), words)).isNull())


def op1_quality(spark, sf_dir: str) -> DataFrame:
    from seedrank.llm.common import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = quality_rules(docs, metrics=BASE)
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return out.select("doc_id", *BASE, failed.alias("base_failed"), "kept")


OP1_SQL = r"""
WITH w AS (
  SELECT doc_id, coalesce(text, '') AS t,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws
  FROM documents),
g AS (
  SELECT doc_id, unnest(range(1, len(ws) - 3)) AS p, ws FROM w WHERE len(ws) >= 5),
h AS (SELECT doc_id, p, array_to_string(ws[p:p+4], chr(1)) AS gram FROM g),
f AS (SELECT doc_id, p, count(*) OVER (PARTITION BY doc_id, gram) AS c FROM h),
r AS (
  SELECT doc_id, count(DISTINCT p + i) AS n_repeat_words
  FROM f, (SELECT unnest(range(0, 5)) AS i) WHERE c >= 2 GROUP BY doc_id),
m AS (
  SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words,
         CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
         CAST(len(regexp_extract_all(t, '[#*$%&|<>]')) AS BIGINT) AS n_symbols,
         CAST(len(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))
              - len(list_distinct(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))) AS BIGINT) AS n_dup_lines,
         CAST(coalesce(n_repeat_words, 0) AS BIGINT) AS n_repeat_words,
         len(regexp_extract_all(t, '!!')) AS n_exclaims
  FROM w LEFT JOIN r USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed,
       NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words
            OR 10 * n_symbols > 2 * n_words OR 10 * n_exclaims > 2 * n_words
            OR word_chars < 2 * n_words OR word_chars > 20 * n_words
            OR 10 * n_dup_lines > 3 * n_words) AS kept
FROM m
"""
