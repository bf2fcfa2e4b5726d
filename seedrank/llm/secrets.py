"""Secret scan with linking of credentials that come in several parts.

A scan of every whole text gives *parts*: strong ones, which are secrets by their own form, and weak
ones: identifiers such as a login, long mixed strings, endpoints.  A weak part alone is noise.  It is
reported only when complementary parts stand within one scope of it: a weak secret beside an
identifier, a weak identifier beside a secret, an endpoint beside both.  Parts are matched by an
interval join: scopes are cut into cells, parts meet on (text, cell), then their distance decides;
a cell holds few parts, as each has a least length.

Defined results: null and empty texts have no spans; positions are code points, ends exclusive;
repeated rows give a row each; a text of any length is scanned whole, and its parts, however many, meet in
cells; an empty table gives no rows; other columns, whatever their names, are ignored by the scan and kept by
``redact``.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, LongType, StructField, StructType

from seedrank.llm.common import fresh, map_batches, named, sha256_text, ship, table, text_key, written

#: Two parts are in one scope if at most so many code points lie between them.
SCOPE = 256
#: Links up to which the table of linked spans is broadcast to the documents (some 100 bytes each).
BROADCAST_ROWS = 200_000
MASK = "[secret]"

# The patterns of the three base kinds.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")

# Weak parts.
LOGIN = re.compile(r"""(?:user(?:name|_?id)?|login|client_?id|account_?id|access_?key_?id)["']?\x20*[:=]\x20*["']?([A-Za-z0-9._@-]{4,})""", re.IGNORECASE | re.ASCII)
OPAQUE = re.compile(r"(?<![A-Za-z0-9+/_=-])(?=[a-z0-9+/_=-]*[A-Z])(?=[A-Z0-9+/_=-]*[a-z])(?=[A-Za-z+/_=-]*[0-9])[A-Za-z0-9+/_=-]{24,}")
ENDPOINT = re.compile(r"""(?:https?|jdbc:[a-z]+|postgres(?:ql)?|mysql|mongodb|redis|amqp|ftp|ssh)://[^\x00-\x20"'<>]+""")

#: Kinds in the order in which equal starts are listed.
KINDS = ("assign", "access", "hex", "login", "opaque", "endpoint")
#: What a part of each kind is to the others.
ROLES = {"assign": "secret", "access": "identifier", "hex": "secret", "login": "identifier", "opaque": "secret", "endpoint": "endpoint"}
#: Roles of which every one must be in scope before a weak part of the role is reported.
NEEDS = {"secret": ("identifier",), "identifier": ("secret",), "endpoint": ("identifier", "secret")}
BASE = KINDS[:3]

_PART = "struct<kind:int,start:long,stop:long>"
_PARTS = ArrayType(StructType([StructField("kind", IntegerType()), StructField("start", LongType()), StructField("stop", LongType())]))


def find_parts(text: str | None) -> list[tuple[int, int, int]]:
    """(index of the kind, start, end) of every part; weak ones that touch a strong one are left out."""
    if not text:
        return []
    out = []
    if ":" in text or "=" in text:
        out += [(0, *m.span()) for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    if "AKIA" in text:
        out += [(1, *m.span()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 16]
    out += [(2, *m.span()) for m in HEX.finditer(text)]
    weak = [(4, *m.span()) for m in OPAQUE.finditer(text)]
    if ":" in text or "=" in text:
        weak += [(3, *m.span()) for m in LOGIN.finditer(text)]
    if "://" in text:
        weak += [(5, *m.span()) for m in ENDPOINT.finditer(text)]
    if weak and out:
        weak = _apart(weak, out)
    return sorted(out + weak, key=lambda p: (p[1], p[0]))


def _apart(weak: list, strong: list) -> list:
    """The weak parts that overlap no strong one."""
    from bisect import bisect_left

    merged: list[list[int]] = []
    for _, a, b in sorted(strong, key=lambda p: p[1]):
        if merged and a <= merged[-1][1]:
            merged[-1][1] = max(merged[-1][1], b)
        else:
            merged.append([a, b])
    ends = [b for _, b in merged]

    def free(a: int, b: int) -> bool:
        i = bisect_left(ends, a + 1)
        return i == len(merged) or merged[i][0] >= b

    return [p for p in weak if free(p[1], p[2])]


def scan(docs: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """``keep`` columns of ``docs`` and ``parts`` of each text."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("kind", pa.int32()), ("start", pa.int64()), ("stop", pa.int64())]))
        for batch in batches:
            found = [[{"kind": k, "start": a, "stop": b} for k, a, b in find_parts(t.as_py())] for t in batch.column(len(keep))]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(found, kind)], [*keep, "parts"])

    kept = docs.select(*[named(c) for c in keep], named(text).alias("_scanned"))
    schema = StructType(list(kept.schema)[:-1]).add("parts", _PARTS)
    return map_batches(kept, run, schema)


def _role(kind: Column) -> Column:
    return F.element_at(F.array(*[F.lit(ROLES[k]) for k in KINDS]), kind + 1)


def linked(found: DataFrame, key: list[str], scope: int = SCOPE) -> DataFrame:
    """``key`` and ``links``: the weak parts that complementary parts vouch for.

    ``found``: one row for each key, with its ``parts``.
    """
    weak = F.exists("parts", lambda p: p["kind"] >= len(BASE))
    parts = found.where((F.size("parts") > 1) & weak).select(*key, F.explode("parts").alias("p"))
    parts = parts.select(*key, "p.kind", "p.start", "p.stop", _role(F.col("p.kind")).alias("role"))
    cell = lambda c: F.floor(c / scope)
    sought = parts.where(F.col("kind") >= len(BASE)).withColumn("cell", F.explode(F.sequence(cell(F.greatest(F.col("start") - scope, F.lit(0))), cell(F.col("stop") + scope))))
    around = parts.select(*key, F.col("start").alias("a"), F.col("stop").alias("b"), F.col("role").alias("other"))
    around = around.withColumn("cell", F.explode(F.sequence(cell(F.col("a")), cell(F.col("b") - 1))))
    near = (F.col("a") <= F.col("stop") + scope) & (F.col("b") >= F.col("start") - scope) & (F.col("other") != F.col("role"))
    met = sought.join(around, [*key, "cell"]).where(near)
    met = met.groupBy(*key, "kind", "start", "stop", "role").agg(F.collect_set("other").alias("others"))
    enough = F.lit(False)
    for role, needs in NEEDS.items():
        all_ = F.lit(True)
        for n in needs:
            all_ = all_ & F.array_contains("others", n)
        enough = enough | ((F.col("role") == role) & all_)
    return met.where(enough).groupBy(*key).agg(F.collect_list(F.struct("kind", "start", "stop")).alias("links"))


def _listed(parts: Column) -> Column:
    """kind:start:end of each part, by start and then kind, comma-joined."""
    ordered = F.array_sort(F.transform(parts, lambda p: F.struct(p["start"].alias("start"), p["kind"].alias("kind"), p["stop"].alias("stop"))))
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(ordered, lambda p: F.concat_ws(":", F.element_at(names, p["kind"] + 1), p["start"], p["stop"])), ",")


def find_secrets(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each document: doc_id, ``base`` (strong parts) and ``links`` (weak parts vouched for)."""
    rows = docs.select(named(doc_id).alias("doc_id"), F.monotonically_increasing_id().alias("uid"), named(text).alias("text"))
    found = written(scan(rows, ["doc_id", "uid"]))
    base = F.filter("parts", lambda p: p["kind"] < len(BASE))
    out = found.select("doc_id", "uid", base.alias("base")).join(linked(found, ["uid"]), "uid", "left")
    return out.select("doc_id", "base", F.coalesce("links", F.array().cast(f"array<{_PART}>")).alias("links"))


def redact(docs: DataFrame, text: str = "text", length: str = "n_chars", mask: str = MASK) -> DataFrame:
    """``docs`` with every found span of ``text`` replaced by ``mask``; ``length`` follows the text."""
    spark, keys = docs.sparkSession, ["k1", "k2"]
    k1, k2 = text_key(named(text))
    found = scan(docs.select(k1.alias("k1"), k2.alias("k2"), named(text).alias("text")), keys)
    some = written(found.where(F.exists("parts", lambda p: p["kind"] >= len(BASE)) & (F.size("parts") > 1)).dropDuplicates(keys))
    own = fresh(docs, *keys, "links")
    links = written(linked(some, keys).toDF(*own))
    if links.count() <= BROADCAST_ROWS:
        links = F.broadcast(links)
    joined = docs.join(links, [k1 == F.col(own[0]), k2 == F.col(own[1])], "left").select(*[named(c) for c in docs.columns], own[2])
    at = docs.columns.index(text)
    sized = docs.columns.index(length) if length in docs.columns else None
    ship(spark)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for t, more in zip(batch.column(at), batch.column(len(batch.columns) - 1), strict=True):
                t = t.as_py()
                spans = [(a, b) for k, a, b in find_parts(t) if k < len(BASE)] + [(p["start"], p["stop"]) for p in more.as_py() or ()]
                texts.append(_masked(t, spans, mask) if spans else t)
            columns = list(batch.columns[:-1])
            columns[at] = pa.array(texts, columns[at].type)
            if sized is not None:
                columns[sized] = pa.array([n if t is None else len(t) for t, n in zip(texts, columns[sized].to_pylist(), strict=True)], columns[sized].type)
            yield pa.RecordBatch.from_arrays(columns, batch.schema.names[:-1])

    return map_batches(joined, run, docs.schema)


def _masked(text: str, spans: list[tuple[int, int]], mask: str) -> str:
    out, upto = [], 0
    for a, b in sorted(spans):
        if a >= upto:
            out += [text[upto:a], mask]
        upto = max(upto, b)
    return "".join([*out, text[upto:]])


def op9_secrets(spark, sf_dir: str) -> DataFrame:
    found = find_secrets(table(spark, sf_dir, "documents"))
    of = lambda k: F.size(F.filter("base", lambda p: p["kind"] == k)).cast("long")
    return found.select(
        "doc_id",
        of(0).alias("n_assign"), of(1).alias("n_access"), of(2).alias("n_hex"),
        sha256_text(_listed(F.col("base"))).alias("base_sha256"),
        _listed(F.concat("base", "links")).alias("spans"),
    )
