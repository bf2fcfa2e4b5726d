"""The experiment workloads on the given tables: weights by name, as plans and as SQL.

Each entry states long weights (assignment, key, weight); colocated ones are made wide from them.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seedrank.sources import weights as W
from seedrank.sources.tables import cents, scan


@dataclass(frozen=True)
class Workload:
    """``plan(spark, sf_dir)`` gives (assignment, key, weight); ``sql`` the same for DuckDB; ``names`` its assignments."""

    plan: object
    sql: str
    names: tuple[str, ...]


def _months(spark: SparkSession, sf: str) -> DataFrame:
    rows = scan(spark, sf, "lineitem")
    return W.aggregate(rows, F.concat(F.lit("m"), F.lpad(F.month("l_shipdate").cast("string"), 2, "0")), F.col("l_partkey"), F.count(F.lit(1)))


def _years(spark, sf):
    rows = scan(spark, sf, "lineitem")
    return W.aggregate(rows, F.concat(F.lit("y"), F.year("l_shipdate").cast("string")), F.col("l_partkey"), F.sum(cents(F.col("l_extendedprice"))))


def _day(ts):
    return F.concat(F.lit("d"), F.lpad(F.dayofmonth(ts).cast("string"), 2, "0"))


def _event_days(key, weight):
    def plan(spark, sf):
        rows = scan(spark, sf, "events").where((F.col("ts") >= "2024-01-01") & (F.col("ts") < "2024-01-24"))
        return W.aggregate(rows, _day(F.col("ts")), key(), weight())

    return plan


def _event_hours(spark, sf):
    """The first four hours of one day: few keys, and hardly any that two hours share."""
    rows = scan(spark, sf, "events").where((F.col("ts") >= "2024-01-03") & (F.col("ts") < "2024-01-03 04:00:00"))
    return W.aggregate(rows, F.concat(F.lit("h"), F.lpad(F.hour("ts").cast("string"), 2, "0")), F.col("user_id"), F.sum(cents(F.col("value"))))


def _halves(key, weight):
    """Rows in the order of shipping, cut into two halves of equal number.

    The cut falls into one day: days before it are the first half, days after it the second, and only the
    rows of that day are sorted.
    """

    def plan(spark, sf):
        rows = scan(spark, sf, "lineitem").withColumn("day", F.to_date("l_shipdate"))
        days = rows.groupBy("day").agg(F.count(F.lit(1)).alias("n"))
        upto = days.withColumn("upto", F.sum("n").over(Window.orderBy("day"))).withColumn("all", F.sum("n").over(Window.partitionBy()))
        # of an odd number the first half has one more
        cut = upto.withColumn("half", F.ceil(F.col("all") / 2)).where((F.col("upto") >= F.col("half")) & (F.col("upto") - F.col("n") < F.col("half")))
        cut = cut.select(F.col("day").alias("cut"), (F.col("half") - (F.col("upto") - F.col("n"))).alias("room"))
        marked = rows.crossJoin(F.broadcast(cut))
        order = Window.partitionBy("day").orderBy("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
        inside = marked.where(F.col("day") == F.col("cut")).withColumn("half", F.when(F.row_number().over(order) <= F.col("room"), "h1").otherwise("h2"))
        outside = marked.where(F.col("day") != F.col("cut")).withColumn("half", F.when(F.col("day") < F.col("cut"), "h1").otherwise("h2"))
        both = outside.unionByName(inside)
        # parts grow with the data: whether they are broadcast is left to their size
        both = both.join(scan(spark, sf, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey") if "brand" in key.__name__ else both
        return W.aggregate(both, F.col("half"), key(), weight())

    return plan


def _by_part():
    return F.col("l_partkey")


def _by_supplier_and_brand():
    return W.composite_key(F.col("l_suppkey"), F.col("p_brand"))


def _words(spark, sf):
    docs = scan(spark, sf, "documents").where((F.col("lang") == "en") & F.col("source").isin("src0", "src1", "src2", "src3"))
    tokens = docs.select("source", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("token")).where("token <> ''")
    return W.aggregate(tokens, F.col("source"), F.col("token"), F.count(F.lit(1)))


def _unpivot(wide: DataFrame, columns: list[str]) -> DataFrame:
    return wide.select("key", F.explode(F.array(*[F.struct(F.lit(c).alias("assignment"), F.col(c).cast("bigint").alias("weight")) for c in columns])).alias("x")).select("x.assignment", "key", "x.weight").where("weight > 0")


def _pairs(spark, sf):
    rows = scan(spark, sf, "lineitem").groupBy(W.composite_key(F.col("l_partkey"), F.col("l_suppkey")).alias("key"))
    return _unpivot(rows.agg(F.sum(cents(F.col("l_extendedprice"))).alias("gross"), F.count(F.lit(1)).alias("lines"), F.lit(1).alias("uniform")), ["gross", "lines", "uniform"])


def _parts(spark, sf):
    rows = scan(spark, sf, "lineitem").groupBy("l_partkey", "l_suppkey").agg(F.sum(cents(F.col("l_extendedprice"))).alias("g"), F.count(F.lit(1)).alias("n"))
    wide = rows.groupBy(F.col("l_partkey").cast("string").alias("key")).agg(F.sum("g").alias("gross"), F.sum("n").alias("lines"), F.count(F.lit(1)).alias("suppliers"), F.lit(1).alias("uniform"))
    return _unpivot(wide, ["gross", "lines", "suppliers", "uniform"])


def _event_day3(spark, sf):
    rows = scan(spark, sf, "events").where((F.col("ts") >= "2024-01-03") & (F.col("ts") < "2024-01-04"))
    wide = rows.groupBy(F.col("user_id").cast("string").alias("key")).agg(F.sum(cents(F.col("value"))).alias("value"), F.count(F.lit(1)).alias("events"), F.count_distinct("event_type").alias("types"), F.lit(1).alias("uniform"))
    return _unpivot(wide, ["value", "events", "types", "uniform"])


def _event_pair_day3(spark, sf):
    rows = scan(spark, sf, "events").where((F.col("ts") >= "2024-01-03") & (F.col("ts") < "2024-01-04"))
    wide = rows.groupBy(W.composite_key(F.col("user_id"), F.col("event_type")).alias("key")).agg(
        F.sum(cents(F.col("value"))).alias("value"), F.count(F.lit(1)).alias("events"), F.count_distinct(F.get_json_object("props", "$.k")).alias("kinds"), F.lit(1).alias("uniform")
    )
    return _unpivot(wide, ["value", "events", "kinds", "uniform"])


def _supplier_parts(spark, sf):
    """Suppliers as assignments of parts, for similarity of pairs."""
    return W.aggregate(scan(spark, sf, "lineitem"), F.col("l_suppkey"), F.col("l_partkey"), F.sum(F.col("l_quantity").cast("bigint")))


def _ohlc(spark, sf):
    rows = scan(spark, sf, "events").where((F.col("ts") >= "2024-01-01") & (F.col("ts") < "2024-01-02")).withColumn("c", cents(F.col("value")))
    at = F.struct("ts", "event_id")
    wide = rows.groupBy(F.col("user_id").cast("string").alias("key")).agg(
        F.min_by("c", at).alias("open"), F.max("c").alias("high"), F.min("c").alias("low"), F.max_by("c", at).alias("close"), F.max_by("event_type", at).alias("last"), F.sum("c").alias("volume")
    )
    wide = wide.withColumn("adj_close", F.when(F.col("last") == "error", F.floor(F.col("close") * 9 / 10)).otherwise(F.col("close")))
    return _unpivot(wide, ["open", "high", "low", "close", "adj_close", "volume"])


def _money(spark, sf):
    net = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    wide = scan(spark, sf, "lineitem").groupBy(F.col("l_partkey").cast("string").alias("key")).agg(
        F.sum(cents(F.col("l_extendedprice"))).alias("gross"), F.sum(cents(net)).alias("net"), F.sum(cents(net * (1 + F.col("l_tax")))).alias("net_tax"),
        F.sum(F.col("l_quantity").cast("bigint")).alias("quantity"), F.count(F.lit(1)).alias("lines"), F.max(cents(F.col("l_extendedprice"))).alias("top"),
    )
    return _unpivot(wide, ["gross", "net", "net_tax", "quantity", "lines", "top"])


def _moments(spark, sf):
    rows = scan(spark, sf, "events").withColumn("c", cents(F.col("value")))
    wide = rows.groupBy(F.col("user_id").cast("string").alias("key")).agg(F.sum("c").alias("x"), F.sum(F.col("c") * F.col("c")).alias("xx"))
    return _unpivot(wide, ["x", "xx"])


def _baskets(spark, sf):
    brand = scan(spark, sf, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand")
    rows = scan(spark, sf, "lineitem").join(brand, "l_partkey")
    return W.aggregate(rows, F.col("p_brand"), F.col("l_orderkey"), F.count(F.lit(1)))


def _document_words(spark, sf):
    """English documents as assignments of words, for similarity of pairs."""
    docs = scan(spark, sf, "documents").where(F.col("lang") == "en")
    tokens = docs.select("doc_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("token")).where("token <> ''")
    return W.aggregate(tokens, F.col("doc_id"), F.col("token"), F.count(F.lit(1)))


def _doc_words(spark, sf):
    """The part of them that the SQL of ``doc_words`` states; no other query reads it."""
    return _document_words(spark, sf).where(F.col("assignment").cast("bigint") < 60)


_C = "CAST(round({} * 100) AS BIGINT)"
_PRICE, _VALUE = _C.format("l_extendedprice"), _C.format("value")
_ORDER = "l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice"
_HALVED = f"(SELECT *, 'h' || ntile(2) OVER (ORDER BY {_ORDER}) AS half FROM lineitem)"
_TOKENS = "(SELECT {} AS a, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS token FROM documents WHERE {})"
_DAYS = "(SELECT *, 'd' || lpad(CAST(day(ts) AS VARCHAR), 2, '0') AS d FROM events WHERE ts >= '2024-01-01' AND ts < '2024-01-24')"
_NET = "l_extendedprice * (1 - l_discount)"


def _wide_sql(columns: list[str], body: str) -> str:
    parts = " UNION ALL ".join(f"SELECT '{c}' AS assignment, key, CAST({c} AS BIGINT) AS weight FROM x" for c in columns)
    return f"SELECT * FROM (WITH x AS ({body}) {parts}) WHERE weight > 0"


_MONTHS = tuple(f"m{i:02d}" for i in range(1, 13))
_DAY_NAMES = tuple(f"d{i:02d}" for i in range(1, 24))

WORKLOADS: dict[str, Workload] = {
    "part_months": Workload(_months, "SELECT 'm' || lpad(CAST(month(l_shipdate) AS VARCHAR), 2, '0') AS assignment, CAST(l_partkey AS VARCHAR) AS key, count(*) AS weight FROM lineitem GROUP BY 1, 2", _MONTHS),
    "part_years": Workload(_years, f"SELECT 'y' || CAST(year(l_shipdate) AS VARCHAR) AS assignment, CAST(l_partkey AS VARCHAR) AS key, CAST(sum({_PRICE}) AS BIGINT) AS weight FROM lineitem GROUP BY 1, 2", tuple(f"y{y}" for y in range(1995, 2002))),
    "event_days": Workload(_event_days(lambda: F.col("user_id"), lambda: F.sum(cents(F.col("value")))), f"SELECT d AS assignment, CAST(user_id AS VARCHAR) AS key, CAST(sum({_VALUE}) AS BIGINT) AS weight FROM {_DAYS} GROUP BY 1, 2", _DAY_NAMES),
    "event_pair_days": Workload(_event_days(lambda: W.composite_key(F.col("user_id"), F.col("event_type")), lambda: F.sum(cents(F.col("value")))), f"SELECT d AS assignment, concat_ws('|', CAST(user_id AS VARCHAR), event_type) AS key, CAST(sum({_VALUE}) AS BIGINT) AS weight FROM {_DAYS} GROUP BY 1, 2", _DAY_NAMES),
    "event_hours": Workload(
        _event_hours,
        f"SELECT 'h' || lpad(CAST(hour(ts) AS VARCHAR), 2, '0') AS assignment, CAST(user_id AS VARCHAR) AS key, CAST(sum({_VALUE}) AS BIGINT) AS weight FROM events WHERE ts >= '2024-01-03' AND ts < '2024-01-03 04:00:00' GROUP BY 1, 2",
        ("h00", "h01", "h02", "h03"),
    ),
    "event_pair_day3": Workload(
        _event_pair_day3,
        _wide_sql(
            ["value", "events", "kinds", "uniform"],
            f"SELECT concat_ws('|', CAST(user_id AS VARCHAR), event_type) AS key, sum({_VALUE}) AS value, count(*) AS events, count(DISTINCT json_extract_string(props, '$.k')) AS kinds, 1 AS uniform FROM events WHERE ts >= '2024-01-03' AND ts < '2024-01-04' GROUP BY 1",
        ),
        ("value", "events", "kinds", "uniform"),
    ),
    "supplier_parts": Workload(_supplier_parts, "SELECT CAST(l_suppkey AS VARCHAR) AS assignment, CAST(l_partkey AS VARCHAR) AS key, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS weight FROM lineitem GROUP BY 1, 2", ()),
    "event_high": Workload(_event_days(lambda: F.col("user_id"), lambda: F.max(cents(F.col("value")))), f"SELECT d AS assignment, CAST(user_id AS VARCHAR) AS key, max({_VALUE}) AS weight FROM {_DAYS} GROUP BY 1, 2", _DAY_NAMES),
    "halves_part_gross": Workload(_halves(_by_part, lambda: F.sum(cents(F.col("l_extendedprice")))), f"SELECT half AS assignment, CAST(l_partkey AS VARCHAR) AS key, CAST(sum({_PRICE}) AS BIGINT) AS weight FROM {_HALVED} GROUP BY 1, 2", ("h1", "h2")),
    "halves_part_suppliers": Workload(_halves(_by_part, lambda: F.count_distinct("l_suppkey")), f"SELECT half AS assignment, CAST(l_partkey AS VARCHAR) AS key, count(DISTINCT l_suppkey) AS weight FROM {_HALVED} GROUP BY 1, 2", ("h1", "h2")),
    "halves_brand_gross": Workload(_halves(_by_supplier_and_brand, lambda: F.sum(cents(F.col("l_extendedprice")))), f"SELECT half AS assignment, concat_ws('|', CAST(l_suppkey AS VARCHAR), p_brand) AS key, CAST(sum({_PRICE}) AS BIGINT) AS weight FROM {_HALVED} JOIN part ON p_partkey = l_partkey GROUP BY 1, 2", ("h1", "h2")),
    "halves_brand_lines": Workload(_halves(_by_supplier_and_brand, lambda: F.count(F.lit(1))), f"SELECT half AS assignment, concat_ws('|', CAST(l_suppkey AS VARCHAR), p_brand) AS key, count(*) AS weight FROM {_HALVED} JOIN part ON p_partkey = l_partkey GROUP BY 1, 2", ("h1", "h2")),
    "words": Workload(_words, "SELECT a AS assignment, token AS key, count(*) AS weight FROM " + _TOKENS.format("source", "lang = 'en' AND source IN ('src0', 'src1', 'src2', 'src3')") + " GROUP BY 1, 2", ("src0", "src1", "src2", "src3")),
    "pairs": Workload(_pairs, _wide_sql(["gross", "lines", "uniform"], f"SELECT concat_ws('|', CAST(l_partkey AS VARCHAR), CAST(l_suppkey AS VARCHAR)) AS key, sum({_PRICE}) AS gross, count(*) AS lines, 1 AS uniform FROM lineitem GROUP BY 1"), ("gross", "lines", "uniform")),
    "parts": Workload(_parts, _wide_sql(["gross", "lines", "suppliers", "uniform"], f"SELECT CAST(l_partkey AS VARCHAR) AS key, sum({_PRICE}) AS gross, count(*) AS lines, count(DISTINCT l_suppkey) AS suppliers, 1 AS uniform FROM lineitem GROUP BY 1"), ("gross", "lines", "suppliers", "uniform")),
    "event_day3": Workload(_event_day3, _wide_sql(["value", "events", "types", "uniform"], f"SELECT CAST(user_id AS VARCHAR) AS key, sum({_VALUE}) AS value, count(*) AS events, count(DISTINCT event_type) AS types, 1 AS uniform FROM events WHERE ts >= '2024-01-03' AND ts < '2024-01-04' GROUP BY 1"), ("value", "events", "types", "uniform")),
    "ohlc": Workload(
        _ohlc,
        _wide_sql(
            ["open", "high", "low", "close", "adj_close", "volume"],
            "SELECT *, CASE WHEN last = 'error' THEN floor(close * 9 / 10) ELSE close END AS adj_close FROM (SELECT CAST(user_id AS VARCHAR) AS key, arg_min(c, (ts, event_id)) AS open, max(c) AS high, min(c) AS low, arg_max(c, (ts, event_id)) AS close, arg_max(event_type, (ts, event_id)) AS last, sum(c) AS volume "
            f"FROM (SELECT *, {_VALUE} AS c FROM events WHERE ts >= '2024-01-01' AND ts < '2024-01-02') GROUP BY 1)",
        ),
        ("open", "high", "low", "close", "adj_close", "volume"),
    ),
    "money": Workload(
        _money,
        _wide_sql(
            ["gross", "net", "net_tax", "quantity", "lines", "top"],
            f"SELECT CAST(l_partkey AS VARCHAR) AS key, sum({_PRICE}) AS gross, sum({_C.format(_NET)}) AS net, sum({_C.format(f'{_NET} * (1 + l_tax)')}) AS net_tax, sum(CAST(l_quantity AS BIGINT)) AS quantity, count(*) AS lines, max({_PRICE}) AS top FROM lineitem GROUP BY 1",
        ),
        ("gross", "net", "net_tax", "quantity", "lines", "top"),
    ),
    "moments": Workload(_moments, _wide_sql(["x", "xx"], "SELECT CAST(user_id AS VARCHAR) AS key, sum(c) AS x, sum(c * c) AS xx FROM (SELECT *, " + _VALUE + " AS c FROM events) GROUP BY 1"), ("x", "xx")),
    "baskets": Workload(_baskets, "SELECT p_brand AS assignment, CAST(l_orderkey AS VARCHAR) AS key, count(*) AS weight FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1, 2", ()),
    "doc_words": Workload(_doc_words, "SELECT CAST(a AS VARCHAR) AS assignment, token AS key, count(*) AS weight FROM " + _TOKENS.format("doc_id", "lang = 'en' AND doc_id < 60") + " GROUP BY 1, 2", ()),
    "document_words": Workload(_document_words, "SELECT CAST(a AS VARCHAR) AS assignment, token AS key, count(*) AS weight FROM " + _TOKENS.format("doc_id", "lang = 'en'") + " GROUP BY 1, 2", ()),
}


def long_weights(spark: SparkSession, sf_dir: str, name: str, assignments: list[str] | None = None) -> DataFrame:
    rows = WORKLOADS[name].plan(spark, sf_dir)
    return rows if assignments is None else rows.where(F.col("assignment").isin(assignments))


def wide_weights(spark: SparkSession, sf_dir: str, name: str, assignments: list[str] | None = None) -> DataFrame:
    return W.to_wide(long_weights(spark, sf_dir, name, assignments))
