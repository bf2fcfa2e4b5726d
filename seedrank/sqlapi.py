"""SQL functions, and a table function, over samples."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from seedrank.functions.seeds import BITS

_FUNCTIONS = (
    f"key_seed(k STRING, salt STRING) RETURNS DOUBLE RETURN (CAST(conv(substr(md5(CAST(concat_ws('|', salt, k) AS BINARY)), 1, {BITS // 4}), 16, 10) AS BIGINT) + 0.5D) / {float(2**BITS)!r}D",
    "ipps_rank(w DOUBLE, u DOUBLE) RETURNS DOUBLE RETURN CASE WHEN w > 0 THEN u / w ELSE double('Infinity') END",
    "exp_rank(w DOUBLE, u DOUBLE) RETURNS DOUBLE RETURN CASE WHEN w > 0 THEN -log1p(-u) / w ELSE double('Infinity') END",
    "ipps_cdf(w DOUBLE, x DOUBLE) RETURNS DOUBLE RETURN CASE WHEN w > 0 THEN least(1.0D, w * x) ELSE 0.0D END",
    "exp_cdf(w DOUBLE, x DOUBLE) RETURNS DOUBLE RETURN CASE WHEN w > 0 THEN -expm1(-(w * x)) ELSE 0.0D END",
)


@udtf(returnType="assignment string, key string, rank double, pos int")
class BottomKRows:
    """The first k rows of each partition of an ordered table (assignment, key, rank)."""

    def __init__(self):
        self.seen = 0

    def eval(self, row, k: int):
        self.seen += 1
        if self.seen <= k:
            yield row["assignment"], row["key"], row["rank"], self.seen


def register(spark: SparkSession) -> None:
    """Make the functions known to ``spark.sql``."""
    for text in _FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
    spark.udtf.register("bottom_k_rows", BottomKRows)
