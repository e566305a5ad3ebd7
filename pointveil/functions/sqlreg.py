"""The SQL surface: temporary functions and table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="a int, b int, kind string")
class WindowSpans:
    """spans(length, n): all windows of a trajectory, 1-based."""

    def eval(self, length: int, n: int):
        m = min(n, length)
        for a in range(1, length - m + 2):
            yield a, a + m - 1, "main"
        for k in range(1, m):
            yield 1, k, "prefix"
            yield length - k + 1, length, "suffix"


def register(spark: SparkSession) -> None:
    """haversine_km, time_h, stc_cell, is_open_at as SQL expressions, and spans() as a table function."""
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION haversine_km(a DOUBLE, b DOUBLE, c DOUBLE, d DOUBLE) RETURNS DOUBLE
        RETURN 2 * 6371.0 * asin(sqrt(least(1.0D, pow(sin(radians(c - a) / 2), 2) + cos(radians(a)) * cos(radians(c)) * pow(sin(radians(d - b) / 2), 2))))""")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION time_h(a DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN least(abs(a - b), 12.0D)")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION stc_cell(v DOUBLE, low DOUBLE, width DOUBLE, gs INT) RETURNS INT
        RETURN CAST(greatest(0, least(gs - 1, floor((v - low) / width * gs))) AS INT)""")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION is_open_at(h INT, o INT, c INT) RETURNS BOOLEAN
        RETURN coalesce((h >= o AND h < IF(c < o, c + 24, c)) OR (h + 24 >= o AND h + 24 < IF(c < o, c + 24, c)), true)""")
    spark.udtf.register("spans", WindowSpans)
