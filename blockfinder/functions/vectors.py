"""Vectors as array columns, and the SQL functions that a session can register."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def scaled(a: Column, factor: Column) -> Column:
    return F.transform(a, lambda x: x.cast("double") * factor)


def normalised(a: Column) -> Column:
    """Length 1; a zero vector stays."""
    return scaled(a, F.when(norm(a) > 0, 1 / norm(a)).otherwise(F.lit(0.0)))


#: Column forms are in ``rng`` and here; these are the same for SQL text.
SQL_FUNCTIONS = {
    "bf_hash01": "(seed BIGINT, node BIGINT, stream BIGINT) RETURNS DOUBLE RETURN CAST(conv(substring(md5(concat_ws('|', CAST(seed AS STRING), CAST(node AS STRING), CAST(stream AS STRING))), 1, 13), 16, 10) AS BIGINT) / 4503599627370496.0D",
    "bf_pairs": "(n BIGINT) RETURNS BIGINT RETURN n * (n - 1) DIV 2",
    "bf_split_gain": "(vol_a BIGINT, vol_b BIGINT, cut BIGINT, total BIGINT) RETURNS DOUBLE RETURN CASE WHEN total = 0 THEN 0D ELSE 2D / total * (CAST(vol_a AS DOUBLE) * vol_b / total - cut) END",
    "bf_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
}


def register(spark: SparkSession) -> None:
    """Make the SQL functions known to the session, as temporary ones."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
