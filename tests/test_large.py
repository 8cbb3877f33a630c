"""What is only seen on more rows."""

from pyspark.sql import functions as F

from blockfinder import queries

queries.load_all()


def test_recursion_over_more_rows_than_spark_allows_by_default(spark, tmp_path):
    spark.range(1, 100_001).select(F.col("id").alias("p_partkey")).write.parquet(f"{tmp_path}/part.parquet")
    found = queries.QUERIES["op_recursive"](spark, str(tmp_path)).agg(F.count(F.lit(1)).alias("n"), F.sum("steps").alias("steps"), F.max("top").alias("top")).first()
    assert tuple(found) == (100_000, sum(k.bit_length() for k in range(1, 100_001)), 1)
