"""Results of streams are tables: no rows come to the driver."""

from pyspark.sql import functions as F

from blockfinder.streaming import jobs


def test_streams_keep_their_rows_in_tables(spark, tmp_path):
    for k in range(3):
        spark.range(4).selectExpr("id AS a", "id + 10 AS b", f"timestamp_seconds(86400 * {k}) AS event_time").write.parquet(f"{tmp_path}/rows/{k}")
    rows = spark.readStream.schema("a long, b long, event_time timestamp").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/rows")
    counted = jobs.run(jobs.windowed(rows, "sliding"), "complete", spark)
    assert counted.inputFiles() and counted.count() == 4 * 3 * 2 and counted.agg(F.sum("n")).first()[0] == 4 * 3 * 2
    once = jobs.run(jobs.without_repeats(rows), "append", spark)
    assert once.inputFiles() and once.select("a", "b").distinct().count() == 4
    nothing = jobs.run(rows.where("a < 0"), "append", spark)
    assert nothing.columns == rows.columns and nothing.count() == 0
