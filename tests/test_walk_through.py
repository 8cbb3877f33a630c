"""The walk-through reads its points from a table."""

from blockfinder import queries

queries.load_all()


def test_nations_are_divided_by_balance(spark, tmp_path):
    balance = {3: 0.0, 4: 10.0, 5: 1000.0, 6: 1010.0, 7: 1500.0, 8: 5.0}
    rows = [(nation, x + d) for nation, x in balance.items() for d in (-1.0, 1.0)] + [(None, 9e9), (3, None)]
    spark.createDataFrame(rows, "c_nationkey long, c_acctbal double").write.parquet(f"{tmp_path}/customer.parquet")
    found = sorted(map(tuple, queries.QUERIES["walk_through"](spark, str(tmp_path)).collect()))
    assert found[0] == ("", 6, 3, 3) and found[2] == ("1", 3, 2, 1) and found[1][:2] == ("0", 3)
