"""The catalogue scans its tables: columns and how many values each has."""

from tabseek.sources import catalogue


def test_columns_and_values_are_read(spark, tmp_path):
    spark.createDataFrame([(1, "a"), (2, None)], "n_nationkey long, n_name string").write.parquet(f"{tmp_path}/nation.parquet")
    spark.createDataFrame([], "r_regionkey long").write.parquet(f"{tmp_path}/region.parquet")
    got = {r.table_name: r for r in catalogue.tables(spark, str(tmp_path)).collect()}
    assert set(got) == {"nation", "region"}
    assert (got["nation"].n_columns, got["nation"].columns, got["nation"].n_rows, got["nation"].n_values) == (2, ["n_nationkey", "n_name"], 2, [2, 1])
    assert (got["region"].columns, got["region"].types, got["region"].n_values) == (["r_regionkey"], ["bigint"], [0])
    assert catalogue.tables(spark, f"{tmp_path}/none").count() == 0
