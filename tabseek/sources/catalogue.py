"""The catalogue: one row a table of a folder, its columns as a scan finds them."""

from __future__ import annotations

from functools import reduce

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..plans.datasets import CATALOGUE


def tables(spark: SparkSession, sf_dir: str, names=tuple(CATALOGUE)) -> DataFrame:
    """(table_name, n_columns, columns, types, n_rows, n_values) of the ``names`` that stand in ``sf_dir``.

    Every table is scanned: a column stands in the catalogue once its values were
    read to the end, and ``n_values`` tells how many are not null.
    """
    parts = []
    for name in names:
        try:
            rows = spark.read.parquet(f"{sf_dir}/{name}.parquet")
        except AnalysisException as error:
            if error.getCondition() != "PATH_NOT_FOUND":
                raise
            continue
        read = [F.struct(F.lit(f.name).alias("name"), F.lit(f.dataType.simpleString()).alias("type"), F.count(f"`{f.name}`").alias("n")) for f in rows.schema.fields]
        parts.append(rows.agg(F.lit(name).alias("table_name"), F.count("*").alias("n_rows"), F.array(*read).alias("c")))
    if not parts:
        return spark.createDataFrame([], "table_name string, n_columns long, columns array<string>, types array<string>, n_rows long, n_values array<long>")
    found = reduce(DataFrame.unionByName, parts).withColumn("c", F.filter("c", lambda c: c["n"] <= F.col("n_rows")))
    part = lambda key: F.transform("c", lambda c: c[key])
    return found.select("table_name", F.size("c").cast("long").alias("n_columns"), part("name").alias("columns"), part("type").alias("types"), "n_rows", part("n").alias("n_values"))
