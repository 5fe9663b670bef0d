"""Source mixing: nearness to targets, clashing names, odd inputs."""

import numpy as np
from pyspark.sql import functions as F

from tabseek.llm import mixing


def by_source(docs):
    rows = mixing.mix(docs).groupBy("source").agg(F.sum(F.col("size") * F.col("copies")).alias("taken"), F.first("target").alias("target"), F.first("source_size").alias("own"), F.max("size").alias("largest"))
    return {r.source: r for r in rows.collect()}


def test_every_source_comes_near_its_target(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    for r in by_source(docs).values():
        # as near as the documents' sizes allow
        assert abs(r.taken - r.target) <= max(0.02 * r.target, 0.5 * r.largest), r
    r = np.random.default_rng(0)
    many = spark.createDataFrame([(i, "w " * int(n), f"s{i % 5}") for i, n in enumerate(r.integers(1, 200, 4000))], "doc_id long, text string, source string")
    assert all(abs(r.taken - r.target) <= 0.01 * r.target for r in by_source(many).values())


def test_a_document_keeps_its_chance(spark):
    """Over seeds, a document's copies average its source's rate."""
    docs = spark.createDataFrame([(i, "w " * (1 + i % 7), "ab"[i % 2]) for i in range(60)], "doc_id long, text string, source string").cache()
    taken = [mixing.mix(docs, seed=s).select("doc_id", "copies", (F.col("target") / F.col("source_size")).alias("rate")).toPandas().sort_values("doc_id") for s in range(5)]
    mean = sum(t["copies"].to_numpy() for t in taken) / len(taken)
    assert abs(mean - taken[0]["rate"].to_numpy()).mean() < 0.25


def test_clashing_names_hot_source_and_repeated_rows(spark):
    schema = "doc_id long, text string, source string, size string, target int, rate double, copies int, _source string, _copy int, _own_size int, source_size int"
    rows = [(i, "a b c", "hot" if i % 3 else f"s{i}", "x", 1, 2.0, 3, "y", 4, 5, 6) for i in range(40)] + [(1, "a b c", "hot", "x", 1, 2.0, 3, "y", 4, 5, 6)] * 2
    docs = spark.createDataFrame(rows + [(None, None, None, None, None, None, None, None, None, None, None)], schema)
    out = mixing.emit(docs)
    assert out.columns == docs.columns and {r.size for r in out.collect()} == {"x", None}
    assert {"size", "source_size", "target", "copies", "_own_size"} <= set(mixing.mix(docs).columns)
    copies = {(r.doc_id, r.copies) for r in mixing.mix(docs).where("doc_id = 1").collect()}
    assert len(copies) == 1  # repeated rows share a draw
    assert mixing.emit(docs.limit(0)).count() == 0
