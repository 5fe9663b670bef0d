"""Experiments that compare two systems do so on all six datasets, with the systems named."""

from pyspark.sql import functions as F

from tabseek import experiments
from tabseek.operators import benchmark, train
from tabseek.plans import datasets

SF = "/root/testdata/sf0.001"


def test_bootstrap_covers_every_dataset_and_document(spark):
    rows = {r.dataset: r for r in experiments.exp_bootstrap(spark, SF).collect()}
    assert set(rows) == set(datasets.SIX)
    assert all(r.low <= r.high for r in rows.values())
    for name, table in (("web_a", "documents"), ("web_b", "pages")):
        assert experiments.load(spark, SF, name).tables.count() == datasets.read(spark, SF, table).count()


def test_a_system_without_hits_counts_with_0(spark):
    hits = spark.createDataFrame([("d", "a", 1, 7, 1)], "dataset string, config string, query_id long, table_id long, rank int")
    qrels = spark.createDataFrame([("d", 1, 7, 1), ("e", 1, 7, 1)], "dataset string, query_id long, table_id long, grade int")
    values = benchmark.by_query(hits, qrels, configs=("a", "b"))
    assert {(r.dataset, r.config): r.value for r in values.collect()} == {("d", "a"): 1.0, ("d", "b"): 0.0, ("e", "a"): 0.0, ("e", "b"): 0.0}
    assert {(r.dataset, r.low, r.high) for r in benchmark.bootstrap(values, "a", "b", 50).collect()} == {("d", 1.0, 1.0), ("e", 0.0, 0.0)}


def test_lengths_are_those_of_trained_descriptions(spark):
    got = {r.dataset: r.avg_chars for r in experiments.exp_lengths(spark, SF).where("system = 'FULL'").collect()}
    names, cfg = list(datasets.SIX), experiments.FULL.cfg
    tuned = experiments.adapters(spark, SF, names, (experiments.FULL,), names)["FULL"]
    assert set(tuned) == set(names)
    mean = lambda name, weights: train.generate(experiments.shown(experiments.load(spark, SF, name), True), weights, cfg).agg(F.round(F.avg(F.length("body")), 4)).first()[0]
    assert got == {name: mean(name, train.trained_weights(*tuned[name], cfg)) for name in names}
    assert got != {name: mean(name, train.base_weights(cfg)) for name in names}


def test_an_empty_description_has_no_words(spark):
    said = spark.createDataFrame([("d", 1, "FULL", ""), ("d", 2, "FULL", "a bc")], "dataset string, table_id long, field string, text string")
    assert [tuple(r) for r in experiments.lengths(said).collect()] == [("d", "FULL", 1.0, 2.0)]
