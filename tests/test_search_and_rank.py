"""Worked values computed outside Spark, and properties of the methods."""

import math

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import Window, functions as F

from tabseek import workloads
from tabseek.functions import analysis
from tabseek.operators import evaluate, names, rank, search, train

C = ["employee phone list", "staff contact phone numbers and names", "employee employee phone phone records kept daily"]


@pytest.fixture(scope="module")
def tiny(spark):
    rows = [("t", 1, True, i, b) for i, b in enumerate(C)] + [("t", 2, False, 0, "phone price list"), ("t", 3, False, 0, "discounted product catalogue")]
    cands = spark.createDataFrame(rows, "dataset string, table_id long, is_gold boolean, cand_id int, body string")
    queries = spark.createDataFrame([("t", 1, "employee phone"), ("t", 2, "staff names")], "dataset string, query_id long, text string")
    qrels = spark.createDataFrame([("t", 1, 1, 1), ("t", 2, 1, 1)], "dataset string, query_id long, table_id long, grade int")
    return cands, queries, qrels


def scores(rows):
    return [r.score for r in rows.orderBy("cand_id").collect()]


def test_candidate_scores(tiny):
    cands, queries, qrels = tiny
    one = qrels.where("query_id = 1")
    assert scores(rank.score(cands, queries, one, "individual")) == pytest.approx([1.450833, 0.390192, 1.700566], abs=1e-6)
    assert scores(rank.score(cands, queries, one)) == pytest.approx([1.337209, 0.250428, 1.371413], abs=1e-6)
    both = rank.score(cands, queries, qrels)
    assert scores(both) == pytest.approx([0.668605, 1.331988, 0.685706], abs=1e-6)
    assert rank.pairs(both).select("win_cand", "lose_cand").collect() == [(1, 0)]
    assert rank.pairs(rank.score(cands, queries, one)).select("win_cand", "lose_cand").collect() == [(2, 1)]
    assert {tuple(r) for r in rank.pairs(both, "adjacent").select("win_cand", "lose_cand").collect()} == {(1, 2), (2, 0)}


def test_unified_equals_a_materialised_corpus(spark, tiny):
    cands, queries, qrels = tiny
    docs = cands.select("dataset", F.row_number().over(Window.orderBy("table_id", "cand_id")).cast("long").alias("table_id"), F.lit("text").alias("field"), F.col("body").alias("text"))
    hits = search.single(queries.where("query_id = 1"), search.build_index(docs), k=5)
    got = {r.table_id: r.score for r in hits.collect()}
    assert [got[i] for i in (1, 2, 3)] == pytest.approx([1.337209, 0.250428, 1.371413], abs=1e-6)


def test_iterated_defaults_end(tiny):
    cands, queries, qrels = tiny
    rows, rounds = rank.iterate(cands, queries, qrels, lambda d: d.cache())
    assert rounds <= 3 and rows.count() == 3


def test_metrics(spark):
    hits = spark.createDataFrame([("t", "a", 1, i, i) for i in (1, 2, 3, 4)], "dataset string, config string, query_id long, table_id long, rank int")
    qrels = spark.createDataFrame([("t", 1, 1, 1), ("t", 1, 3, 2), ("t", 1, 9, 2)], "dataset string, query_id long, table_id long, grade int")
    value = lambda d: [r.value for r in d.orderBy("k").collect()]
    assert value(evaluate.ndcg(hits, qrels, (1, 3, 5))) == pytest.approx([0.5, 0.531652, 0.531652], abs=1e-6)
    assert value(evaluate.ndcg(hits, qrels, (1, 3, 5), "exp")) == pytest.approx([0.333333, 0.463582, 0.463582], abs=1e-6)
    assert value(evaluate.recall(hits, qrels, (1, 3))) == pytest.approx([1 / 3, 2 / 3], abs=1e-6)


def test_fields_combine(spark):
    fields = spark.createDataFrame([("t", i, f, t) for i, f, t in [(1, "description", "a b"), (1, "context", "a"), (2, "description", "b"), (3, "context", "a c")]], "dataset string, table_id long, field string, text string")
    queries = spark.createDataFrame([("t", 1, "A a")], "dataset string, query_id long, text string")
    index = search.build_index(fields)
    by_field = {(r.table_id, r.field): r.score for r in search.field_scores(queries, index, ["description", "context"]).collect()}
    multi = {r.table_id: r.score for r in search.multi(queries, index, ("description", "context")).collect()}
    high, low = sorted((by_field[1, "description"], by_field[1, "context"]), reverse=True)
    assert multi[1] == pytest.approx(high + 0.1 * low, abs=1e-6) and set(multi) == {1, 3}
    one = search.multi(queries, index, ("description",)).collect()
    assert one == search.single(queries, index, "description").collect()
    with pytest.raises(ValueError):
        index.check("context", search.WORDS.__class__("trigram"))


def test_stems(spark):
    known = {"caresses": "caress", "ponies": "poni", "ties": "ti", "cats": "cat", "feed": "feed", "agreed": "agre", "plastered": "plaster", "motoring": "motor", "sing": "sing", "conflated": "conflat", "hopping": "hop", "falling": "fall", "filing": "file", "happy": "happi", "sky": "sky", "relational": "relat", "conditional": "condit", "rational": "ration", "digitizer": "digit", "operator": "oper", "feudalism": "feudal", "hopefulness": "hope", "formative": "form", "electrical": "electr", "goodness": "good", "allowance": "allow", "adjustment": "adjust", "adoption": "adopt", "effective": "effect", "probate": "probat", "rate": "rate", "cease": "ceas", "controll": "control", "roll": "roll", "by": "by"}
    got = {r.term: r.stem for r in analysis.stem_terms(spark.createDataFrame([(w,) for w in known], "term string")).collect()}
    assert got == known


def test_names(spark):
    rows = spark.createDataFrame([("DTPhone2nd",), ("c_acctbal",), ("cust_n07",)], "n string")
    assert [r.t for r in rows.select(names.split_name(F.col("n")).alias("t")).collect()] == [["dt", "phone", "2", "nd"], ["c", "acctbal"], ["cust", "n", "07"]]
    parsed = names.parse_expansion(spark.createDataFrame([("cust_nm: cust → customer, nm → name",)], "answer string")).first()
    assert parsed.expanded == "customer name" and parsed.original == "cust_nm" and len(parsed.mapping) == 2
    table = spark.createDataFrame([("e", 1, "documents", "documents", ["n_chars"]), ("e", 2, "orders", "orders", ["o_totalprice"])], "dataset string, table_id long, table_name string, base string, columns array<string>")
    assert [r.expanded for r in names.expand(table).orderBy("table_id").collect()] == ["n characters", "order total price"]


def test_preference_training(spark):
    row = spark.createDataFrame([(2.0, 0.0, 0.0, 0.0)], "win double, win_ref double, lose double, lose_ref double")
    assert train.preference_loss(row, 0.1).first().loss == pytest.approx(0.598139)
    assert train.preference_loss(row.selectExpr("-win as win", "win_ref", "lose", "lose_ref"), 0.5).first().loss == pytest.approx(1.313262)
    assert train.preference_loss(row.selectExpr("0d as win", "win_ref", "lose", "lose_ref"), 0.5).first().loss == pytest.approx(math.log(2), abs=1e-6)
    cfg = train.TrainConfig(epochs=30, rate=0.2)
    model = train.LowRank.new(train.base_weights(cfg), cfg.rank, cfg.alpha)
    assert (model.weights() == model.base).all() and model.n_trainable == cfg.rank * (cfg.features + cfg.vocabulary)
    pairs = pd.DataFrame([("d", i, f"name {i % 3}", "good words here", "bad phrase there") for i in range(16)], columns=["dataset", "table_id", "prompt", "chosen", "rejected"])
    _, steps = train.fit(pairs, cfg)
    assert steps.loss.iloc[-1] < steps.loss.iloc[0] and steps.accuracy.iloc[-1] == 1
    w = np.random.default_rng(1).normal(size=(8, 64))
    assert (np.abs(train.quantize4(w) - w).max(1) <= np.abs(w).max(1) / 14 + 1e-12).all()
    assert train.sample(np.array([0.0, 5.0, 1.0]), temperature=0) == 1
    assert train.linear_warmup(5, 100) == pytest.approx(2.5e-6) and train.linear_warmup(100, 100) == 0


def test_search_plan_stays_in_the_engine(spark):
    plan = workloads.bm25_top10(spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()
    assert "Python" not in plan and "WindowGroupLimit" in plan and "Cartesian" not in plan


@pytest.mark.parametrize("name", ["multi_field_top10", "pref_pairs", "expand_columns", "ndcg", "interval_join"])
def test_against_sql(spark, name):
    duckdb = pytest.importorskip("duckdb")
    sf = "/root/testdata/sf0.001"
    c = duckdb.connect()
    for t in ("customer", "supplier", "part", "orders", "events", "documents", "benchmark"):
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    mine, oracle = workloads.queries()[name](spark, sf), c.sql(workloads.oracle_sql()[name])
    columns = sorted(mine.columns)
    assert columns == sorted(oracle.columns)
    as_rows = lambda rows, names_: sorted(repr([round(v, 5) if isinstance(v, float) else v for _, v in sorted(zip(names_, r))]) for r in rows)
    assert as_rows(map(tuple, mine.collect()), mine.columns) == as_rows(oracle.fetchall(), oracle.columns)
