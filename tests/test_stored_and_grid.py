"""The stored index against the one in memory, streams against batches, construction and the experiment grid."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from tabseek import experiments, workloads_build
from tabseek.functions.analysis import Analyzer
from tabseek.operators import benchmark, names, rank, search, stored, train
from tabseek.plans import datasets

SF = "/root/testdata/sf0.001"
TEXTS = [(1, "red apple red"), (2, "green apple"), (3, None), (4, ""), (5, "the quick fox"), (6, "apple " * 50)]


@pytest.fixture
def fields(spark):
    rows = [("d", i, "text", t) for i, t in TEXTS]
    return spark.createDataFrame(rows, "dataset string, table_id long, field string, text string")


@pytest.fixture
def asked(spark):
    return spark.createDataFrame([("d", 1, "red apple"), ("d", 2, "fox unknown"), ("d", 3, "")], "dataset string, query_id long, text string")


def _rows(df):
    return sorted(map(tuple, df.collect()))


def test_versions_add_up(spark, fields, asked, tmp_path):
    path = str(tmp_path / "index")
    stored.write_version(fields.where("table_id <= 2"), path, 0)
    stored.write_version(fields.where("table_id > 2"), path, 1)
    stored.write_version(fields.where("table_id > 2"), path, 1)  # again: replaces itself
    terms = search.query_terms(asked).select("dataset", "term").distinct()
    expected = _rows(search.single(asked, search.build_index(fields)))
    assert _rows(search.single(asked, stored.open_index(spark, path))) == expected
    assert _rows(search.single(asked, stored.open_index(spark, path, terms))) == expected
    first = _rows(search.single(asked, stored.open_index(spark, path, as_of=0)))
    assert first == _rows(search.single(asked, search.build_index(fields.where("table_id <= 2"))))


def test_uncommitted_version_is_not_seen(spark, fields, asked, tmp_path):
    import shutil

    path = str(tmp_path / "index")
    stored.write_version(fields.where("table_id <= 2"), path, 0)
    stored.write_version(fields.where("table_id > 2"), path, 1)
    shutil.rmtree(f"{path}/commits/version=1")
    assert {r.table_id for r in stored.open_index(spark, path).postings.collect()} == {1, 2}


def test_empty_index_and_empty_version(spark, fields, asked, tmp_path):
    assert _rows(search.single(asked, stored.open_index(spark, str(tmp_path / "none")))) == []
    path = str(tmp_path / "index")
    stored.write_version(fields.limit(0), path, 0)
    stored.write_version(fields, path, 1)
    assert _rows(search.single(asked, stored.open_index(spark, path))) == _rows(search.single(asked, search.build_index(fields)))


def test_other_analyzer_raises(spark, fields, tmp_path):
    path = str(tmp_path / "index")
    stored.write_version(fields, path, 0)
    with pytest.raises(ValueError):
        stored.open_index(spark, path, analyzer=Analyzer("trigram"))


def test_slots_reach_the_scan(spark, fields, asked, tmp_path):
    path = str(tmp_path / "index")
    stored.write_version(fields, path, 0)
    terms = search.query_terms(asked).select("dataset", "term").distinct()
    plan = stored.open_index(spark, path, terms).postings._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters" in plan and "slot" in plan.split("PartitionFilters")[1][:400]


def test_streams_equal_batches(spark):
    assert _rows(workloads_build.stream_index_top10(spark, SF)) == _rows(workloads_build.stored_index_top10(spark, SF))


def test_distinct_pair_ties_and_empty_texts(spark):
    rows = [(1, 1, "a b"), (1, 2, "a c"), (1, 3, "a b"), (2, 1, "x"), (3, 1, ""), (3, 2, None)]
    got = _rows(benchmark.distinct_pair(spark.createDataFrame(rows, "task int, query_id int, text string")))
    assert got == [(1, 1, 2, round(1 / 3, 6)), (3, 1, 2, 1.0)]


def test_relabel_and_task_judgements(spark):
    qrels = spark.createDataFrame([("t", 1, 3), ("t", 2, 1), ("t", 3, 2)], "task string, table_id long, grade int")
    verdicts = spark.createDataFrame([("t", 1, 0), ("t", 2, 3)], "task string, table_id long, verdict int")
    assert _rows(benchmark.relabel(qrels, verdicts)) == [("t", 1, 0), ("t", 2, 1), ("t", 3, 2)]
    asked = spark.createDataFrame([("t", 7), ("t", 8)], "task string, query_id long")
    assert benchmark.task_to_query(qrels, asked).count() == 6


def test_bootstrap_of_equal_systems_is_zero(spark):
    rows = [("d", c, q, q / 10) for c in "ab" for q in range(10)]
    frame = spark.createDataFrame(rows, "dataset string, config string, query_id long, value double")
    assert _rows(benchmark.bootstrap(frame, "a", "b", 50)) == [("d", 0.0, 0.0)]


def test_resample_weights_have_mean_one(spark):
    mean = spark.range(2000).select(F.avg(benchmark._weight(F.col("id"), F.lit(1)))).first()[0]
    assert math.isclose(mean, 1, abs_tol=0.1)


def test_training_prefers_what_won(spark):
    rows = [("other", i, "station rain", "rain month", "zebra lamp") for i in range(200)]
    pairs = spark.createDataFrame(rows, "dataset string, table_id long, prompt string, chosen string, rejected string").withColumn("held_out", F.lit("x"))
    adapter = train.adapters(pairs).first()
    tables = spark.createDataFrame([("x", i, "station rain", ["zebra", "lamp", "rain", "month"]) for i in range(40)] + [("x", 99, None, None)], "dataset string, table_id long, prompt string, words array<string>")

    def share(weights):
        bodies = [r.body for r in train.generate(tables, weights, n=2).where("table_id < 99").collect()]
        return sum(w in ("rain", "month") for b in bodies for w in b.split()) / (2 * len(bodies))

    assert share(train.trained_weights(adapter.a, adapter.b)) > share(train.trained_weights(None, None)) + 0.1
    assert train.generate(tables, train.base_weights(train.TrainConfig())).where("table_id = 99").first().body == ""
    gains = train.margins(train.likelihoods(pairs, train.trained_weights(adapter.a, adapter.b))).first()
    assert gains.accuracy == 1 and gains.avg_margin > 0
    x, w, c = np.ones((1, 64)) / 8, train.base_weights(train.TrainConfig()), train.choices("rain month rain", 128)
    assert train.log_likelihoods(w, x, c[None])[0] == pytest.approx(train.log_likelihood(w, x[0], c))


def test_draws_depend_on_table_and_candidate_alone(spark):
    tables = spark.createDataFrame([("x", i, "p", [f"w{j}" for j in range(30)]) for i in range(20)], "dataset string, table_id long, prompt string, words array<string>")
    base = train.base_weights(train.TrainConfig())
    one, many = (_rows(train.generate(tables.repartition(n), base, k=3, n=5)) for n in (1, 7))
    assert one == many and len({r[3] for r in one}) > 50


def test_published_settings():
    cfg = train.TrainConfig()
    assert (cfg.rank, cfg.alpha, cfg.beta, cfg.batch, cfg.bits, cfg.state_bits, cfg.warmup) == (64, 64.0, 0.1, 8, 4, 8, 0.1)
    r = np.random.default_rng(1).normal(size=(10, 64))
    assert (np.abs(train.quantize(r, 8) - r).max(1) <= np.abs(r).max(1) / 254 + 1e-12).all()


def test_expansion_wins_over_names_as_they_are(spark):
    got = {(r.config, r.k): r.value for r in experiments.exp_expansion(spark, SF).collect()}
    assert all(got["expanded names", k] > got["names as they are", k] for k in (5, 10, 20))


def test_compaction_replaces_versions(spark, fields, asked, tmp_path):
    path = str(tmp_path / "index")
    for i in range(3):
        stored.write_version(fields.where(f"table_id % 3 = {i}"), path, i, slots=i + 1)
    expected = _rows(search.single(asked, search.build_index(fields)))
    terms = search.query_terms(asked).select("dataset", "term").distinct()
    assert _rows(search.single(asked, stored.open_index(spark, path, terms))) == expected
    assert stored.compact(spark, path) == 3 and stored.compact(spark, path) is None
    assert _rows(search.single(asked, stored.open_index(spark, path, terms))) == expected
    assert {r.version for r in stored._live(stored.versions(spark, path).collect())} == {3}


def test_layout_follows_the_size():
    assert stored.layout(0) == (1, 4)
    small, large = stored.layout(1 << 36), stored.layout(1 << 46)
    assert small[1] * stored.TASK_BYTES >= 1 << 36 and large[0] == stored.MOST_SLOTS and large[1] > 1000 * small[1]


def test_target_positions_equal_lists_of_own_corpora(spark):
    bodies = {1: ["red apple", "red red apple pie", "blue"], 2: ["red"], 3: ["red green"], 4: ["apple tart red red"]}
    rows = [("t", t, t == 1, c, b) for t, bs in bodies.items() for c, b in enumerate(bs)]
    cands = spark.createDataFrame(rows, "dataset string, table_id long, is_gold boolean, cand_id int, body string")
    queries = spark.createDataFrame([("t", 1, "red apple"), ("t", 2, "apple")], "dataset string, query_id long, text string")
    qrels = spark.createDataFrame([("t", q, 1, 1) for q in (1, 2)], "dataset string, query_id long, table_id long, grade int")
    got = {r.cand_id: r.mean_rank for r in rank.position(cands, queries, qrels).collect()}
    for c, body in enumerate(bodies[1]):
        corpus = spark.createDataFrame([("t", t, "text", body if t == 1 else bs[0]) for t, bs in bodies.items()], "dataset string, table_id long, field string, text string")
        hits = search.single(queries, search.build_index(corpus)).collect()
        places = [next((h.rank for h in hits if (h.query_id, h.table_id) == (q, 1)), 1 + sum(h.query_id == q for h in hits)) for q in (1, 2)]
        assert got[c] == pytest.approx(sum(places) / 2)


def test_dense_search_in_blocks(spark):
    r = np.random.default_rng(0)
    data = r.normal(size=(200, 6))
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(data)] + [(500, None), (501, [0.0] * 6), (502, [1.0, 2.0]), (503, [None] * 6), (504, [3.0, 1.0])]
    vectors = spark.createDataFrame(rows, "table_id long, embedding array<double>")
    asked = vectors.where("table_id % 10 = 0 OR table_id > 500").withColumnRenamed("table_id", "query_id")
    got = {}
    for x in search.dense(asked.unionByName(asked.limit(3)), vectors, k=5, block=8).collect():
        got.setdefault(x.query_id, {})[x.rank] = x.table_id
    unit = data / np.linalg.norm(data, axis=1, keepdims=True)
    for q in range(0, 200, 10):
        scores = np.round(unit @ unit[q], 6)
        scores[q] = -2
        assert [got[q][i] for i in range(1, 6)] == np.lexsort((np.arange(200), -scores))[:5].tolist()
    assert got[502] == {1: 504} and got[504] == {1: 502} and not {500, 501, 503} & set(got)


def test_containment_equals_substrings(spark):
    docs = {1: "xx alpha beta gamma delta yy", 2: "alpha beta gamma", 3: "zalpha beta gamma deltas", 4: None, 5: "one two", 6: "alpha betax gamma delta"}
    heads = {1: "alpha beta gamma delta", 2: "one two", 3: "", 4: "lpha beta gam"}
    frame = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    asked = spark.createDataFrame(list(heads.items()), "item_id long, head string")
    want = sorted((d, i) for d, t in docs.items() for i, h in heads.items() if t and h and h in t)
    assert _rows(datasets.containing(frame, asked)) == want
    only = datasets.containing(frame, asked.where("item_id = 1"))._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in only and "Cartesian" not in only


def test_answers_with_reasoning(spark):
    rows = [(1, "It holds: things.\nFinal answer:\nemp_nm: emp → employee, nm → name\nqty: qty → quantity"), (2, "a_b: a → alpha, b → beta"), (3, None), (4, "no line")]
    got = {(r.table_id, r.original): r.expanded for r in names.parse_answer(spark.createDataFrame(rows, "table_id long, answer string")).collect()}
    assert got == {(1, "emp_nm"): "employee name", (1, "qty"): "quantity", (2, "a_b"): "alpha beta"}
