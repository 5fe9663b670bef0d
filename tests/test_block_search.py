"""One pass over the postings for many queries and runs, and many descriptions drawn at once."""

from __future__ import annotations

import numpy as np

from tabseek import workloads
from tabseek.operators import search, train


def _fields(spark):
    random = np.random.default_rng(3)
    rows = [(d, i, f, " ".join(f"w{j}" for j in random.zipf(1.6, 12) % 30)) for d in ("a", "b") for i in range(60) for f in ("x", "y")]
    fields = spark.createDataFrame(rows, "dataset string, table_id long, field string, text string").repartition(3)
    asked = [(d, q, t) for d in ("a", "b") for q, t in enumerate(["w1 w2 w3", "w3 w2 w1 w1", "w7", "nothing", "w1 w5 w9 w4"])]
    return fields, spark.createDataFrame(asked, "dataset string, query_id long, text string")


def test_one_pass_equals_a_search_a_run(spark, monkeypatch):
    fields, queries = _fields(spark)
    index = search.build_index(fields)
    runs = {"x": search.Run(("x",)), "flat": search.Run(("y",), k1=2.0, b=0.0), "both": search.Run(("x", "y"), tie=0.3), "none": search.Run(("x",), k1=0.0)}
    key = ["dataset", "query_id", "table_id", "score", "rank"]
    want = {}
    for name, run in runs.items():
        rows = search.multi(queries, index, run.fields, run.tie, 7, run.k1, run.b).select(*key).collect()
        want[name] = sorted(map(tuple, rows))
    for block, postings in ((4_096, 1 << 20), (5, 40)):  # whole partitions, and documents that meet a block's end
        monkeypatch.setattr(search, "DOC_BLOCK", block)
        monkeypatch.setattr(search, "POSTING_BLOCK", postings)
        got = search.runs_top_k(queries, index, runs, 7, query_block=3 if block == 5 else 100).select("config", *key).collect()
        assert {n: sorted(tuple(r)[1:] for r in got if r.config == n) for n in runs} == want


def test_parameters_share_one_pass(spark):
    """The texts are read for statistics and postings, not once more for each pair of parameters."""
    seen = []
    found = workloads.search.runs_top_k
    try:
        workloads.search.runs_top_k = lambda *a, **k: seen.append(a[2]) or found(*a, **k)
        plan = workloads.bm25_params(spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    finally:
        workloads.search.runs_top_k = found
    assert len(seen) == 1 and len(seen[0]) == 4
    assert plan.count("FileScan parquet [doc_id") <= 1


def test_descriptions_drawn_together_are_those_drawn_alone():
    random = np.random.default_rng(0)
    sizes = np.array([0, 1, 2, 49, 50, 51, 79, 80, 81, 160, *random.integers(0, 170, 60)])
    words = [[f"w{i}" for i in random.permutation(500)[:n]] for n in sizes]
    own = [np.round(random.normal(0, 4, n), 1) for n in sizes]
    logits = np.full((len(sizes), sizes.max()), -np.inf)
    for i, x in enumerate(own):
        logits[i, : len(x)] = x
    for n in (30, 60):
        drawn = train.draw_many(logits, sizes, n, list(range(len(sizes))))
        assert [" ".join(words[i][j] for j in row) for i, row in enumerate(drawn)] == [train.describe_by_sampling(w, x, n, i) for i, (w, x) in enumerate(zip(words, own))]


def test_generate_keeps_its_draws(spark):
    rows = [("d", i, "p q", [f"w{j}" for j in range(i)], ["s"]) for i in (0, 3, 70)] + [("d", 9, None, None, None)]
    tables = spark.createDataFrame(rows, "dataset string, table_id long, prompt string, words array<string>, said array<string>")
    weights = train.base_weights(train.TrainConfig())
    got = {(r.table_id, r.cand_id): r.body for r in train.generate(tables, weights, k=2).collect()}
    for _, i, prompt, own, said in rows:
        own = own or []
        logits = (weights @ train.features(prompt, 64))[[train._bucket(w, 128) for w in own]] if own else np.zeros(0)
        for c in range(2):
            assert got[i, c] == " ".join([*(said or []), train.describe_by_sampling(own, logits * train.LOGIT_SCALE, 30, train._bucket(f"42:d:{i}:{c}", 1 << 31))]).strip()
