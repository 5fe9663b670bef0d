"""The pipeline on odd inputs, and run() against the operators' slow references."""

import re

import numpy as np
import pytest

import corpus_pipeline
from tabseek.llm import jaccard_join, mixing, secrets, toxicity
from tabseek.llm.store import free_prefix

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def sf_dir(spark, tmp_path_factory):
    """Documents with nulls, copies, near copies, repeated ids, a hot source, secrets and toxic words."""
    r = np.random.default_rng(6)
    plain = lambda n: " ".join(f"{a}{b}" for a, b in zip(r.choice(list("bdfgklm"), n), r.choice(["ato", "eno", "iru", "olan", "uti", "ares"], n)))
    rows = [(i, plain(60), "en", "hot" if i % 3 else f"s{i % 4}", 60) for i in range(240)]
    rows += [(1000 + i, rows[i][1], "en", "hot", 60) for i in range(0, 60, 4)]  # copies
    rows += [(2000 + i, rows[i][1] + " end", "en", "s1", 61) for i in range(0, 60, 5)]  # near copies
    rows += [(3000 + i, plain(40) + " scoundrel " + plain(20), "en", "s2", 61) for i in range(60)]
    rows += [(4000, "password: hunter2secret " + plain(20), "en", "s3", 30), (4001, None, None, None, None), (4002, "", "en", None, 0), (None, plain(30), "en", "s1", 30)]
    rows += [rows[7], rows[7], (8, plain(50), "en", "s0", 50)]  # repeated rows, and another text of one id
    labels = [(i, 1, int(i >= 3000)) for i, *_ in rows if i is not None]
    path = tmp_path_factory.mktemp("tables")
    spark.createDataFrame(rows, SCHEMA).coalesce(2).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(sorted(set(labels)), "doc_id long, quality int, toxic int").coalesce(1).write.parquet(f"{path}/labels.parquet")
    spark.createDataFrame([], SCHEMA).write.parquet(f"{path}/empty/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{path}/empty/labels.parquet")
    return str(path)


def test_run_equals_the_slow_pipeline(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    rows = [r for r in docs.collect() if toxicity.batch_scores(model, __import__("pyarrow").array([r.text]))[0] < toxicity.THRESHOLD]
    assert all("scoundrel" not in (r.text or "") for r in rows)
    # rows of one id with different texts count for themselves
    variants = sorted({(r.doc_id, r.text) for r in rows if r.doc_id is not None}, key=lambda x: (x[0], x[1] or ""))
    groups = jaccard_join.brute_force(dict(enumerate(t for _, t in variants)))
    stay = {variants[g] for g in groups.values()}
    rows = [next(r for r in rows if (r.doc_id, r.text) == v) for v in stay] + [r for r in rows if r.doc_id is None]
    hidden = spark.createDataFrame([(r.doc_id, secrets.hide(r.text, "[SECRET]") if r.text else r.text, r.lang, r.source, r.n_chars) for r in rows], SCHEMA)
    copies = {(r.doc_id, r.text): r.copies for r in mixing.mix(hidden).collect()}
    want = {}
    for (doc_id, text), n in copies.items():
        n = n if text and re.search(r"\S", text) else 1
        want[doc_id] = want.get(doc_id, 0) + n
    got = {}
    for piece in corpus_pipeline.run(spark, sf_dir).collect():
        if piece.start == 0:
            got[piece.doc_id] = got.get(piece.doc_id, 0) + 1
    assert got == {d: n for d, n in want.items() if n}


def test_empty_tables(spark, sf_dir):
    assert corpus_pipeline.run(spark, f"{sf_dir}/empty").count() == 0


def test_stages_keep_columns_of_any_name(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(120)
    names = ["size", "rate", "copies", "score", "predicted", "label", "component_id", "_own_key", "key", "set_id", "spans", "target"]
    for name in names:
        docs = docs.selectExpr("*", f"cast(doc_id as string) as {name}")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf_dir)
        assert out.columns == docs.columns, name
        assert out.where(" or ".join(f"not ({c} <=> cast(doc_id as string))" for c in names)).isEmpty(), name
    assert not any(n.startswith(free_prefix(names)) for n in names)
    assert not corpus_pipeline.STAGES[-1][1](spark, docs, sf_dir).isEmpty()
