"""The factorization machine: planted pairs, a slow reference score, odd inputs."""

import re

import numpy as np
import pyarrow as pa
import pytest

from tabseek.llm import toxicity


def words(random, n):
    return ["w" + "".join(chr(97 + int(c)) for c in str(x)) for x in random.integers(100, 400, n)]


@pytest.fixture(scope="module")
def planted(spark):
    """Toxic where exactly one of two words stands: neither word tells anything alone."""
    r = np.random.default_rng(4)
    rows, truth = [], []
    for i in range(2400):
        text, a, b = words(r, 50), int(r.integers(2)), int(r.integers(2))
        if a:
            text[3] = "Scoundrel,"
        if b:
            text[20] = "gnomes"
        rows.append((i, " ".join(text)))
        truth.append((i, a ^ b))
    return spark.createDataFrame(rows, "doc_id long, text string").cache(), spark.createDataFrame(truth, "doc_id long, toxic int").cache()


def accuracy(planted, **options):
    docs, truth = planted
    out = toxicity.report(docs, truth, **options).where("held_out").join(truth, "doc_id").toPandas()
    return ((out["score"] >= 0.5) == (out["toxic"] == 1)).mean()


def test_pairs_are_learnt_where_a_linear_model_fails(planted):
    assert accuracy(planted) >= 0.95
    assert accuracy(planted, factors=0) < 0.65


def slow_score(model, text):
    """Bias, weights and products of all pairs, term by term."""
    terms = set()
    for word in set(re.findall(rb"[A-Za-z\x80-\xff]+", (text or "").encode())):
        word = bytes(c + 32 if 65 <= c <= 90 else c for c in word)
        for _, pairs in toxicity.term_hits(pa.array([word.decode(errors="replace")])):
            terms |= {int(p) & ((1 << toxicity.HASH_BITS) - 1) for p in pairs}
    at = [i for i, t in enumerate(model.terms.tolist()) if t in terms]
    margin = model.bias + sum(model.weights[i] for i in at)
    for k, i in enumerate(at):
        for j in at[k + 1 :]:
            margin += float(model.factors[i] @ model.factors[j])
    return 1 / (1 + np.exp(-np.clip(margin, -30, 30)))


def test_scores_equal_the_slow_reference(planted):
    docs, truth = planted
    model = toxicity.train(docs, truth)
    texts = [r.text for r in docs.limit(20).collect()] + [None, "", "gnomes " * 3, "SCOUNDREL gnomes", "x" * 40, " ".join(words(np.random.default_rng(1), 60_000))]
    got = toxicity.batch_scores(model, pa.array(texts))
    assert got == pytest.approx([slow_score(model, t) for t in texts])


def test_repeated_ids_and_clashing_names(spark, planted):
    docs, truth = planted
    again = docs.unionByName(docs.where("doc_id < 50"))
    model = toxicity.train(again, truth.unionByName(truth.limit(100)), sample_per_label=200)
    assert (model.terms == toxicity.train(docs, truth, sample_per_label=200).terms).all()
    assert toxicity.sampled_terms(again, truth, 200).count() == 400
    odd = spark.createDataFrame([(1, "gnomes", 7.0, "a", 3, 1), (None, None, 8.0, "b", 4, 2), (1, "gnomes", 7.0, "a", 3, 1)], "doc_id long, text string, score double, predicted string, _label int, terms int")
    kept = toxicity.keep_clean(odd, docs, truth.limit(0))
    assert kept.columns == odd.columns and sorted(map(str, kept.collect())) == sorted(map(str, odd.collect()))
    assert toxicity.score(odd, model).columns == ["doc_id", "text", "_label", "terms", "score", "predicted"]
    assert toxicity.keep_clean(odd.limit(0), docs.limit(0), truth).count() == 0
