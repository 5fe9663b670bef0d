"""Batches and workers of the pipeline hold bounded memory."""

import pyarrow as pa
import pytest

import corpus_pipeline
from tabseek.llm import jaccard_join, toxicity, workers

SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


@pytest.mark.parametrize("k", [0, 1, 2, 4])
def test_stages_bound_batches_of_long_texts(spark, monkeypatch, tmp_path, k):
    def largest(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], ["n", "size"])

    monkeypatch.setattr(toxicity, "keep_clean", lambda docs, corpus, labels: docs)
    monkeypatch.setattr(jaccard_join, "keep_one", lambda docs: docs)
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs = spark.range(0, 2000, 1, 1).selectExpr("id AS doc_id", "repeat('a long text ', if(id = 7, 500000, 1000)) AS text", "'en' AS lang", "'s' AS source", "12000L AS n_chars")
    spark.conf.unset(SETTING)
    corpus_pipeline.STAGES[k][1](spark, docs, str(tmp_path))
    got = docs.mapInArrow(largest, "n long, size long").collect()
    assert sum(r.n for r in got) == 2000
    assert max(r["size"] for r in got if r.n > 1) < 2 * workers.BATCH_BYTES  # 24 MB in one batch before
    assert max(r["size"] for r in got) > 5_000_000  # no text is cut


@pytest.mark.parametrize("now, then", [("1m", "1m"), ("64m", str(workers.BATCH_BYTES)), ("1000", "1000")])
def test_a_smaller_bound_stays(spark, now, then):
    spark.conf.set(SETTING, now)
    workers.small_batches(spark)
    assert spark.conf.get(SETTING) == then
    spark.conf.unset(SETTING)


def test_lean_passes_all_on_and_drops_the_vocabulary():
    from tabseek.llm import tokens

    kept = dict(tokens._made)
    try:
        tokens._made["there"] = object()
        assert list(workers.lean(lambda b: (x + 1 for x in b), vocabulary=True)([1, 2])) == [2, 3] and "there" in tokens._made
        assert list(workers.lean(lambda b: (x + 1 for x in b))([1, 2])) == [2, 3] and not tokens._made
    finally:
        tokens._made.update(kept)
