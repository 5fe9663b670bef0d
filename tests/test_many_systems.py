"""Many systems in one pass: drawn, trained and counted as one by one."""

from collections import Counter

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from tabseek.functions.analysis import tally
from tabseek.operators import train


def test_tally_counts_in_the_row(spark):
    rows = [["b", "a", "b", "é", "ab"], [], ["x"] * 7, [str(i * i % 13) for i in range(200)]]
    got = spark.createDataFrame([(i, w) for i, w in enumerate(rows)], "i int, w array<string>").select("i", tally(F.col("w")).alias("t")).collect()
    assert {r.i: [(x.term, x.tf) for x in r.t] for r in got} == {i: sorted(Counter(w).items(), key=lambda x: x[0].encode()) for i, w in enumerate(rows)}
    null = spark.range(1).select(tally(F.lit(None).cast("array<string>")).alias("t")).first()
    assert null.t is None


def test_many_voices_say_what_each_says_alone(spark):
    rows = [("d", i, f"price of part {i}", [f"w{j * i % 37}" for j in range(40)], ["said"]) for i in range(30)] + [("d", 99, None, [], [])]
    tables = spark.createDataFrame(rows, "dataset string, table_id long, prompt string, words array<string>, said array<string>")
    voices = {"one": train.Voice(train.base_weights(train.TrainConfig())), "other": train.Voice(train.base_weights(train.TrainConfig(), 1), n=12)}
    asked = tables.withColumn("voice", F.explode(F.array(*map(F.lit, voices)))).withColumn("k", F.when(F.col("voice") == "one", 2).otherwise(1))
    got = {(r.voice, r.table_id, r.cand_id): r.body for r in train.describe(asked, voices).collect()}
    for name, k in (("one", 2), ("other", 1)):
        alone = {(name, r.table_id, r.cand_id): r.body for r in train.generate(tables, voices[name].weights, k=k, n=voices[name].n).collect()}
        assert alone == {key: body for key, body in got.items() if key[0] == name}


def test_runs_train_side_by_side(spark):
    pairs = [("d", i, f"p{i % 5} q", f"good w{i}", f"bad w{i + 1}", held, run) for i in range(20) for held in ("a", "b") for run in ("x", "y")]
    folds = spark.createDataFrame(pairs, "dataset string, table_id long, prompt string, chosen string, rejected string, held_out string, run string")
    runs = {"x": (train.TrainConfig(), 0), "y": (train.TrainConfig(epochs=2), 1)}
    got = train.many_adapters(folds, runs).collect()
    assert len(got) == 4
    for r in got:
        frame = pd.DataFrame(pairs, columns=["dataset", "table_id", "prompt", "chosen", "rejected", "held_out", "run"])
        model, _ = train.fit(frame[(frame.held_out == r.held_out) & (frame.run == r.run)], *runs[r.run])
        assert np.allclose(r.a, model.a.ravel()) and np.allclose(r.b, model.b.ravel())


def test_described_words_keep_their_hashes():
    """Rows without words, without a prompt, and no rows at all, beside others."""
    frame = pd.DataFrame({"dataset": "d", "table_id": [1, 2, 3], "prompt": ["a b a", None, ""], "words": [["x", "y", "x"], [], None], "said": [None, ["s"], []], "k": [2, 1, 1]})
    cfg = train.TrainConfig()
    hashes = train._Hashes()
    out = train._described(frame, train.base_weights(cfg), cfg, 30, 42, hashes)
    assert sorted(out.body[0].split()) == ["x", "y"] and list(out.body[2:]) == ["s", ""]
    assert hashes["x"] == train.zlib.crc32(b"x")
    assert len(train._described(frame[:0], train.base_weights(cfg), cfg, 30, 42, hashes)) == 0
