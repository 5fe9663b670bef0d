"""Where a target stands, with many alike rivals: classes of tables against a plain count."""

from __future__ import annotations

import math

import numpy as np
import pytest

from tabseek.operators import rank


def _plain(cands, queries, wanted):
    """Every other table scored by itself in the candidate's own corpus."""
    default = {t: b.split() for t, c, b, gold in cands if not gold or c == (t * 7919 + 42) % 2}
    out = {}
    for table, cand, body, gold in cands:
        places = []
        for q, t in wanted:
            if t != table or not gold:
                continue
            corpus = default | {table: body.split()}
            avg = sum(map(len, corpus.values())) / len(corpus)

            def score(words):
                total = 0.0
                for term in set(queries[q].split()):
                    df, tf = sum(term in w for w in corpus.values()), words.count(term)
                    total += math.log(1 + (len(corpus) - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * len(words) / avg))
                return round(total, 6)

            own = score(corpus[table])
            places.append(1 + sum(score(w) > 0 and (score(w) > own or (score(w) == own and i < table)) for i, w in corpus.items() if i != table))
        if places:
            out[table, cand] = sum(places) / len(places)
    return out


def test_position_equals_a_plain_count(spark, monkeypatch):
    random = np.random.default_rng(5)
    body = lambda: " ".join(f"w{j}" for j in random.integers(0, 6, random.integers(2, 6)))
    cands = [(t, c, body(), t % 3 == 0) for t in range(60) for c in range(2 if t % 3 == 0 else 1)]
    queries = {1: "w1 w2", 2: "w3", 3: "w4 w1 w5"}
    wanted = [(q, t) for q in queries for t in range(0, 60, 3) if (t + q) % 2]
    frame = spark.createDataFrame([("d", *c) for c in cands], "dataset string, table_id long, cand_id int, body string, is_gold boolean")
    asked = spark.createDataFrame([("d", q, t) for q, t in queries.items()], "dataset string, query_id long, text string")
    judged = spark.createDataFrame([("d", q, t, 1) for q, t in wanted], "dataset string, query_id long, table_id long, grade int")
    met = []
    kept = rank.materialise
    monkeypatch.setattr(rank, "materialise", lambda df, name: met.append((name, out := kept(df, name))) or out)
    got = {(r.table_id, r.cand_id): r.mean_rank for r in rank.position(frame, asked, judged, 2).collect()}
    assert got == pytest.approx(_plain(cands, queries, wanted), abs=1e-6)
    # a candidate meets classes, not tables
    rivals = dict(met)["rivals"].groupBy("table_id", "cand_id", "query_id").count().agg({"count": "max"}).first()[0]
    assert rivals < 45
