"""Collision counting: repeated rows, clashing names, ties, the verified share, blocks."""

import numpy as np

from tabseek.llm import ann


def test_repeated_rows_and_clashing_names(spark):
    r = np.random.default_rng(8)
    data = {i: [float(x) for x in r.normal(size=8)] for i in range(60)}
    rows = [(i, v, 1, 2.0, 3, 4) for i, v in data.items()]
    schema = "vec_id long, embedding array<double>, rank int, score double, dim int, ib int"
    once = spark.createDataFrame(rows, schema)
    # twice in the same way, and one id with another vector, of which the least counts
    more = spark.createDataFrame(rows + rows[::20] * 3 + [(7, [99.0] * 8, 1, 2.0, 3, 4), (None, [1.0] * 8, 1, 2.0, 3, 4)], schema)
    key = lambda frame: sorted(tuple(x) for x in ann.nearest(frame, frame.where("vec_id % 20 = 0")).collect())
    got = key(more)
    assert got == key(once) and len(got) == 3 * 20
    for q in (0, 20, 40):
        mine = [x for x in got if x[0] == q]
        assert [x[1] for x in mine] == list(range(1, 21)) and len({x[2] for x in mine}) == 20 and q not in {x[2] for x in mine}


def test_ties_go_to_smaller_ids(spark):
    frame = spark.createDataFrame([(i, [1.0, 0.0]) for i in range(40)], "vec_id long, embedding array<double>")
    got = ann.nearest(frame, frame.where("vec_id = 20")).orderBy("rank").collect()
    assert [x.vec_id for x in got] == list(range(20))


def test_recall_over_blocks_and_lengths(spark):
    r = np.random.default_rng(3)
    data = r.normal(size=(1500, 24))
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(data)] + [(5000 + i, [float(i + 1)] * 3) for i in range(4)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {}
    for x in ann.nearest(frame, frame.where("vec_id % 20 = 0"), index_block=400, query_block=16, least=100).collect():
        got.setdefault(x.query_id, set()).add(x.vec_id)
    want = ann.brute_force(np.arange(1500), data, np.arange(0, 1500, 20))
    assert np.mean([len(got[q] & set(w)) / 20 for q, w in want.items()]) >= 0.95
    assert got[5000] == {5001, 5002, 5003}


def test_a_small_share_is_verified():
    r = np.random.default_rng(2)
    data, ids = r.normal(size=(8000, 32)), np.arange(8000)
    index = ann.ProjectionIndex.opened(ann.ProjectionIndex(ids, data).stored(), ann.PROJECTIONS)
    verified, plain = [], index._verify
    index._verify = lambda q, length, found, ids, k: verified.append(len(found)) or plain(q, length, found, ids, k)
    asked = np.arange(0, 8000, 80)
    found = {int(q): set(ids[places].tolist()) for q, places, _ in index.search(data[asked], asked, 20, 0.65, 0.05, 400, 1.5, 1.4)}
    want = ann.brute_force(ids, data, asked)
    assert np.mean([len(found[q] & set(w)) / 20 for q, w in want.items()]) >= 0.95
    assert np.mean(verified) < 0.1 * len(ids)
