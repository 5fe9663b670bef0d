"""The training-data operators against brute force, round trips and odd inputs."""

import base64
import hashlib
import zlib
from pathlib import Path

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from tabseek.llm import ann, jaccard_join, licenses, mixing, packing, quality, secrets, token_files, tokens, toxicity, warc

DOC = "doc_id long, text string, lang string, source string, n_chars long, score double"


def docs(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), 0.5) for i, t, s in rows], DOC)


LONG = " ".join(f"word{i % 997}x{i}" for i in range(30_000))
ODD = [(1, None, "a"), (2, "", "b"), (3, " \n\t ", None), (4, "one two", "a"), (4, "one two", "a"), (None, "null id here", "b"), (5, LONG, "a"), (6, LONG + " end", "c")]


@pytest.fixture(scope="module")
def odd(spark):
    return docs(spark, ODD).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return docs(spark, [])


def library(text):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(tokens.default_vocabulary()).encode(text or "", add_special_tokens=False).ids


def test_token_ids_are_the_librarys():
    texts = ["á ́b", "e\x1cf g h", "don't  I'll  <|endoftext|> x<|startoftext|>y", "Σας ΟΔΟΣ İ", "ß. ÿ, ÀÉ!? naïve; x..: é ×", "", None, "x" * 500, LONG[:5000]]
    tok = tokens.WordTokenizer(tokens.default_vocabulary())
    got = {}
    for row, end, ids, at in tok.encode_texts(pa.array(texts), 2):
        got |= {i: ids[at[i - row] : at[i - row + 1]].tolist() for i in range(row, end)}
    assert got == {i: library(t) + [2] for i, t in enumerate(texts)}


def test_word_aligned_coding():
    r = np.random.default_rng(3)
    for ids in (np.zeros(5000, np.uint64), r.integers(0, 49408, 10_000), np.array([1, (1 << 64) - 1, (1 << 60) - 1, (1 << 63) + 5, (1 << 60) - 2, 0], np.uint64), r.integers(0, 3, 3000), np.zeros(0, np.uint64)):
        words, starts = token_files.encode_blocks(ids)
        assert (token_files.decode_words(words) == np.asarray(ids, np.uint64)).all()
        for b, (s, e) in enumerate(zip(starts, [*starts[1:], len(words)])):
            assert (token_files.decode_words(words[s:e]) == np.asarray(ids[b * 1024 : (b + 1) * 1024], np.uint64)).all()


def test_token_files(odd, empty):
    got = token_files.token_files(odd).collect()
    start = 0
    for row, (doc_id, text, _) in zip(sorted(got, key=lambda r: r.start), sorted(ODD, key=lambda x: (x[0] is not None, x[0] or 0))):
        ids = np.array(library(text) + [2], "<u4")
        assert (row.doc_id, row.start, row.n_tokens, row.ids_crc32) == (doc_id, start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    assert token_files.token_files(empty).count() == 0


def test_packing(odd, empty):
    rows = packing.pack(odd.where("doc_id <> 4"), with_ids=True).collect()
    for doc_id, text, _ in ODD:
        if doc_id not in (None, 4):
            pieces = sorted((r for r in rows if r.doc_id == doc_id), key=lambda r: r.start)
            assert [i for p in pieces for i in p.ids] == library(text) + [2]
            assert all(zlib.crc32(np.array(p.ids, "<u4").tobytes()) == p.ids_crc32 for p in pieces)
    for sequence in {r.sequence_id for r in rows}:
        at = 0
        for p in sorted((r for r in rows if r.sequence_id == sequence), key=lambda r: r.offset):
            assert p.offset == at
            at += p.length
        assert at <= 4096
    assert packing.pack(empty).count() == 0


def test_differencing_keeps_capacity():
    sizes = [int(x) for x in np.random.default_rng(0).integers(1, 4000, 80)]
    windows = packing.fill(sizes)
    assert len(windows) == -(-sum(sizes) // 4096) and all(sum(b - a for _, a, b in w) <= 4096 for w in windows)
    assert sorted((i, u) for w in windows for i, a, b in w for u in range(a, b)) == [(i, u) for i, n in enumerate(sizes) for u in range(n)]
    sums = [sum(sizes[i] for i in w) for w in packing.difference(sizes, 10)]
    assert max(sums) - min(sums) < 100
    assert sorted(sum([8, 7, 6, 5, 4][i] for i in w) for w in packing.difference([8, 7, 6, 5, 4], 2)) == [14, 16]
    assert packing.difference([], 3) == [[], [], []] and packing.fill([]) == []


def test_window_count_rises_with_capacity():
    # nothing is cut: three items of 3,000 need three windows though their sum fills two and a fifth
    assert [[(i, 0, 3000)] for i in range(3)] == sorted(packing.fill([3000] * 3, waste=1.0))
    sizes = [2100] * 40 + [900] * 10
    whole = packing.fill(sizes, waste=1.0)
    assert len(whole) > -(-sum(sizes) // 4096) and all(a == 0 and b == sizes[i] for w in whole for i, a, b in w)
    assert len(packing.fill(sizes)) == -(-sum(sizes) // 4096)


def test_windows_come_from_differencing(monkeypatch):
    sizes = [int(x) for x in np.exp(np.random.default_rng(5).normal(5.5, 1.2, 600)).clip(1, 4095)]
    ours = len(packing.fill(sizes, waste=1.0))
    assert ours * 4096 <= 1.03 * sum(sizes) + 4096
    monkeypatch.setattr(packing, "difference", lambda sizes, n: [list(range(k, len(sizes), n)) for k in range(n)])
    assert len(packing.fill(sizes, waste=1.0)) > 1.2 * ours


def test_jaccard_join(spark, odd, empty, monkeypatch):
    r = np.random.default_rng(7)
    base = [[f"w{x}" for x in r.integers(0, 400, n)] for n in (3, 12, 40, 60, 200, 400)]
    texts, k = {}, 0
    for words in base:
        for _ in range(14):
            copy = list(words)
            for _ in range(int(r.integers(0, max(len(words) // 25, 2)))):
                copy[int(r.integers(len(copy)))] = f"e{r.integers(10**6)}"
            texts[k] = " ".join(copy)
            k += 1
    texts |= {k: None, k + 1: "", k + 2: "one", k + 3: "ONE", k + 4: "one two"}
    frame = docs(spark, [(i, t, "a") for i, t in texts.items()])
    want, links = jaccard_join.brute_force_links(texts)
    for frequent in (10, 1):
        rows = jaccard_join.join(frame, frequent).collect()
        assert {x.doc_id: x.component_id for x in rows} == want and {x.doc_id: x.n_links for x in rows} == links
    assert max(links.values()) > 5
    monkeypatch.setattr(jaccard_join, "LINK_SHINGLES", 300)  # components in many parts
    assert {x.doc_id: x.n_links for x in jaccard_join.join(frame).collect()} == links
    rows = jaccard_join.join(odd).collect()
    assert {(1, 0), (3, 0), (4, 1), (None, 1)} <= {(x.doc_id, x.n_shingles) for x in rows}
    assert {(x.doc_id, x.n_links) for x in rows} == {(1, 0), (2, 0), (3, 0), (4, 1), (None, None), (5, 1), (6, 1)}
    assert jaccard_join.join(empty).count() == 0
    kept = jaccard_join.keep_one(frame)
    assert kept.columns == frame.columns and {x.doc_id for x in kept.collect()} == set(want.values())


def test_keep_one_of_repeated_rows(spark):
    texts = {1: LONG, 2: LONG + " end", 3: "one two three", 4: "five six seven", 5: None}
    rows = [(i, t, "a") for i, t in texts.items()] * 2 + [(1, LONG, "a"), (None, "five six seven", "b"), (None, "five six seven", "b")]
    frame = docs(spark, rows)
    kept = jaccard_join.keep_one(frame)
    want = sorted(set(jaccard_join.brute_force(texts).values()))
    ids = [x.doc_id for x in kept.collect()]
    assert sorted(i for i in ids if i is not None) == want and ids.count(None) == 2 and kept.columns == frame.columns


def test_neighbours(spark):
    r = np.random.default_rng(1)
    data = r.normal(size=(900, 16)).astype(np.float32)
    data[500:520] = data[7]
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(data)] + [(2000, None), (2020, [0.0] * 16), (2040, [float("nan")] * 16), (2060, [None] * 16), (2080, [])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = ann.nearest(frame, frame.where("vec_id % 20 = 0")).collect()
    found = {}
    for x in sorted(got, key=lambda x: (x.query_id, x.rank)):
        found.setdefault(x.query_id, []).append(x.vec_id)
        assert x.score == pytest.approx(float(data[x.query_id].astype(float) @ data[x.vec_id].astype(float)))
    want = ann.brute_force(np.arange(900), data.astype(float), np.arange(0, 900, 20))
    assert set(found) == set(want)
    assert np.mean([len(set(found[q]) & set(w)) / 20 for q, w in want.items()]) >= 0.9
    assert ann.nearest(frame.limit(0), frame.limit(0)).count() == 0
    few = ann.nearest(frame.where("vec_id < 5"), frame.where("vec_id = 0"))
    assert few.count() == 4


def test_secrets(odd, empty):
    token = ".".join(base64.urlsafe_b64encode(x).decode().rstrip("=") for x in (b'{"alg":"HS256"}', b'{"sub":"1"}', b"signature"))
    number = b"\x02\x08" + bytes(range(1, 9))
    der = b"\x30" + bytes([3 + 8 * 10]) + b"\x02\x01\x00" + number * 8
    encoded = base64.b64encode(der).decode()
    text = f'é Password = "abcdefgh" secret: token: abcdefg {token} {encoded} AKIA{"A" * 16} {"0a" * 12} AKIAA {"f" * 23}'
    base, every = secrets.spans(text)
    # "token" is too short a value; it is consumed and hides what follows
    assert [(text[s:e], k) for s, e, k in base] == [('Password = "abcdefgh', "assign"), ("AKIA" + "A" * 16, "access"), ("0a" * 12, "hex")]
    assert {k for _, _, k in every} >= {"assign", "access", "hex", "jwt", "der"}
    assert all(b in every for b in base)
    assert not secrets.is_private_der(der[:-1]) and not secrets.is_signed_token("eyJhbGciOiJ9.eyJ9.x")
    rows = secrets.scan(odd).collect()
    assert all(r.base_sha256 == hashlib.sha256(b"").hexdigest() and r.spans == "" for r in rows) and len(rows) == len(ODD)
    assert secrets.scan(empty).count() == 0 and secrets.redact(odd).collect() == odd.collect()
    assert "abcdefgh" not in secrets.hide(text, "[X]")


def test_encoded_keys_in_every_form():
    item = lambda tag, body: bytes([tag, 0x82]) + len(body).to_bytes(2, "big") + body
    der = item(0x30, b"\x02\x01\x00" + (b"\x02\x28" + bytes(range(1, 41))) * 8)
    scheme = b"\x30\x0f\x06\x09" + bytes.fromhex("2a864886f70d01050d") + b"\x30\x02\x05\x00"
    sealed = item(0x30, scheme + item(0x04, bytes(range(200))))
    part = lambda b: len(b).to_bytes(4, "big") + b
    ssh = b"openssh-key-v1\0" + part(b"none") + part(b"none") + part(b"") + b"\0\0\0\1" + part(b"p" * 51) + part(b"s" * 136)
    b64 = lambda b: base64.b64encode(b).decode()
    wrap = lambda t, n, by="\n": by.join(t[i : i + n] for i in range(0, len(t), n))
    bare = [(wrap(b64(d), n, by), kind) for d, kind in ((der, "der"), (sealed, "der"), (ssh, "ssh")) for n in (64, 76, 9999) for by in ("\n", "\r\n  ", "\\n")]
    bare += [(t, kind) for d, kind in ((der, "der"), (sealed, "der"), (ssh, "ssh")) for t in (d.hex(), d.hex().upper(), wrap(d.hex(), 64))]
    for before in ("key: ", "0x", "x", "/", "_", "-", '"\\n'):
        for body, kind in bare:
            text = f"é {before}{body}\nThe end"
            found = [(s, e) for s, e, k in secrets.spans(text)[1] if k == kind]
            assert (len(text) - len("\nThe end") - len(body), len(text) - len("\nThe end")) in found, (before, body)
            assert body[5:60] not in secrets.hide(text, "[X]") and body[-30:] not in secrets.hide(text, "[X]")
    pem = lambda name, head, d: f"-----BEGIN {name}-----\n{head}{wrap(b64(d), 64)}\n-----END {name}-----"
    old = "Proc-Type: 4,ENCRYPTED\nDEK-Info: AES-128-CBC,0123456789ABCDEF0123456789ABCDEF\n\n"
    for block in (pem("ENCRYPTED PRIVATE KEY", "", sealed), pem("RSA PRIVATE KEY", old, bytes(range(160))), pem("PRIVATE KEY", "", der), pem("OPENSSH PRIVATE KEY", "", ssh)):
        for text in (block, block.replace("\n", "\\n"), block.replace("\n", "\r\n")):
            assert secrets.hide(f"a {text} b", "[X]") == "a [X] b"
    assert not secrets.confirmed_spans(b64(der[:-9])) and not secrets.confirmed_spans(pem("RSA PRIVATE KEY", "", bytes(range(160))))


def test_mixing(spark, odd, empty):
    rows = mixing.report(odd).collect()
    total = sum(r["size"] for r in rows)
    targets = {(s, r.target) for (_, _, s), r in zip(ODD, rows)}
    assert sum(dict.fromkeys(t for _, t in targets)) <= total + 1e-6
    assert all(r.taken in (0, r["size"], 2 * r["size"], 3 * r["size"]) and r.target <= 3 * r.source_size for r in rows)
    assert mixing.report(odd).collect() == rows and mixing.report(empty).count() == 0
    many = docs(spark, [(i, "w " * 20, f"s{i % 4}") for i in range(2000)])
    taken = {r.source: (r.taken, r.target) for r in mixing.mix(many).groupBy("source").agg(F.sum(F.col("size") * F.col("copies")).alias("taken"), F.first("target").alias("target")).collect()}
    assert all(abs(a - b) < 0.15 * b for a, b in taken.values())
    assert mixing.emit(many).columns == many.columns


def test_toxicity(spark, empty):
    r = np.random.default_rng(2)
    plain = lambda: [f"t{x}".translate(str.maketrans("0123456789", "abcdefghij")) for x in r.integers(100, 999, 60)]
    rows, labels = [], []
    for i in range(600):
        words = plain()
        if i % 4 == 0:
            words[5] = ["Scoundrel", "wretches,", "wretched"][i // 4 % 3]
        rows.append((i, " ".join(words), "a"))
        labels.append((i, 1, int(i % 4 == 0)))
    truth = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = {x.doc_id: x for x in toxicity.report(docs(spark, rows + [(1000, None, "a"), (None, "x", "b")]), truth).collect()}
    held = [x for x in got.values() if x.held_out and x.doc_id is not None]
    assert held and np.mean([x.predicted == int(x.doc_id % 4 == 0) for x in held]) > 0.95
    assert all(x.held_out == (zlib.crc32(str(x.doc_id).encode()) % 3 == 1) for x in got.values() if x.doc_id is not None)
    assert 0 <= got[1000].score <= 1
    assert toxicity.report(empty, truth).count() == 0
    assert {x.predicted for x in toxicity.report(docs(spark, rows), truth.limit(0)).collect()} == {0}


def test_quality(odd, empty, spark):
    def plain(text):
        words = (text or "").split()
        at = {}
        for i in range(len(words) - 2):
            at.setdefault(tuple(words[i : i + 3]), []).append(i)
        return len({p + o for places in at.values() if len(places) > 1 for p in places for o in range(3)})

    texts = ["a b c a b c a b c d", "x y", "a a a a", "p q r s p q r t", "l1\nl2\nl1\n\n\nl1"]
    rows = quality.judge(docs(spark, [(i, t, "a") for i, t in enumerate(texts)])).collect()
    assert [r.n_repeat_words for r in sorted(rows, key=lambda r: r.doc_id)] == [plain(t) for t in texts]
    assert [r.n_dup_lines for r in rows if r.doc_id == 4] == [2]
    assert {(r.doc_id, r.n_words, r.base_failed, r.kept) for r in quality.judge(odd).collect()} >= {(1, 0, True, False), (5, 30_000, False, True)}
    assert quality.judge(empty).count() == 0
    parts = {r.rule: r for r in quality.ablations(quality.ledger(odd.select("doc_id", "text"))).collect()}
    assert parts["too_few_words"].n_failed == 6 and parts["too_few_words"].n_kept_without == 8
    assert "Python" not in quality.judge(odd)._jdf.queryExecution().toString()


def test_licenses(spark, empty):
    rows = [("lib/a/1", "Licensed under the Apache License, Version 2.0."), ("lib/a/2", "code " * 50), ("lib/a/b/3", "more " * 50 + "\nReleased under the MIT License."), ("lib/c/4", "x"), ("top", None), (None, "MIT license")]
    frame = spark.createDataFrame([(i, p, t) for i, (p, t) in enumerate(rows)], "doc_id long, path string, text string")
    got = {r.doc_id: (r.own_license, r.license, r.inherited_from) for r in licenses.scan(frame).collect()}
    assert got[0] == ("Apache-2.0", "Apache-2.0", None) and got[1] == (None, "Apache-2.0", "lib/a") and got[2][:2] == ("MIT", "MIT")
    assert got[3] == (None, None, None) and got[4] == (None, None, None) and len(got) == 6
    assert licenses.scan(frame.limit(0)).count() == 0


def test_whole_headers_and_licence_texts(spark):
    texts = Path(licenses.__file__).parent / "license_texts"
    whole = {name: (texts / f"{name}.txt").read_text() for name in ("MIT", "GPL-3.0", "Apache-2.0")}
    rows = [(f"{name}/repo/terms", "Copyright (c) 2020 A. Person\n\n" + text) for name, text in whole.items()]
    rows += [(f"{name}/repo/src/main.c", "int main(void);") for name in whole]
    gnu = "# This program is free software: you can redistribute it and/or modify\n# it under the terms of the GNU General Public License as published by\n# the Free Software Foundation, either version {} of the License, or\n# (at your option) any later version.\nimport os\nprint(1)\n" + "x = 1\n" * 90
    rows += [("w/3", gnu.format(3)), ("w/2", gnu.format(2)), ("t/x", "GNU GENERAL PUBLIC LICENSE\nVersion 3, 29 June 2007"), ("n/LICENSE", "words " * 60 + "\nReleased under the MIT License."), ("n/a", "code")]
    frame = spark.createDataFrame([(i, p, t) for i, (p, t) in enumerate(rows)], "doc_id long, path string, text string")
    got = {r.path: r for r in licenses.scan(frame).collect()}
    for name in whole:
        assert got[f"{name}/repo/terms"].own_license == name and got[f"{name}/repo/terms"].is_file
        assert (got[f"{name}/repo/src/main.c"].license, got[f"{name}/repo/src/main.c"].inherited_from) == (name, f"{name}/repo")
    assert [got[p].own_license for p in ("w/3", "w/2", "t/x")] == ["GPL-3.0", "GPL-2.0", "GPL-3.0"] and not got["w/3"].is_file
    assert got["n/LICENSE"].is_file and got["n/a"].license == "MIT"


def test_warc(spark):
    body = "<p>" + "ünïcode " * 40
    rows = [(1, "http://a/1", body), (2, "http://a/2\r\nX: y", body), (3, None, None), (4, "u", ""), (5, "u", "tiny"), (6, "u", "tiny"), (7, "u", LONG), (8, "u", LONG), (1, "http://a/1", body)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = sorted((tuple(r) for r in warc.round_trip(pages, segment_bytes=5000).collect()), key=str)
    digest = lambda t: hashlib.sha256((t or "").encode()).hexdigest()
    first = {digest(body): 1, digest(LONG): 7}
    want = []
    for page, _, html in rows:
        lead = first.get(digest(html), page)
        want.append((page, len((html or "").encode()), digest(html), "response" if lead == page else "revisit", None if lead == page else lead))
    assert got == sorted(want, key=str)
    assert warc.round_trip(pages.limit(0)).count() == 0
    assert warc.unchunked(warc.chunked(b"x" * 10_000)) == b"x" * 10_000
    with pytest.raises(ValueError):
        warc.unchunked(b"5\r\nabc\r\n0\r\n\r\n")


def test_pipeline(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    frame = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, frame, sf)
        assert out.columns == frame.columns, name
        frame = out.cache()
    pieces = corpus_pipeline.STAGES[-1][1](spark, frame, sf)
    assert pieces.count() >= frame.count() > 0
