"""Secret spans against a slow scanner, licences and archives on odd inputs."""

import hashlib

import numpy as np

from tabseek.llm import licenses, secrets, warc

NAMES = ("password", "passwd", "secret", "token", "apikey", "api_key")
VALUE = set("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_.=-")


def run_of(text, at, letters):
    end = at
    while end < len(text) and text[end] in letters:
        end += 1
    return end


def assign_at(text, at):
    """Where an assignment that begins at ``at`` has its value: (start, end), or None."""
    for name in NAMES:
        if "".join(c.lower() if c.isascii() else c for c in text[at : at + len(name)]) != name:
            continue
        for quote in (1, 0):
            i = at + len(name)
            if quote and text[i : i + 1] not in ("'", '"'):
                continue
            i = run_of(text, i + quote, " ")
            if text[i : i + 1] not in (":", "="):
                continue
            i = run_of(text, i + 1, " ")
            for skip in (1, 0):
                if skip and text[i : i + 1] not in ("'", '"'):
                    continue
                end = run_of(text, i + skip, VALUE)
                if end > i + skip:
                    return i + skip, end
    return None


def slow_base(text):
    found, at = [], 0
    while at < len(text):  # assignments: what matches is used up even if its value is too short
        hit = assign_at(text, at)
        if hit and hit[1] - hit[0] >= 6:
            found.append((at, hit[1], "assign"))
        at = hit[1] if hit else at + 1
    for kind, head, letters, least in (("access", "AKIA", set("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789"), 20), ("hex", "", set("0123456789abcdef"), 24)):
        at = 0
        while at < len(text):
            end = run_of(text, at + len(head), letters) if text.startswith(head, at) else at
            if end > at + len(head):
                if end - at >= least:
                    found.append((at, end, kind))
                at = end
            else:
                at += 1
    return sorted(found, key=lambda s: (s[0], secrets.KINDS.index(s[2])))


def test_base_spans_equal_the_slow_scanner(spark):
    r = np.random.default_rng(12)
    pieces = [*NAMES, "Password", "TOKEN", "Api_Key", ":", "=", " ", "  ", '"', "'", "\n", "AKIA", "AKIAKIA", "A" * 15, "0Z9" * 7, "deadbeef" * 2, "0123456789abcdef", "xyz", "é", "ſecret", "K", "a.b-c", "==", "/", "\t"]
    texts = ["".join(pieces[i] for i in r.integers(0, len(pieces), int(r.integers(1, 30)))) for _ in range(3000)]
    for text in texts:
        assert secrets.spans(text)[0] == slow_base(text), text
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for x in secrets.scan(rows).collect():
        base = slow_base(texts[x.doc_id])
        assert x.base_sha256 == hashlib.sha256(secrets.joined(base).encode()).hexdigest()
        assert (x.n_assign, x.n_access, x.n_hex) == tuple(sum(s[2] == k for s in base) for k in secrets.KINDS[:3])


def test_licences_on_odd_inputs(spark):
    long = "word " * 200_000 + "\nReleased under the MIT License."
    rows = [("a/LICENSE", "Released under the MIT License."), ("a/COPYING", "Licensed under the Apache License, Version 2.0."), ("a/x", None), ("b/x", long), ("b/x", long), ("", ""), (None, None)]
    frame = spark.createDataFrame([(i, p, t, "mine", 1, 2) for i, (p, t) in enumerate(rows)] + [(None, "a/y", "", "mine", 1, 2)], "doc_id long, path string, text string, license string, dir int, count int")
    got = sorted(((r.doc_id, r.own_license, r.license, r.is_file) for r in licenses.scan(frame).collect()), key=str)
    by = {g[0]: g for g in got}
    # one vote each for the directory: the smaller name
    assert by[2][1:3] == (None, "Apache-2.0") and by[None][2] == "Apache-2.0"
    assert by[3][1:] == by[4][1:] == ("MIT", "MIT", False) and by[5][2] is None and by[6][2] is None
    assert len(got) == len(rows) + 1


def test_archives_with_clashing_names_and_long_pages(spark):
    body = "<p>" + "x" * 400
    rows = [(3, "u", body, "a", "b", 1, 2), (1, "u", body, "a", "b", 1, 2), (2, "u", "y" * 300_000, "a", "b", 1, 2), (None, "u", body, "a", "b", 1, 2)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, digest string, bytes string, salt int, refers_to int")
    got = {r.page_id: (r.record_type, r.refers_to, r.payload_bytes) for r in warc.round_trip(pages.where("page_id IS NOT NULL"), segment_bytes=5000).collect()}
    assert got == {1: ("response", None, 403), 3: ("revisit", 1, 403), 2: ("response", None, 300_000)}
