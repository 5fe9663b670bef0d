"""Licence texts and headers of any length are compared."""

from __future__ import annotations

from pathlib import Path

from tabseek.llm import licenses


def test_long_texts_and_blocks_are_compared(spark):
    gpl = (Path(licenses.__file__).parent / "license_texts" / "GPL-3.0.txt").read_text()
    worded = "\n".join((gpl * 5).split())  # no line of it tells the licence
    header = next(text for name, text in licenses.HEADERS if name == "MPL-2.0").split()
    third = -(-len(header) // 3)
    framed = "\n".join("*" * 2_000 + " " + " ".join(header[i : i + third]) for i in range(0, len(header), third))
    assert len(worded) > 4 * max(len(t) for _, t in licenses.TEXTS) and len(framed) > 4_000
    frame = spark.createDataFrame([(1, "a/x.txt", worded), (2, "b/y.c", framed)], "doc_id long, path string, text string")
    got = {r.doc_id: r for r in licenses.own_licenses(frame).collect()}
    assert (got[1].own_license, got[1].is_file) == ("GPL-3.0", True) and got[1].own_score >= licenses.TEXT_SCORE
    assert got[2].own_license == "MPL-2.0" and got[2].own_score > 0.9
