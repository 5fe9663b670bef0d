"""The corpus pipeline: its stages run one after another over ``documents``.

Each stage takes (spark, docs, sf_dir), works on all rows its predecessor kept
and returns a DataFrame, which is written as Parquet and reread as the next
one's ``docs``. All but the last return the columns of ``docs``.

Stages that run Python bound their Arrow batches by bytes; the setting stays on
the session, as their results are made when they are read.
"""

from __future__ import annotations

from tabseek.llm import jaccard_join, mixing, packing, secrets, toxicity
from tabseek.llm.store import discard, materialise, table
from tabseek.llm.workers import small_batches


def without_toxic(spark, docs, sf_dir):
    """Documents that the toxicity machine does not reject; it learns from the labelled ones among them."""
    small_batches(spark)
    return toxicity.keep_clean(docs, docs, table(spark, sf_dir, "labels"))


def without_near_copies(spark, docs, sf_dir):
    """One document of each group that the Jaccard join connects: that of the smallest id."""
    small_batches(spark)
    return jaccard_join.keep_one(docs)


def without_secrets(spark, docs, sf_dir):
    """All documents, with what the secret scan reports replaced by a mark."""
    small_batches(spark)
    return secrets.redact(docs)


def mixed(spark, docs, sf_dir):
    """Each document as often as its source's target weight asks."""
    return mixing.emit(docs)


def packed(spark, docs, sf_dir):
    """Pieces of all documents in near-equal windows."""
    small_batches(spark)
    return packing.pack(docs)


STAGES = [
    ("toxicity", without_toxic),
    ("n-gram Jaccard join", without_near_copies),
    ("secret scans", without_secrets),
    ("mixing sources to target weights", mixed),
    ("packing", packed),
]


def run(spark, sf_dir):
    """All stages over ``documents``; each reads what its predecessor wrote."""
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES[:-1]):
        kept = materialise(stage(spark, docs, sf_dir), name.replace(" ", "-"))
        if k:
            discard(docs)  # what the stage before wrote
        docs = kept
    return STAGES[-1][1](spark, docs, sf_dir)


#: Tokenising and the fitted scores have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None
