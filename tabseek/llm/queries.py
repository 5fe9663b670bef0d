"""The registered queries of this subpackage, each over its whole tables."""

from __future__ import annotations

from . import ann, jaccard_join, licenses, mixing, packing, quality, secrets, token_files, toxicity, warc
from .store import table


def op1_collision_neighbours(spark, sf_dir):
    vectors = table(spark, sf_dir, "embeddings")
    return ann.nearest(vectors, vectors.where("vec_id % 20 = 0"))


def op2_jaccard_join(spark, sf_dir):
    return jaccard_join.join(table(spark, sf_dir, "documents"))


def op3_pack_differencing(spark, sf_dir):
    return packing.pack(table(spark, sf_dir, "documents"))


def op4_license_scan(spark, sf_dir):
    return licenses.scan(licenses.document_paths(table(spark, sf_dir, "documents")))


def op5_mix_sources(spark, sf_dir):
    return mixing.report(table(spark, sf_dir, "documents"))


def op6_secret_scan(spark, sf_dir):
    return secrets.scan(table(spark, sf_dir, "documents"))


def op7_toxicity_machine(spark, sf_dir):
    return toxicity.report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_quality_ledger(spark, sf_dir):
    return quality.judge(table(spark, sf_dir, "documents"))


def op9_token_files(spark, sf_dir):
    return token_files.token_files(table(spark, sf_dir, "documents"))


def op10_warc_round_trip(spark, sf_dir):
    return warc.round_trip(table(spark, sf_dir, "pages"))


def queries():
    return {f.__name__: f for f in (op1_collision_neighbours, op2_jaccard_join, op3_pack_differencing, op4_license_scan, op5_mix_sources, op6_secret_scan, op7_toxicity_machine, op8_quality_ledger, op9_token_files, op10_warc_round_trip)}


def oracle_sql():
    return {"op4_license_scan": licenses.oracle(), "op5_mix_sources": mixing.ORACLE, "op8_quality_ledger": quality.ORACLE, "op10_warc_round_trip": warc.ORACLE}
