"""Streams against the stored index: tables that arrive, and queries (T1s, T2s)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.streaming import StreamingQuery

from ..functions.analysis import WORDS, Analyzer
from ..operators.search import Run, query_terms, runs_top_k
from ..operators.stored import open_index, write_version


def index(fields: DataFrame, path: str, checkpoint: str, analyzer: Analyzer = WORDS) -> StreamingQuery:
    """Each micro-batch of ``fields`` (dataset, table_id, field, text) becomes the version of its number.

    A batch that runs again replaces its own version, so each table counts once.
    """

    def add(batch: DataFrame, number: int) -> None:
        write_version(batch, path, number, analyzer)

    return fields.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def search(queries: DataFrame, path: str, out: str, checkpoint: str, field: str = "text", k: int = 10, analyzer: Analyzer = WORDS) -> StreamingQuery:
    """The best ``k`` of each arriving query (dataset, query_id, text), below ``out``/batch=number.

    A batch opens the index once: all its queries see the same versions.
    """

    def answer(batch: DataFrame, number: int) -> None:
        batch = batch.persist()
        terms = query_terms(batch, analyzer).select("dataset", "term").distinct()
        index = open_index(batch.sparkSession, path, terms, analyzer)
        index.analyzers = {field: analyzer}
        hits = runs_top_k(batch, index, {"": Run((field,))}, k).select("dataset", "query_id", "table_id", "score", "rank")
        hits.write.mode("overwrite").parquet(f"{out}/batch={number}")
        batch.unpersist()

    return queries.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
