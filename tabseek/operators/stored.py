"""The stored index: postings as Parquet by slot of term, added to in versions (T2s).

A version is written once, in one pass over its texts, and holds the postings of
its own tables. Document frequencies and lengths add up over versions, so new
tables never rewrite old ones. A reader sees the versions committed when it
opens the index: one consistent set of N, document frequencies and lengths. A
version written again, as after a lost driver, replaces itself. ``compact`` puts
many versions into one, which replaces them in the same moment it is committed.

A version's slots and tasks follow the size of its texts. Rows of a slot are
dealt to several tasks by table, so that a term in most tables meets no single
task; the more tasks there are, the smaller each one's share of it. Every
document also has a row of the empty term, which carries its length; these rows
lie in a folder of their own and are dealt to all tasks.
"""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..functions.analysis import WORDS, Analyzer
from .search import Index, tokenised

#: Bytes of text a writing task takes, and the most slots of a version.
TASK_BYTES, MOST_SLOTS = 64 << 20, 4096
#: The slot of the empty term.
LENGTHS = -1


def slot_of(term: Column, slots: int) -> Column:
    return F.when(term == "", F.lit(LENGTHS)).otherwise(F.pmod(F.crc32(term.cast("binary")), F.lit(slots)).cast("int"))


def layout(n_bytes: int, task_bytes: int = TASK_BYTES) -> tuple[int, int]:
    """(slots, tasks) of a version of ``n_bytes`` of text: a slot for every four tasks, within bounds."""
    tasks = max(4, -(-n_bytes // task_bytes))
    return min(max(1, tasks // 4), MOST_SLOTS), tasks


def write_version(fields: DataFrame, path: str, version: int, analyzer: Analyzer = WORDS, slots: int | None = None) -> None:
    """Add ``fields`` (dataset, table_id, field, text) as one version; each table belongs to one version.

    No rows make an empty version. All fields of an index share the analyzer,
    whose id is stored with every version, as is its number of slots.
    """
    n_bytes = fields.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    chosen, tasks = layout(n_bytes)
    slots = slots or chosen
    tokens = tokenised(fields, analyzer)
    terms = F.explode(F.concat(F.coalesce("tokens", F.array().cast("array<string>")), F.array(F.lit("")))).alias("term")
    rows = tokens.select("dataset", "field", "table_id", F.greatest("dl", F.lit(0)).alias("dl"), terms)
    if analyzer.kind == "word":
        rows = analyzer.finish(rows)  # the empty term stays
    counted = rows.groupBy("dataset", "field", "term", "table_id", "dl").agg(F.count("*").alias("tf"))
    _store(counted, path, version, analyzer.id, slots, tasks)


def _store(counted: DataFrame, path: str, version: int, analyzer_id: str, slots: int, tasks: int, replaces: list[int] | None = None) -> None:
    """Write postings (dataset, field, term, table_id, dl, tf) as a version, its term counts, and at last its commit."""
    spark = counted.sparkSession
    placed = counted.withColumn("slot", slot_of(F.col("term"), slots))
    spread = max(1, -(-tasks // slots))
    deal = F.pmod(F.xxhash64("table_id"), F.when(F.col("slot") == LENGTHS, F.lit(tasks)).otherwise(F.lit(spread)))
    placed = placed.repartition(tasks, "dataset", "field", "slot", deal).sortWithinPartitions("dataset", "field", "slot", "term", "table_id")
    placed.write.mode("overwrite").partitionBy("dataset", "field", "slot").parquet(f"{path}/postings/version={version}")
    stored = _postings(spark, path, version)
    df = stored.groupBy("dataset", "field", "slot", "term").agg(F.count("*").alias("df"), F.sum("dl").alias("sum_len"))
    df.repartition(max(1, tasks // 4), "dataset", "field", "slot").write.mode("overwrite").partitionBy("dataset", "field", "slot").parquet(f"{path}/terms/version={version}")
    # written last: a version without it does not exist for readers
    commit = spark.range(1).select(F.lit(analyzer_id).alias("analyzer"), F.lit(slots).alias("slots"), F.array(*map(F.lit, replaces or [])).cast("array<long>").alias("replaces"))
    commit.coalesce(1).write.mode("overwrite").parquet(f"{path}/commits/version={version}")


def compact(spark: SparkSession, path: str, task_bytes: int = TASK_BYTES) -> int | None:
    """Put all versions that readers see into one new version and return its number; None if there is at most one.

    Readers that opened the index before keep reading the old files, which stay.
    """
    seen = _live(versions(spark, path).collect())
    if len(seen) < 2:
        return None
    old = [v.version for v in seen]
    rows = spark.read.schema(_LAYOUT + ", version long").parquet(f"{path}/postings").where(F.col("version").isin(old))
    slots, tasks = layout(rows.count() * 16, task_bytes)  # a posting is some sixteen bytes of text
    new = max(v.version for v in versions(spark, path).collect()) + 1
    _store(rows.select("dataset", "field", "term", "table_id", "dl", "tf"), path, new, seen[0].analyzer, slots, tasks, old)
    return new


def _live(known: list) -> list:
    """Of committed versions those that no other replaces."""
    gone = {r for v in known for r in (v.replaces or [])}
    return [v for v in known if v.version not in gone]


_LAYOUT = "dataset string, field string, slot int, term string, table_id long, dl long, tf long"
_TERMS = "dataset string, field string, slot int, term string, df long, sum_len long"


def _postings(spark: SparkSession, path: str, version: int) -> DataFrame:
    return spark.read.schema(_LAYOUT).parquet(f"{path}/postings/version={version}")


def versions(spark: SparkSession, path: str) -> DataFrame:
    """(version, analyzer, slots, replaces) of committed versions, one row each."""
    schema = "analyzer string, slots int, replaces array<long>, version long"
    try:
        return spark.read.schema(schema).parquet(f"{path}/commits")
    except AnalysisException as error:
        if error.getCondition() != "PATH_NOT_FOUND":
            raise
        return spark.createDataFrame([], schema)


def open_index(spark: SparkSession, path: str, terms: DataFrame | None = None, analyzer: Analyzer = WORDS, as_of: int | None = None) -> Index:
    """The index of all versions committed by now, or up to ``as_of``.

    With ``terms`` (dataset, term) only their slots and terms are read. What
    comes to the driver is a row per version and at most a number per slot.
    """
    committed = versions(spark, path)
    if as_of is not None:
        committed = committed.where(F.col("version") <= as_of)
    known = _live(committed.collect())
    wrong = {v.analyzer for v in known} - {analyzer.id}
    if wrong:
        raise ValueError(f"indexed by {sorted(wrong)}, not {analyzer.id}")
    if not known:
        return Index(spark.createDataFrame([], _LAYOUT), spark.createDataFrame([], _TERMS).drop("slot", "sum_len"), spark.createDataFrame([], "dataset string, field string, n_docs long, sum_len long"))
    seen = [v.version for v in known]
    chosen = F.col("version").isin(seen)
    postings = spark.read.schema(_LAYOUT + ", version long").parquet(f"{path}/postings").where(chosen & (F.col("slot") != LENGTHS))
    stats = spark.read.schema(_TERMS + ", version long").parquet(f"{path}/terms").where(chosen)
    lengths = stats.where(F.col("slot") == LENGTHS).groupBy("dataset", "field").agg(F.sum("df").alias("n_docs"), F.sum("sum_len").alias("sum_len"))
    if terms is not None:
        by_slots: dict[int, list[int]] = {}
        for v in known:
            by_slots.setdefault(v.slots, []).append(v.version)
        wanted = F.lit(False)
        for slots, own in by_slots.items():
            found = [r.slot for r in terms.select(slot_of(F.col("term"), slots).alias("slot")).distinct().collect()]
            wanted = wanted | (F.col("version").isin(own) & F.col("slot").isin(found))
        postings, stats = postings.where(wanted), stats.where(wanted)
    df = stats.where(F.col("slot") != LENGTHS).groupBy("dataset", "field", "term").agg(F.sum("df").alias("df"))
    return Index(postings.select("dataset", "field", "term", "table_id", "tf", "dl"), df, lengths)
