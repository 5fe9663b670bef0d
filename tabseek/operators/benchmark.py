"""Building a labelled benchmark: pruning, relabelling, pooling, sampling."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions.analysis import words
from .names import expand
from .search import Index, weighted


def prune_queries(queries: DataFrame, qrels: DataFrame) -> DataFrame:
    """Queries with a confirmed positive."""
    return queries.join(qrels.where("grade > 0"), ["dataset", "query_id"], "left_semi")


def relabel(qrels: DataFrame, verdicts: DataFrame) -> DataFrame:
    """``qrels`` (task, table_id, grade) with a verdict (task, table_id, verdict) in place of grades of 2 and more; others stay."""
    joined = qrels.join(verdicts, ["task", "table_id"], "left")
    return joined.withColumn("grade", F.when(F.col("grade") >= 2, F.coalesce("verdict", "grade")).otherwise(F.col("grade"))).drop("verdict")


def distinct_pair(queries: DataFrame) -> DataFrame:
    """Per task (task, query_id, text) the two queries that share the smallest part of their words.

    Tasks hold a handful of queries each, so pairs are few; ties go to smaller ids.
    """
    sets = queries.select("task", "query_id", F.array_distinct(words(F.col("text"))).alias("w"))
    other = sets.select("task", F.col("query_id").alias("other_id"), F.col("w").alias("v"))
    union = F.size(F.array_union("w", "v"))
    near = F.when(union > 0, F.size(F.array_intersect("w", "v")) / union).otherwise(F.lit(1.0))
    pairs = sets.join(other, "task").where("query_id < other_id").select("task", "query_id", "other_id", F.round(near, 6).alias("jaccard"))
    least = F.min(F.struct("jaccard", "query_id", "other_id")).alias("p")
    return pairs.groupBy("task").agg(least).select("task", "p.query_id", "p.other_id", "p.jaccard")


def task_to_query(judged: DataFrame, queries: DataFrame) -> DataFrame:
    """Judgements of a task (task, table_id, grade) for each of its queries (task, query_id)."""
    return judged.join(queries.select("task", "query_id"), "task").select("query_id", "table_id", "grade")


def aggregate_grades(votes: DataFrame, how: str = "median") -> DataFrame:
    """One grade a pair from many annotators' (query_id, table_id, grade): median (lower of two), or max."""
    value = F.max("grade") if how == "max" else F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY grade)")
    return votes.groupBy("query_id", "table_id").agg(value.cast("int").alias("grade"))


def pool(runs: dict[str, DataFrame], depth: int) -> DataFrame:
    """(query_id, table_id, runs): every table that some run has within ``depth``, and which runs."""
    parts = [hits.where(F.col("rank") <= depth).select("query_id", "table_id", F.lit(name).alias("run")) for name, hits in runs.items()]
    return reduce(DataFrame.unionByName, parts).groupBy("query_id", "table_id").agg(F.array_sort(F.collect_set("run")).alias("runs"))


def pool_coverage(pooled: DataFrame, qrels: DataFrame) -> DataFrame:
    """(run, n_gold, n_only): judged positives a run finds, and those no other run finds."""
    found = pooled.join(qrels.where("grade > 0").select("query_id", "table_id").distinct(), ["query_id", "table_id"], "left_semi")
    alone = F.sum((F.size("runs") == 1).cast("int")).alias("n_only")
    return found.select("runs", F.explode("runs").alias("run")).groupBy("run").agg(F.count("*").alias("n_gold"), alone)


def sample(tables: DataFrame, n: int, key: str = "table_id", seed: int = 42) -> DataFrame:
    """``n`` tables by hash order: the same on every run and layout."""
    return tables.withColumn("_h", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col(key).cast("string")))).orderBy("_h", key).limit(n).drop("_h")


def top_by(tables: DataFrame, column: str, n: int, key: str = "table_id") -> DataFrame:
    """The ``n`` tables of the largest ``column``, ties to smaller keys."""
    return tables.orderBy(F.desc_nulls_last(column), key).limit(n)


def parseable(rows: DataFrame, column: str, schema: str) -> DataFrame:
    """Rows whose JSON in ``column`` can be read by ``schema``."""
    return rows.where(F.from_json(column, schema).isNotNull() & F.get_json_object(column, "$").isNotNull())


def downsample(queries: DataFrame, index: Index, qrels: DataFrame, weights: dict[str, float], n: int = 50) -> DataFrame:
    """(dataset, table_id): the ``n`` best tables of each query over the weighted fields, each by its own analyzer, and every judged positive."""
    top = weighted(queries, index, weights, k=n).select("dataset", "table_id")
    return top.union(qrels.where("grade > 0").select("dataset", "table_id")).distinct()


def abbrev_rate(tables: DataFrame) -> DataFrame:
    """(kind, n_tokens, rate): the share of tokens in column and table names that stand for something longer."""
    out = None
    for kind in ("column", "table"):
        expanded = expand(tables, "columns" if kind == "column" else "table")
        tokens = expanded.select(F.explode("mapping").alias("m")).select((F.col("m.token") != F.col("m.phrase")).cast("int").alias("short"))
        part = tokens.agg(F.lit(kind).alias("kind"), F.count("*").alias("n_tokens"), F.round(F.avg("short"), 6).alias("rate"))
        out = part if out is None else out.unionByName(part)
    return out


def _weight(query_id: Column, round_no: Column) -> Column:
    """How often a query stands in a resample: 0 to 4 by hash, as often as a rate of 1 asks."""
    u = F.pmod(F.xxhash64(query_id, round_no), F.lit(1_000_000)) / 1_000_000
    cut = [0.367879, 0.735759, 0.919699, 0.981012]  # fixed values: running sums of 1/e, 1/e, 1/(2e), 1/(6e)
    return sum(((u >= c).cast("int") for c in cut), F.lit(0))


def bootstrap(by_query: DataFrame, a: str, b: str, rounds: int = 200) -> DataFrame:
    """(dataset, low, high): the middle 95 % of resampled mean differences of ``a`` over ``b`` from (dataset, config, query_id, value)."""
    both = by_query.where(F.col("config").isin(a, b)).groupBy("dataset", "query_id").agg(F.sum(F.when(F.col("config") == a, F.col("value")).otherwise(-F.col("value"))).alias("d"), F.count("*").alias("n")).where("n = 2")
    drawn = both.withColumn("round", F.explode(F.sequence(F.lit(1), F.lit(rounds)))).withColumn("w", _weight(F.col("query_id"), F.col("round")))
    means = drawn.where("w > 0").groupBy("dataset", "round").agg((F.sum(F.col("w") * F.col("d")) / F.sum("w")).alias("mean"))
    return means.groupBy("dataset").agg(F.round(F.percentile("mean", 0.025), 6).alias("low"), F.round(F.percentile("mean", 0.975), 6).alias("high"))


def by_query(hits: DataFrame, qrels: DataFrame, k: int = 10, configs: tuple[str, ...] = ()) -> DataFrame:
    """(dataset, config, query_id, value): each judged query's NDCG at ``k``, 0 without hits; of ``configs`` also where one has no hits on a whole dataset."""
    judged = qrels.where("grade > 0")
    gain = F.col("grade") / F.log2(F.col("rank") + 1)
    ideal = judged.withColumn("rank", F.row_number().over(Window.partitionBy("dataset", "query_id").orderBy(F.desc("grade"), "table_id"))).where(F.col("rank") <= k).groupBy("dataset", "query_id").agg(F.sum(gain).alias("i"))
    got = hits.where(F.col("rank") <= k).join(judged, ["dataset", "query_id", "table_id"]).groupBy("dataset", "config", "query_id").agg(F.sum(gain).alias("d"))
    if configs:
        every = ideal.withColumn("config", F.explode(F.array(*map(F.lit, configs))))
    else:
        every = ideal.join(hits.select("dataset", "config").distinct(), "dataset")
    return every.join(got, ["dataset", "config", "query_id"], "left").select("dataset", "config", "query_id", F.round(F.coalesce("d", F.lit(0.0)) / F.col("i"), 6).alias("value"))
