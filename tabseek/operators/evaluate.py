"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

KS = (5, 10, 20, 50, 100)


def _gain(grade: Column, gain: str) -> Column:
    return grade.cast("double") if gain == "linear" else F.pow(F.lit(2.0), grade) - 1


def ndcg(hits: DataFrame, qrels: DataFrame, ks=KS, gain: str = "linear") -> DataFrame:
    """(dataset, config, k, value): mean over judged queries; one join and one aggregation for all k.

    ``hits`` (dataset, config, query_id, table_id, rank). A query without hits
    counts with 0; the ideal list is that of all judged tables.
    """
    judged = qrels.where("grade > 0")
    by_grade = Window.partitionBy("dataset", "query_id").orderBy(F.desc("grade"), "table_id")
    ranked = judged.withColumn("r", F.row_number().over(by_grade))
    part = lambda k, rank: F.sum(F.when(F.col(rank) <= k, _gain(F.col("grade"), gain) / F.log2(F.col(rank) + 1)))
    ideal = ranked.groupBy("dataset", "query_id").agg(*[part(k, "r").alias(f"i{k}") for k in ks])
    got = hits.join(judged, ["dataset", "query_id", "table_id"]).groupBy("dataset", "config", "query_id").agg(*[part(k, "rank").alias(f"d{k}") for k in ks])
    configs = hits.select("dataset", "config").distinct()
    rows = ideal.join(configs, "dataset").join(got, ["dataset", "config", "query_id"], "left")
    means = rows.groupBy("dataset", "config").agg(*[F.round(F.avg(F.coalesce(F.col(f"d{k}"), F.lit(0.0)) / F.col(f"i{k}")), 6).alias(f"v{k}") for k in ks])
    return _long(means, ks)


def recall(hits: DataFrame, qrels: DataFrame, ks=KS) -> DataFrame:
    """(dataset, config, k, value): relevant in the top k of all relevant, mean over judged queries."""
    judged = qrels.where("grade > 0").select("dataset", "query_id", "table_id").distinct()
    total = judged.groupBy("dataset", "query_id").agg(F.count("*").alias("n"))
    got = hits.join(judged, ["dataset", "query_id", "table_id"]).groupBy("dataset", "config", "query_id").agg(*[F.sum((F.col("rank") <= k).cast("int")).alias(f"c{k}") for k in ks])
    rows = total.join(hits.select("dataset", "config").distinct(), "dataset").join(got, ["dataset", "config", "query_id"], "left")
    means = rows.groupBy("dataset", "config").agg(*[F.round(F.avg(F.coalesce(F.col(f"c{k}"), F.lit(0)) / F.col("n")), 6).alias(f"v{k}") for k in ks])
    return _long(means, ks)


def _long(wide: DataFrame, ks) -> DataFrame:
    rows = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"v{k}").alias("value")) for k in ks])).alias("m")
    return wide.select("dataset", "config", rows).select("dataset", "config", "m.k", "m.value")


def relative(metrics: DataFrame, base: str) -> DataFrame:
    """Gain in percent of each configuration over ``base``."""
    against = metrics.where(F.col("config") == base).select("dataset", "k", F.col("value").alias("base"))
    return metrics.where(F.col("config") != base).join(against, ["dataset", "k"]).select("dataset", "config", "k", F.round((F.col("value") / F.when(F.col("base") > 0, F.col("base")) - 1) * 100, 4).alias("gain"))


def best(metrics: DataFrame) -> DataFrame:
    """The best configurations of each dataset and k; ties all."""
    rank = F.rank().over(Window.partitionBy("dataset", "k").orderBy(F.desc("value")))
    return metrics.withColumn("r", rank).where("r = 1").drop("r")


def win_loss(metrics_by_query: DataFrame, a: str, b: str) -> DataFrame:
    """Queries won, tied and lost by ``a`` against ``b`` from (dataset, config, query_id, value)."""
    x = metrics_by_query.where(F.col("config") == a).select("dataset", "query_id", F.col("value").alias("x"))
    y = metrics_by_query.where(F.col("config") == b).select("dataset", "query_id", F.col("value").alias("y"))
    d = x.join(y, ["dataset", "query_id"])
    count = lambda c: F.sum(c.cast("int")).alias
    return d.groupBy("dataset").agg(count(F.col("x") > F.col("y"))("wins"), count(F.col("x") == F.col("y"))("ties"), count(F.col("x") < F.col("y"))("losses"))


def length(descriptions: DataFrame, tokens) -> DataFrame:
    """(system, n_tables, avg_words, avg_chars) of (system, body)."""
    return descriptions.groupBy("system").agg(F.count("*").alias("n_tables"), F.round(F.avg(F.size(tokens(F.col("body")))), 4).alias("avg_words"), F.round(F.avg(F.length("body")), 4).alias("avg_chars"))


def density(qrels: DataFrame, tables: DataFrame) -> DataFrame:
    """Relevant tables a query, over all tables."""
    n = tables.groupBy("dataset").agg(F.count("*").alias("n_tables"))
    per = qrels.where("grade > 0").groupBy("dataset", "query_id").agg(F.count("*").alias("g"))
    return per.join(n, "dataset").groupBy("dataset").agg(F.count("*").alias("n_queries"), F.round(F.avg(F.col("g") / F.col("n_tables")), 6).alias("density"))


def summary(tables: DataFrame, queries: DataFrame, qrels: DataFrame) -> DataFrame:
    """(dataset, n_tables, n_queries, n_gold)."""
    gold = qrels.where("grade > 0").groupBy("dataset").agg(F.count_distinct("table_id").alias("n_gold"))
    return tables.groupBy("dataset").agg(F.count("*").alias("n_tables")).join(queries.groupBy("dataset").agg(F.count("*").alias("n_queries")), "dataset", "left").join(gold, "dataset", "left").na.fill(0)


def index_cost(n_gold: Column, n_docs: Column, k: int = 3) -> list[Column]:
    """Documents indexed by one corpus a candidate, one a table, and one in all."""
    return [(k * n_gold * n_docs).alias("docs_individual"), (n_gold * (n_docs + k - 1)).alias("docs_unified"), (n_docs + (k - 1) * n_gold).alias("docs_shared")]
