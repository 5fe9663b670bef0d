"""Registered queries of the remaining inventory rows: ranks of targets, parsing, exports, functions, joins and table functions, with their DuckDB oracles."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window, functions as F, types as T
from pyspark.sql.functions import udtf

from .functions import analysis
from .operators import benchmark, describe, evaluate, names, rank, search, stored, train
from .plans import datasets
from .plans.scratch import scratch
from .sources import catalogue
from .streaming import feedback, upkeep
from .workloads import _KNOWN_ALL, _SCI, _SCORED, _SYSTEMS, _catalogue_sql, _known, _pairs_sql, _scores, _sci, _score_sql, _sci_sql, _systems, _top, _w, _written, _bm25, _ent_fields, _ent_search, _log_likelihoods, _both_pairs
from .workloads_build import _texts


def idf(spark, sf_dir):
    """The weight of each document frequency that occurs."""
    index = _known(spark, sf_dir, terms_only=False)[1]
    n = index.field_stats.select("dataset", "n_docs")
    return index.term_stats.select("dataset", "df").distinct().join(F.broadcast(n), "dataset").select("df", F.round(search.idf(F.col("n_docs"), F.col("df")), 6).alias("idf"))


def stem_step1(spark, sf_dir):
    """Plural endings off: the first part of the stemmer's first step."""
    vocabulary = datasets.read(spark, sf_dir, "conversations").select(F.explode(analysis.words(F.col("text"))).alias("term")).distinct()
    return vocabulary.where(F.col("term").rlike("^[a-z]{3,}$")).select("term", analysis.step1a(F.col("term")).alias("stem"))


def tie_order(spark, sf_dir):
    """Tables of one score stand by ascending id."""
    data, fields = _ent_fields(spark, sf_dir)
    hits = search.single(data.queries, search.build_index(fields), "raw_names", k=10)
    ids = F.transform(F.array_sort(F.collect_list(F.struct("rank", "table_id"))), lambda x: x["table_id"].cast("string"))
    return hits.groupBy("query_id", "score").agg(F.array_join(ids, ",").alias("ids"))


def cand_scores(spark, sf_dir):
    return _scores(spark, sf_dir, "unified").select("table_id", "cand_id", "score", "n_queries")


def position_signal(spark, sf_dir):
    data, cands = _sci(spark, sf_dir)
    return rank.position(cands, data.queries, data.qrels).drop("dataset")


def pref_loss_beta(spark, sf_dir):
    rows = _log_likelihoods(spark, sf_dir)
    out = None
    for beta in (0.05, 0.1, 0.5, 1.0):
        part = train.preference_loss(rows, beta)
        out = part if out is None else out.unionByName(part)
    return out


def pair_export(spark, sf_dir):
    """Pairs written as JSON lines, one folder a fold, and read back."""
    path = scratch(spark, "pairs")
    train.export_jsonl(rank.folds(_both_pairs(spark, sf_dir), ["sci_s", "sci_l"]), path)
    back = spark.read.schema("prompt string, chosen string, rejected string, held_out string").json(path)
    return back.groupBy("held_out").agg(F.count("*").alias("n"), F.sum(F.length("chosen")).alias("chosen_chars"), F.sum(F.length("rejected")).alias("rejected_chars"), F.sum(F.length("prompt")).alias("prompt_chars"))


def mcb_descriptions(spark, sf_dir):
    """The multi-call baseline's descriptions, and their calls."""
    data = datasets.sci(spark, sf_dir)
    stats = data.tables.select("dataset", "table_id", F.concat(F.size("vis"), F.lit(" words")).alias("stats"))
    return describe.multicall(data.tables, stats).select("table_id", F.md5("body").alias("body_md5"), "n_calls")


def win_loss(spark, sf_dir):
    data, hits = _systems(spark, sf_dir)
    return evaluate.win_loss(benchmark.by_query(hits, data.qrels), "cand2", "cand0").drop("dataset")


def abbrev_rate(spark, sf_dir):
    return benchmark.abbrev_rate(datasets.ent(spark, sf_dir).tables)


def expansion_field(spark, sf_dir):
    data = datasets.ent(spark, sf_dir)
    columns, tables = names.expand(data.tables), names.expand(data.tables, "table")
    return names.expansion_field(tables.withColumn("pos", F.col("pos") - 1).unionByName(columns)).select("table_id", "text")


def parse_expansions(spark, sf_dir):
    """Model answers with reasoning before the final part, made of the lexicon's mappings, and parsed back."""
    expanded = names.expand(datasets.ent(spark, sf_dir).tables)
    line = F.concat(F.col("original"), F.lit(": "), F.array_join(F.transform("mapping", lambda m: F.concat(m["token"], F.lit(" → "), m["phrase"])), ", "))
    lines = F.transform(F.array_sort(F.collect_list(F.struct("pos", line.alias("l")))), lambda x: x["l"])
    answer = F.concat(F.lit("Reasoning: c → short, first letters name the table.\nFinal answer:\n"), F.array_join(lines, "\n"))
    answers = expanded.groupBy("dataset", "table_id").agg(answer.alias("answer"))
    return names.parse_answer(answers).select("table_id", "original", "expanded", F.size("mapping").cast("long").alias("n_tokens"))


def parse_descriptions(spark, sf_dir):
    doc = F.col("doc")
    concepts = F.transform(doc["concepts_and_synonyms"], lambda c: F.concat_ws("=", c["concept"], F.array_join(c["synonyms"], "+")))
    return _written(spark, sf_dir).select("table_id", "valid", F.array_join(doc["key_themes_or_topics"], " ").alias("themes"), F.array_join(concepts, " ").alias("concepts"), doc["additional_context"][0].alias("context"))


def grade_ntile(spark, sf_dir):
    """Quarters of each task's judged tables, best grades first."""
    best = Window.partitionBy("task").orderBy(F.desc("grade"), "table_id")
    return datasets.gov_judgements(spark, sf_dir).select("task", "table_id", F.ntile(4).over(best).alias("quarter"))


def math_fns(spark, sf_dir):
    price, size = F.col("p_retailprice"), F.col("p_size")
    return datasets.read(spark, sf_dir, "part").select("p_partkey", F.round(F.ln(price), 6).alias("ln"), F.round(F.log2(price), 6).alias("log2"), F.round(F.exp(-size / 10), 6).alias("fade"), F.greatest(size, F.lit(10)).alias("at_least"), F.round(F.sqrt(price), 6).alias("root"))


def string_fns(spark, sf_dir):
    """Each nation's name against the others of its region: edit distance of the nearest."""
    n = datasets.read(spark, sf_dir, "nation").select("n_nationkey", "n_name", "n_regionkey")
    other = n.select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("o"), "n_regionkey")
    return n.join(other, "n_regionkey").where("n_nationkey <> k").groupBy("n_nationkey", F.lower("n_name").alias("name"), F.substring("n_name", 1, 3).alias("head")).agg(F.min(F.levenshtein("n_name", "o")).alias("nearest"))


def date_fns(spark, sf_dir):
    at = F.col("o_orderdate")
    return datasets.read(spark, sf_dir, "orders").groupBy(F.date_format(F.date_trunc("month", at), "yyyy-MM-dd").alias("month")).agg(F.count("*").alias("n"), F.date_format(F.max(F.to_date(at)), "yyyy-MM-dd").alias("last"), F.count_distinct(F.dayofmonth(at)).alias("days"))


def array_fns(spark, sf_dir):
    w = analysis.words(F.col("text"))
    long = F.filter(F.array_distinct(w), lambda x: F.length(x) >= 6)
    return datasets.read(spark, sf_dir, "benchmark").select(
        "item_id",
        F.array_join(F.slice(F.array_sort(long), 1, 5), " ").alias("first_long"),
        F.aggregate(w, F.lit(0).cast("long"), lambda s, x: s + F.length(x)).alias("letters"),
        F.exists(w, lambda x: F.length(x) > 12).alias("has_very_long"),
        F.array_join(F.zip_with(F.slice(w, 1, 3), F.slice(w, 2, 3), lambda a, b: F.concat_ws("_", a, b)), " ").alias("pairs"),
    )


def tf_map(spark, sf_dir):
    """Term counts of each passage as a map; its entries by count."""
    counted = datasets.read(spark, sf_dir, "benchmark").select("item_id", F.explode(analysis.words(F.col("text"))).alias("term")).groupBy("item_id", "term").agg(F.count("*").alias("tf"))
    maps = counted.groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("term", "tf"))).alias("m"))
    entries = F.array_sort(F.transform(F.map_entries("m"), lambda e: F.struct((-e["value"]).alias("n"), e["key"].alias("term"))))
    return maps.select("item_id", F.size("m").cast("long").alias("n_terms"), F.array_join(F.transform(F.slice(entries, 1, 5), lambda e: F.concat_ws(":", e["term"], (-e["n"]).cast("string"))), " ").alias("top"))


def join_strategies(spark, sf_dir):
    """Postings with their document frequencies, joined in three ways."""
    index = _known(spark, sf_dir)[1]
    out = None
    for way in ("broadcast", "merge", "shuffle_hash"):
        joined = index.postings.join(index.term_stats.hint(way), ["dataset", "field", "term"])
        part = joined.agg(F.lit(way).alias("way"), F.count("*").alias("n"), F.sum(F.col("tf") * F.col("df")).alias("mass"))
        out = part if out is None else out.unionByName(part)
    return out


def catalog_tables(spark, sf_dir):
    return catalogue.tables(spark, sf_dir).select("table_name", "n_columns", F.array_join("columns", ",").alias("columns"))


@F.pandas_udf(T.DoubleType())
def ndcg_at_10(rank_: pd.Series, grade: pd.Series, ideal: pd.Series) -> float:
    """A query's gain in the top ten over the ideal; null ranks were not found."""
    import numpy as np

    seen = rank_.notna() & (rank_ <= 10)
    return float((grade[seen] / np.log2(rank_[seen].astype(float) + 1)).sum() / (grade[ideal <= 10] / np.log2(ideal[ideal <= 10] + 1)).sum())


def ndcg_udaf(spark, sf_dir):
    """NDCG of one system as a grouped aggregate function over judged tables."""
    data, hits = _systems(spark, sf_dir)
    judged = data.qrels.withColumn("ideal", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("grade"), "table_id")))
    rows = judged.join(hits.where("config = 'cand0'").select("query_id", "table_id", "rank"), ["query_id", "table_id"], "left")
    return rows.groupBy("query_id").agg(ndcg_at_10(F.col("rank"), F.col("grade"), F.col("ideal")).alias("v")).select("query_id", F.round("v", 6).alias("value"))


@udtf(returnType="query_id: long, table_id: long, score: double, place: int")
class SearchTables:
    """A table function over scored (query_id, table_id, score, k), dealt by query and sorted: the k best with their places."""

    def __init__(self):
        self._place = 0

    def eval(self, row):
        self._place += 1
        if self._place <= row["k"]:
            yield row["query_id"], row["table_id"], row["score"], self._place


def search_tables(spark, sf_dir):
    spark.udtf.register("search_tables", SearchTables)
    data, index = _known(spark, sf_dir)
    scored = search.field_scores(data.queries, index).select("query_id", "table_id", F.round("score", 6).alias("score")).where("score > 0").withColumn("k", F.lit(3))
    scored.createOrReplaceTempView("scored_tables")
    return spark.sql("SELECT query_id, table_id, score, place FROM search_tables(TABLE(scored_tables) PARTITION BY query_id ORDER BY (score DESC, table_id))")


def stream_index(spark, sf_dir):
    """Statistics of an index that grew from a stream of documents, one file a batch."""
    path = scratch(spark, "index")
    schema = datasets.read(spark, sf_dir, "documents").schema
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{sf_dir}/documents.parque[t]")
    texts = source.select(F.lit("known").alias("dataset"), F.col("doc_id").alias("table_id"), F.lit("text").alias("field"), "text")
    upkeep.index(texts, path, path + "-log").awaitTermination()
    return stored.open_index(spark, path).field_stats.select("field", "n_docs", "sum_len")


def stream_search(spark, sf_dir):
    """User turns as a stream of queries against a stored index."""
    path, out = scratch(spark, "index"), scratch(spark, "hits")
    stored.write_version(_texts(spark, sf_dir), path, 0)
    schema = datasets.read(spark, sf_dir, "conversations").schema
    turns = spark.readStream.schema(schema).parquet(f"{sf_dir}/conversations.parque[t]").where("role = 'user' AND turn = 0")
    upkeep.search(turns.select(F.lit("known").alias("dataset"), F.col("conv_id").cast("long").alias("query_id"), "text"), path, out, out + "-log", k=3).awaitTermination()
    return spark.read.schema("dataset string, query_id long, table_id long, score double, rank int").parquet(out).select("query_id", "table_id", "score", "rank")


def running_wins(spark, sf_dir):
    """Clicks and purchases of each item, counted in custom state over a stream of events."""
    out = scratch(spark, "wins")
    events = spark.readStream.schema(datasets.read(spark, sf_dir, "events").schema).parquet(f"{sf_dir}/events.parque[t]")
    write = lambda batch, n: batch.write.mode("overwrite").parquet(f"{out}/batch={n}")
    feedback.running_wins(events).writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", out + "-log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("item long, wins long").parquet(out).groupBy("item").agg(F.max("wins").alias("wins"))


_QUERIES = (
    idf, stem_step1, tie_order, cand_scores, position_signal, pref_loss_beta, pair_export, mcb_descriptions, win_loss, abbrev_rate, expansion_field,
    parse_expansions, parse_descriptions, grade_ntile, math_fns, string_fns, date_fns, array_fns, tf_map, join_strategies, catalog_tables, ndcg_udaf,
    search_tables, stream_index, stream_search, running_wins,
)


def queries():
    return {f.__name__: f for f in _QUERIES}


def oracle_sql():
    known = "WITH " + _KNOWN_ALL.lstrip()
    gov = "SELECT source AS task, d.doc_id AS table_id, CASE WHEN quality = 1 AND toxic = 0 THEN 3 WHEN quality = 1 THEN 2 ELSE 1 END AS grade FROM documents d JOIN labels l ON d.doc_id = l.doc_id WHERE source IN ('src0', 'src1', 'src2', 'src3', 'src4', 'src5')"
    softplus = lambda beta: f"SELECT {beta}::DOUBLE AS beta, round(avg(greatest(-x, 0.0) + ln(1 + exp(-abs(x)))), 6) AS loss FROM (SELECT {beta} * (margin - 0.1) AS x FROM p)"
    texts = "SELECT doc_id AS table_id, 'text' AS field, text FROM documents"
    passages = "SELECT item_id AS query_id, text FROM benchmark"
    export = lambda held, big: f"""SELECT '{held}' AS held_out, * FROM (WITH {_sci_sql(big)}, {_score_sql().lstrip()}, p AS ({_pairs_sql()})
        SELECT count(*) AS n, sum(length(a.body))::BIGINT AS chosen_chars, sum(length(b.body))::BIGINT AS rejected_chars, sum(length(array_to_string(firsts[1:12], ' ')))::BIGINT AS prompt_chars
        FROM p JOIN cands a ON a.table_id = p.table_id AND a.cand_id = win_cand JOIN cands b ON b.table_id = p.table_id AND b.cand_id = lose_cand JOIN tabs t ON t.table_id = p.table_id) WHERE n > 0"""  # noqa: E731
    by_query = """, i10 AS (SELECT query_id, sum(1 / log2(r + 1)) AS i FROM (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY table_id) AS r FROM qrels) WHERE r <= 10 GROUP BY query_id),
        g10 AS (SELECT config, query_id, sum(1 / log2(rank + 1)) AS d FROM hits JOIN qrels USING (query_id, table_id) WHERE rank <= 10 GROUP BY ALL),
        v10 AS (SELECT config, query_id, round(coalesce(d, 0) / i, 6) AS value FROM i10 CROSS JOIN configs LEFT JOIN g10 USING (config, query_id))"""
    strategies = " UNION ALL ".join(f"SELECT '{way}' AS way, count(*) AS n, sum(tf * df)::BIGINT AS mass FROM tf JOIN df USING (field, term)" for way in ("broadcast", "merge", "shuffle_hash"))
    catalogue_rows = ", ".join(f"('{t}', {len(c)}::BIGINT, '{','.join(c)}')" for t, c in datasets.CATALOGUE.items())
    return {
        "idf": known + " SELECT DISTINCT df, round(ln(1 + (n_docs - df + 0.5) / (df + 0.5)), 6) AS idf FROM df, stats",
        "stem_step1": f"""SELECT DISTINCT term, CASE WHEN ends_with(term, 'sses') OR ends_with(term, 'ies') THEN left(term, length(term) - 2) WHEN ends_with(term, 'ss') THEN term
            WHEN ends_with(term, 's') THEN left(term, length(term) - 1) ELSE term END AS stem FROM (SELECT unnest({_w('text')}) AS term FROM conversations) WHERE regexp_full_match(term, '[a-z]{{3,}}')""",
        "tie_order": f"SELECT query_id, score, string_agg(table_id::VARCHAR, ',' ORDER BY table_id) AS ids FROM ({_ent_search('raw_names')}) GROUP BY ALL",
        "cand_scores": _SCORED + " SELECT s.*, g.n_queries FROM scores s JOIN gold g ON s.table_id = g.table_id",
        "position_signal": _SCI + ", " + _score_sql(False).lstrip() + """,
            need AS (SELECT c.table_id, c.cand_id, q.query_id, a.text AS term, n0 AS n, (len0 - r_len + len(w)) / n0 AS avg, coalesce(df0, 0) - coalesce(in_r, 0) + CASE WHEN t.tf IS NULL THEN 0 ELSE 1 END AS df, coalesce(t.tf, 0) AS tf, len(w) AS dl
                FROM scores_tok c JOIN qrels q ON q.table_id = c.table_id JOIN asked a ON a.query_id = q.query_id JOIN scores_own o ON o.table_id = c.table_id
                LEFT JOIN scores_df d ON d.term = a.text LEFT JOIN scores_in i ON i.table_id = c.table_id AND i.term = a.text LEFT JOIN scores_tf t ON t.table_id = c.table_id AND t.cand_id = c.cand_id AND t.term = a.text, scores_base WHERE c.is_gold),
            mine AS (SELECT *, round(ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * dl / avg)), 6) AS own FROM need),
            ranked AS (SELECT m.table_id, m.cand_id, m.query_id, 1 + count(o.table_id) FILTER (score > own OR (score = own AND o.table_id < m.table_id)) AS place FROM mine m LEFT JOIN LATERAL (
                SELECT t.table_id, round(ln(1 + (m.n - m.df + 0.5) / (m.df + 0.5)) * t.tf * 2.2 / (t.tf + 1.2 * (0.25 + 0.75 * t.dl / m.avg)), 6) AS score FROM scores_tf t WHERE t.is_default AND t.term = m.term AND t.table_id <> m.table_id) o ON true GROUP BY ALL)
            SELECT table_id, cand_id, round(avg(place), 6) AS mean_rank FROM ranked GROUP BY ALL""",
        "pref_loss_beta": f"{_SCORED}, p AS ({_pairs_sql()}) " + " UNION ALL ".join(softplus(b) for b in (0.05, 0.1, 0.5, 1.0)),
        "pair_export": export("sci_s", True) + " UNION ALL " + export("sci_l", False),
        "mcb_descriptions": _SCI + """, counted AS (SELECT table_id, term, count(*) AS n FROM (SELECT table_id, unnest(vis) AS term FROM tabs) GROUP BY ALL),
            top_words AS (SELECT table_id, string_agg(term, ' ' ORDER BY n DESC, term) AS topics FROM (SELECT *, row_number() OVER (PARTITION BY table_id ORDER BY n DESC, term) AS r FROM counted) WHERE r <= 10 GROUP BY table_id)
            SELECT t.table_id, md5(concat_ws(' ', s.source, array_to_string(firsts[1:12], ' '), len(vis) || ' words', topics, array_to_string(vis[1:120], ' '))) AS body_md5, (3 + ceil(len(firsts[1:12]) / 10))::BIGINT AS n_calls
            FROM tabs t JOIN sci s ON s.table_id = t.table_id LEFT JOIN top_words p ON p.table_id = t.table_id""",
        "win_loss": _SYSTEMS + by_query + " SELECT sum((a.value > b.value)::INTEGER)::BIGINT AS wins, sum((a.value = b.value)::INTEGER)::BIGINT AS ties, sum((a.value < b.value)::INTEGER)::BIGINT AS losses FROM v10 a JOIN v10 b USING (query_id) WHERE a.config = 'cand2' AND b.config = 'cand0'",
        "abbrev_rate": f"""WITH {_catalogue_sql()} SELECT CASE WHEN pos < 0 THEN 'table' ELSE 'column' END AS kind, count(*) AS n_tokens, round(avg((coalesce(a.phrase, b.phrase, p.token) <> p.token)::INTEGER), 6) AS rate
            FROM pieces p LEFT JOIN lex a ON a.scope = p.base AND a.token = p.token LEFT JOIN lex b ON b.scope = '*' AND b.token = p.token GROUP BY ALL""",
        "expansion_field": f"WITH {_catalogue_sql()} SELECT table_id::BIGINT AS table_id, string_agg(expanded, ' ' ORDER BY pos) AS text FROM expanded GROUP BY table_id",
        "parse_expansions": f"WITH {_catalogue_sql()} SELECT table_id::BIGINT AS table_id, original, expanded, len({_split('original')})::BIGINT AS n_tokens FROM expanded WHERE pos >= 0",
        "parse_descriptions": _SCI + """ SELECT table_id, table_id % 7 <> 1 AS valid, CASE WHEN table_id % 7 <> 1 THEN array_to_string(firsts[1:3], ' ') END AS themes,
            CASE WHEN table_id % 7 <> 1 THEN firsts[1] || '=' || firsts[4] || ' ' || firsts[2] || '=' || firsts[5] || ' ' || firsts[3] || '=' || firsts[6] END AS concepts, CASE WHEN table_id % 7 <> 1 THEN 'unknown' END AS context FROM tabs WHERE len(firsts) >= 12""",
        "grade_ntile": f"SELECT task, table_id, (ntile(4) OVER (PARTITION BY task ORDER BY grade DESC, table_id))::INTEGER AS quarter FROM ({gov})",
        "math_fns": "SELECT p_partkey, round(ln(p_retailprice), 6) AS ln, round(log2(p_retailprice), 6) AS log2, round(exp(-p_size / 10), 6) AS fade, greatest(p_size, 10)::INTEGER AS at_least, round(sqrt(p_retailprice), 6) AS root FROM part",
        "string_fns": "SELECT a.n_nationkey, lower(a.n_name) AS name, a.n_name[1:3] AS head, min(levenshtein(a.n_name, b.n_name))::INTEGER AS nearest FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey <> b.n_nationkey GROUP BY ALL",
        "date_fns": "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, count(*) AS n, strftime(max(o_orderdate), '%Y-%m-%d') AS last, count(DISTINCT day(o_orderdate)) AS days FROM orders GROUP BY ALL",
        "array_fns": f"""SELECT item_id, array_to_string(list_sort(list_filter(list_distinct(w), lambda x: length(x) >= 6))[1:5], ' ') AS first_long, list_sum(list_transform(w, lambda x: length(x)))::BIGINT AS letters,
            len(list_filter(w, lambda x: length(x) > 12)) > 0 AS has_very_long, array_to_string(list_transform(range(1, 4), lambda i: concat_ws('_', w[i], w[i + 1])), ' ') AS pairs FROM (SELECT item_id, {_w('text')} AS w FROM benchmark)""",
        "tf_map": f"""WITH c AS (SELECT item_id, term, count(*) AS tf FROM (SELECT item_id, unnest({_w('text')}) AS term FROM benchmark) GROUP BY ALL), r AS (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY tf DESC, term) AS r FROM c)
            SELECT item_id, count(*) AS n_terms, string_agg(term || ':' || tf, ' ' ORDER BY r) FILTER (r <= 5) AS top FROM r GROUP BY item_id""",
        "join_strategies": "WITH " + _bm25(texts, passages).lstrip() + " " + strategies,
        "catalog_tables": f"SELECT * FROM (VALUES {catalogue_rows}) v(table_name, n_columns, columns)",
        "ndcg_udaf": _SYSTEMS + by_query + " SELECT query_id, value FROM v10 WHERE config = 'cand0'",
        "search_tables": "SELECT query_id, table_id, score, rank AS place FROM (WITH " + _bm25(texts, passages).lstrip() + " " + _top("sum(score)", 3) + ")",
        "stream_index": known + " SELECT field, n_docs, sum_len FROM stats",
        "stream_search": "WITH " + _bm25(texts, "SELECT conv_id::BIGINT AS query_id, text FROM conversations WHERE role = 'user' AND turn = 0").lstrip() + " " + _top("sum(score)", 3),
        "running_wins": "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS item, count(*) AS wins FROM events WHERE event_type IN ('click', 'purchase') GROUP BY ALL",
    }


def _split(name: str) -> str:
    from .workloads import _split_sql

    return _split_sql(name)
