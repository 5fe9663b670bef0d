"""Registered queries of benchmark construction, the stored index, streams and SQL surface, with their DuckDB oracles."""

from __future__ import annotations

from pyspark.sql import Window, functions as F
from pyspark.sql.functions import udtf

from .functions.analysis import words
from .operators import benchmark, search, stored
from .plans import datasets
from .plans.scratch import scratch
from .streaming import feedback, upkeep
from .workloads import _KNOWN, _KNOWN_ALL, _SCI_FIELDS, _SYSTEMS, _known, _sci_fields, _systems, _top, _w, oracle_sql as _search_oracles


def _texts(spark, sf_dir):
    return datasets.read(spark, sf_dir, "documents").select(F.lit("known").alias("dataset"), F.col("doc_id").alias("table_id"), F.lit("text").alias("field"), "text")


def _asked(spark, sf_dir):
    return datasets.read(spark, sf_dir, "benchmark").select(F.lit("known").alias("dataset"), F.col("item_id").alias("query_id"), "text")


def _hits(rows):
    return rows.select(F.col("query_id").alias("item_id"), F.col("table_id").alias("doc_id"), "score", "rank")


def stored_index_top10(spark, sf_dir):
    """The best ten of each passage from an index written in two versions and read by slots."""
    path, texts, asked = scratch(spark, "index"), _texts(spark, sf_dir), _asked(spark, sf_dir)
    for version, half in enumerate(("table_id % 2 = 0", "table_id % 2 = 1")):
        stored.write_version(texts.where(half), path, version)
    terms = search.query_terms(asked).select("dataset", "term").distinct()
    return _hits(search.single(asked, stored.open_index(spark, path, terms), k=10))


def stream_index_top10(spark, sf_dir):
    """The same from a stream of documents, then a stream of queries."""
    path, out = scratch(spark, "index"), scratch(spark, "hits")
    # a pattern may match one file or a folder; a plain path must be a folder
    source = lambda name: spark.readStream.schema(datasets.read(spark, sf_dir, name).schema).parquet(f"{sf_dir}/{name}.parque[t]")
    texts = source("documents").select(F.lit("known").alias("dataset"), F.col("doc_id").alias("table_id"), F.lit("text").alias("field"), "text")
    upkeep.index(texts, path, path + "-log").awaitTermination()
    asked = source("benchmark").select(F.lit("known").alias("dataset"), F.col("item_id").alias("query_id"), "text")
    upkeep.search(asked, path, out, out + "-log").awaitTermination()
    return _hits(spark.read.parquet(out))


def prune_queries(spark, sf_dir):
    data = datasets.known(spark, sf_dir)
    return benchmark.prune_queries(data.queries, data.qrels).select("query_id")


def distinct_queries(spark, sf_dir):
    """Four passages stand for a task; its two most distinct queries."""
    items = datasets.read(spark, sf_dir, "benchmark")
    return benchmark.distinct_pair(items.select(F.floor(F.col("item_id") / 4).cast("long").alias("task"), F.col("item_id").alias("query_id"), "text"))


def annotator_agg(spark, sf_dir):
    """Three invented annotators a judgement, then their median and largest grade."""
    judged = datasets.gov_judgements(spark, sf_dir).select(F.col("task").alias("query_id"), "table_id", "grade")
    votes = judged.withColumn("a", F.explode(F.sequence(F.lit(0), F.lit(2)))).withColumn("grade", ((F.col("grade") + F.col("a") * F.col("table_id")) % 4).cast("int"))
    median, largest = benchmark.aggregate_grades(votes), benchmark.aggregate_grades(votes, "max")
    return median.withColumnRenamed("grade", "median").join(largest.withColumnRenamed("grade", "largest"), ["query_id", "table_id"])


def pool_coverage(spark, sf_dir):
    data, index = _sci_fields(spark, sf_dir)
    runs = {f: search.single(data.queries, index, f, k=10) for f in ("description", "expansion", "context")}
    return benchmark.pool_coverage(benchmark.pool(runs, 10), data.qrels)


def sample_tables(spark, sf_dir):
    return benchmark.sample(datasets.read(spark, sf_dir, "documents").select("doc_id", "source"), 25, "doc_id")


def top_tables(spark, sf_dir):
    return benchmark.top_by(datasets.read(spark, sf_dir, "documents").select("doc_id", "n_chars"), "n_chars", 25, "doc_id")


def parseable(spark, sf_dir):
    return benchmark.parseable(datasets.read(spark, sf_dir, "events"), "props", "k LONG").groupBy("event_type").agg(F.count("*").alias("n"))


def query_ndcg(spark, sf_dir):
    data, hits = _systems(spark, sf_dir)
    return benchmark.by_query(hits, data.qrels).select("config", "query_id", "value")


def running_dcg(spark, sf_dir):
    """The gain gathered down each list of one system, rank by rank."""
    data, hits = _systems(spark, sf_dir)
    down = Window.partitionBy("query_id").orderBy("rank").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    marked = hits.where("config = 'cand0' AND rank <= 20").join(data.qrels.select("dataset", "query_id", "table_id", "grade"), ["dataset", "query_id", "table_id"], "left")
    return marked.select("query_id", "rank", F.round(F.sum(F.coalesce("grade", F.lit(0)) / F.log2(F.col("rank") + 1)).over(down), 6).alias("dcg"))


def top_terms(spark, sf_dir):
    index = _known(spark, sf_dir, terms_only=False)[1]
    return index.term_stats.orderBy(F.desc("df"), "term").limit(25).select("term", "df")


def distinct_terms(spark, sf_dir):
    docs = datasets.read(spark, sf_dir, "documents")
    return docs.select("source", F.explode(words(F.col("text"))).alias("term")).groupBy("source").agg(F.count_distinct("term").alias("n"))


def vocab_estimate(spark, sf_dir):
    """Vocabulary sizes by sketch: within a few percent of ``distinct_terms``."""
    docs = datasets.read(spark, sf_dir, "documents")
    return docs.select("source", F.explode(words(F.col("text"))).alias("term")).groupBy("source").agg(F.approx_count_distinct("term", 0.02).alias("n"))


def lang_filtered_search(spark, sf_dir):
    """Search of English documents only: the filter reaches the scan."""
    docs = datasets.read(spark, sf_dir, "documents").where("lang = 'en'")
    fields = docs.select(F.lit("known").alias("dataset"), F.col("doc_id").alias("table_id"), F.lit("text").alias("field"), "text")
    asked = _asked(spark, sf_dir)
    terms = search.query_terms(asked).select("dataset", "term").distinct()
    return search.single(asked, search.build_index(fields, terms=terms), k=5).drop("dataset")


def queries_in_window(spark, sf_dir):
    """Events of a user in the hour before each of the user's purchases, counted without pairs."""
    events = datasets.read(spark, sf_dir, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3_600_000_000, 0)
    return events.withColumn("n", F.count("*").over(hour)).where("event_type = 'purchase'").select("event_id", "n")


def json_props(spark, sf_dir):
    k = F.from_json("props", "k LONG")["k"]
    return datasets.read(spark, sf_dir, "events").groupBy(k.alias("k")).agg(F.count("*").alias("n"))


def rank_functions(spark, sf_dir):
    """Documents by length within a source: rank, dense rank, quarter and the next longer one."""
    order = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    tied = Window.partitionBy("source").orderBy(F.desc("n_chars"))
    docs = datasets.read(spark, sf_dir, "documents").select("doc_id", "source", "n_chars")
    return docs.select("doc_id", F.rank().over(tied).alias("r"), F.dense_rank().over(tied).alias("d"), F.ntile(4).over(order).alias("q"), F.coalesce(F.lag("n_chars").over(order), F.lit(0)).alias("longer"))


@udtf(returnType="pos: int, term: string")
class Tokenize:
    """A table function: the words of a text and their places."""

    def eval(self, text: str):
        import re

        for pos, term in enumerate(re.findall("[0-9a-zà-öø-ÿß]+", (text or "").lower())):
            yield pos, term


def udtf_tokenize(spark, sf_dir):
    spark.udtf.register("tokenize", Tokenize)
    return spark.sql("SELECT b.item_id, t.pos, t.term FROM {items} b, LATERAL tokenize(b.text) t", items=datasets.read(spark, sf_dir, "benchmark"))


def sql_bm25(spark, sf_dir):
    """Document frequencies and weights of query terms in plain SQL with parameters."""
    return spark.sql(
        """WITH posted AS (SELECT term, table_id FROM {postings} GROUP BY term, table_id)
        SELECT term, count(*) AS df, round(ln(1 + (:n - count(*) + 0.5) / (count(*) + 0.5)), 6) AS idf FROM posted GROUP BY term""",
        args={"n": datasets.read(spark, sf_dir, "documents").count()},
        postings=_known(spark, sf_dir)[1].postings,
    )


def daily_wins(spark, sf_dir):
    rows = feedback.daily_wins(datasets.read(spark, sf_dir, "events"))
    return rows.withColumn("start", F.date_format("start", "yyyy-MM-dd"))


_QUERIES = (
    stored_index_top10, stream_index_top10, prune_queries, distinct_queries, annotator_agg, pool_coverage, sample_tables,
    top_tables, parseable, query_ndcg, running_dcg, top_terms, distinct_terms, vocab_estimate, lang_filtered_search,
    queries_in_window, json_props, rank_functions, udtf_tokenize, sql_bm25, daily_wins,
)


def queries():
    return {f.__name__: f for f in _QUERIES}


def oracle_sql():
    search_sql = _search_oracles()
    known = "WITH " + _KNOWN.lstrip()
    english = known.replace("FROM documents", "FROM documents WHERE lang = 'en'")
    gov = "SELECT source AS query_id, d.doc_id AS table_id, CASE WHEN quality = 1 AND toxic = 0 THEN 3 WHEN quality = 1 THEN 2 ELSE 1 END AS grade FROM documents d JOIN labels l ON d.doc_id = l.doc_id WHERE source IN ('src0', 'src1', 'src2', 'src3', 'src4', 'src5')"
    pooled = " UNION ALL ".join(f"SELECT '{f}' AS run, query_id, table_id FROM ({_top('score', 10, f'field = {f!r}').replace('GROUP BY query_id, table_id', '')})" for f in ("description", "expansion", "context"))
    return {
        "stored_index_top10": search_sql["bm25_top10"],
        "stream_index_top10": search_sql["bm25_top10"],
        "prune_queries": "SELECT item_id AS query_id FROM benchmark b WHERE EXISTS (SELECT 1 FROM documents d WHERE contains(d.text, b.text[1:60]))",
        "distinct_queries": f"""WITH s AS (SELECT item_id // 4 AS task, item_id, list_distinct({_w('text')}) AS w FROM benchmark),
            p AS (SELECT a.task, a.item_id AS query_id, b.item_id AS other_id, round(CASE WHEN len(list_distinct(list_concat(a.w, b.w))) > 0 THEN len(list_intersect(a.w, b.w)) / len(list_distinct(list_concat(a.w, b.w))) ELSE 1 END, 6) AS jaccard
                  FROM s a JOIN s b ON a.task = b.task AND a.item_id < b.item_id)
            SELECT task, query_id, other_id, jaccard FROM (SELECT *, row_number() OVER (PARTITION BY task ORDER BY jaccard, query_id, other_id) AS r FROM p) WHERE r = 1""",
        "annotator_agg": f"""SELECT query_id, table_id, quantile_disc(g, 0.5)::INTEGER AS median, max(g)::INTEGER AS largest
            FROM (SELECT query_id, table_id, (grade + a * table_id) % 4 AS g FROM ({gov}), range(3) r(a)) GROUP BY ALL""",
        "pool_coverage": _SCI_FIELDS + f""", pooled AS ({pooled}), found AS (SELECT * FROM pooled SEMI JOIN qrels USING (query_id, table_id)), c AS (SELECT query_id, table_id, count(*) AS m FROM found GROUP BY ALL)
            SELECT run, count(*) AS n_gold, count(*) FILTER (m = 1) AS n_only FROM found JOIN c USING (query_id, table_id) GROUP BY run""",
        "sample_tables": "SELECT doc_id, source FROM documents ORDER BY md5('42:' || doc_id), doc_id LIMIT 25",
        "top_tables": "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC NULLS LAST, doc_id LIMIT 25",
        "parseable": "SELECT event_type, count(*) AS n FROM events WHERE json_valid(props) GROUP BY event_type",
        "query_ndcg": _SYSTEMS + """, i10 AS (SELECT query_id, sum(1 / log2(r + 1)) AS i FROM (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY table_id) AS r FROM qrels) WHERE r <= 10 GROUP BY query_id),
            g10 AS (SELECT config, query_id, sum(1 / log2(rank + 1)) AS d FROM hits JOIN qrels USING (query_id, table_id) WHERE rank <= 10 GROUP BY ALL)
            SELECT config, query_id, round(coalesce(d, 0) / i, 6) AS value FROM i10 CROSS JOIN configs LEFT JOIN g10 USING (config, query_id)""",
        "running_dcg": _SYSTEMS + """ SELECT query_id, rank::INTEGER AS rank, round(sum(coalesce(grade, 0) / log2(rank + 1)) OVER (PARTITION BY query_id ORDER BY rank), 6) AS dcg
            FROM hits LEFT JOIN qrels USING (query_id, table_id) WHERE config = 'cand0' AND rank <= 20""",
        "top_terms": "WITH " + _KNOWN_ALL.lstrip() + " SELECT term, df FROM df ORDER BY df DESC, term LIMIT 25",
        "distinct_terms": f"SELECT source, count(DISTINCT term) AS n FROM (SELECT source, unnest({_w('text')}) AS term FROM documents) GROUP BY source",
        "lang_filtered_search": english + " " + _top("score", 5).replace("GROUP BY query_id, table_id", ""),
        "queries_in_window": "SELECT event_id, n FROM (SELECT *, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events) WHERE event_type = 'purchase'",
        "daily_wins": """SELECT strftime(ts, '%Y-%m-%d') AS start, CAST(json_extract_string(props, '$.k') AS BIGINT) AS item, count(*) FILTER (event_type = 'view') AS views,
            count(*) FILTER (event_type IN ('click', 'purchase')) AS wins FROM events GROUP BY ALL""",
        "json_props": "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY ALL",
        "rank_functions": """SELECT doc_id, (rank() OVER t)::INTEGER AS r, (dense_rank() OVER t)::INTEGER AS d, (ntile(4) OVER o)::INTEGER AS q, coalesce(lag(n_chars) OVER o, 0) AS longer
            FROM documents WINDOW t AS (PARTITION BY source ORDER BY n_chars DESC NULLS LAST), o AS (PARTITION BY source ORDER BY n_chars DESC NULLS LAST, doc_id)""",
        "udtf_tokenize": f"SELECT item_id, (unnest(range(1, len(w) + 1)) - 1)::INTEGER AS pos, unnest(w) AS term FROM (SELECT item_id, {_w('text')} AS w FROM benchmark)",
        "sql_bm25": known + " SELECT term, df, round(ln(1 + (n_docs - df + 0.5) / (df + 0.5)), 6) AS idf FROM df JOIN stats USING (field)",
    }
