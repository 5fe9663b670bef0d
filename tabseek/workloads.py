"""Registered queries of the table-search methods and their DuckDB oracles."""

from __future__ import annotations

from pyspark.sql import Window, functions as F

from .functions import analysis
from .operators import benchmark, describe, evaluate, names, rank, search, train
from .plans import datasets
from .plans.scratch import materialise
from .sources import pages as page_source
from .streaming import feedback

WORDS_SQL = "regexp_extract_all(lower(coalesce({}, '')), '[0-9a-zà-öø-ÿß]+')"
KS = (5, 10, 20)


def _w(text: str) -> str:
    return WORDS_SQL.format(text)


# --- shared plans ---------------------------------------------------------------


def _known(spark, sf_dir, terms_only=True):
    data = datasets.known(spark, sf_dir)
    terms = search.query_terms(data.queries).select("dataset", "term").distinct() if terms_only else None
    return data, search.build_index(data.tables, terms=terms)


def _sci(spark, sf_dir, k=3, large=True):
    data = datasets.sci(spark, sf_dir, large)
    return data, rank.candidates(data.tables, data.qrels, k)


def _ent_fields(spark, sf_dir):
    """Names as they are, and their expansions, as two fields."""
    data = datasets.ent(spark, sf_dir)
    raw = data.tables.select("dataset", "table_id", F.lit("raw_names").alias("field"), F.concat_ws(" ", "table_name", F.array_join("columns", " ")).alias("text"))
    columns, tables = names.expand(data.tables), names.expand(data.tables, "table")
    both = tables.withColumn("pos", F.col("pos") - 1).unionByName(columns)
    expansion = names.expansion_field(both).withColumn("field", F.lit("expansion")).select("dataset", "table_id", "field", "text")
    return data, raw.unionByName(expansion)


def _sci_fields(spark, sf_dir):
    """Description, expansion and context of the larger topic dataset."""
    data, cands = _sci(spark, sf_dir, 1)
    description = cands.select("dataset", "table_id", F.lit("description").alias("field"), F.col("body").alias("text"))
    part = lambda name, col: data.tables.select("dataset", "table_id", F.lit(name).alias("field"), col.alias("text"))
    fields = description.unionByName(part("expansion", F.array_join("columns", " "))).unionByName(part("context", F.array_join(F.slice("vis", 41, 80), " ")))
    return data, search.build_index(fields, terms=search.query_terms(data.queries).select("dataset", "term").distinct())


def _systems(spark, sf_dir):
    """Hits of three description systems over the larger topic dataset."""
    data = datasets.sci(spark, sf_dir)
    bodies = data.tables.select("dataset", "table_id", F.posexplode(rank.template_bodies(3)).alias("cand", "text")).withColumn("field", F.concat(F.lit("cand"), "cand"))
    index = search.build_index(bodies.select("dataset", "table_id", "field", "text"), terms=search.query_terms(data.queries).select("dataset", "term").distinct())
    scores = search.field_scores(data.queries, index, [f"cand{i}" for i in range(3)]).withColumn("score", F.round("score", 6)).where("score > 0")
    best = Window.partitionBy("dataset", "field", "query_id").orderBy(F.desc("score"), "table_id")
    hits = scores.withColumn("rank", F.row_number().over(best)).where("rank <= 100").select("dataset", F.col("field").alias("config"), "query_id", "table_id", "rank")
    return data, hits


# --- queries --------------------------------------------------------------------


def analyze_words(spark, sf_dir):
    return datasets.read(spark, sf_dir, "documents").select("doc_id", F.size(analysis.words(F.col("text"))).cast("long").alias("n"), F.size(F.array_distinct(analysis.words(F.col("text")))).cast("long").alias("n_distinct"))


def analyze_trigrams(spark, sf_dir):
    return datasets.read(spark, sf_dir, "benchmark").select("item_id", F.array_join(analysis.trigrams(F.col("text")), " ").alias("grams"))


def stem_vocab(spark, sf_dir):
    vocabulary = datasets.read(spark, sf_dir, "conversations").select(F.explode(analysis.words(F.col("text"))).alias("term")).distinct()
    return analysis.stem_terms(vocabulary)


def field_stats(spark, sf_dir):
    return _known(spark, sf_dir, terms_only=False)[1].field_stats


def term_stats(spark, sf_dir):
    data, index = _known(spark, sf_dir, terms_only=False)
    n = index.field_stats.select("dataset", "n_docs")
    return index.term_stats.join(F.broadcast(n), "dataset").select("term", "df", F.round(search.idf(F.col("n_docs"), F.col("df")), 6).alias("idf"))


def postings(spark, sf_dir):
    return _known(spark, sf_dir, terms_only=False)[1].postings.select("term", "table_id", "tf", "dl")


def bm25_top10(spark, sf_dir):
    data, index = _known(spark, sf_dir)
    return search.single(data.queries, index, k=10).select(F.col("query_id").alias("item_id"), F.col("table_id").alias("doc_id"), "score", "rank")


def bm25_params(spark, sf_dir):
    data, index = _known(spark, sf_dir)
    grid = [(1.2, 0.0), (1.2, 1.0), (0.0, 0.75), (2.0, 0.5)]
    runs = {str(i): search.Run(k1=k1, b=b) for i, (k1, b) in enumerate(grid)}
    of = F.array(*[F.struct(F.lit(k1).alias("k1"), F.lit(b).alias("b")) for k1, b in grid])[F.col("config").cast("int")]
    return search.runs_top_k(data.queries, index, runs, k=5).select(of["k1"].alias("k1"), of["b"].alias("b"), "query_id", "table_id", "score", "rank")


def bm25_explain(spark, sf_dir):
    data, index = _known(spark, sf_dir)
    hit = data.qrels.agg(F.min(F.struct("query_id", "table_id")).alias("h")).select("h.*").first()
    return search.explain(data.queries, index, *(hit or (0, 0)))


def known_item_ranks(spark, sf_dir):
    data, index = _known(spark, sf_dir)
    hits = search.single(data.queries, index, k=10)
    return data.qrels.join(hits, ["dataset", "query_id", "table_id"], "left").groupBy("rank").agg(F.count("*").alias("n"))


def raw_metadata_top10(spark, sf_dir):
    data, fields = _ent_fields(spark, sf_dir)
    return search.single(data.queries, search.build_index(fields), "raw_names", k=10).drop("dataset")


def expansion_top10(spark, sf_dir):
    data, fields = _ent_fields(spark, sf_dir)
    return search.single(data.queries, search.build_index(fields), "expansion", k=10).drop("dataset")


def single_field_top10(spark, sf_dir):
    data, index = _sci_fields(spark, sf_dir)
    return search.single(data.queries, index, "description", k=10).drop("dataset")


def multi_field_top10(spark, sf_dir):
    data, index = _sci_fields(spark, sf_dir)
    return search.multi(data.queries, index, k=10).drop("dataset")


def field_ablation(spark, sf_dir):
    data, index = _sci_fields(spark, sf_dir)
    every = ("description", "expansion", "context")
    return search.multi_runs(data.queries, index, {f"-{gone}": ([f for f in every if f != gone], 0.1) for gone in every}, k=10).drop("dataset")


def tie_sweep(spark, sf_dir):
    data, index = _sci_fields(spark, sf_dir)
    every = ["description", "expansion", "context"]
    runs = search.multi_runs(data.queries, index, {str(t): (every, t) for t in (0.0, 1.0)}, k=10)
    return runs.withColumn("tie", F.col("config").cast("double")).drop("dataset", "config")


def weighted_fields(spark, sf_dir):
    data, index = _two_analyzers(spark, sf_dir)
    return search.weighted(data.queries, index, {"columns": 1.0, "context": 1.0}, k=10).drop("dataset")


def dense_top10(spark, sf_dir):
    vectors = datasets.read(spark, sf_dir, "embeddings")
    queries = vectors.where("vec_id % 25 = 0").select(F.col("vec_id").alias("query_id"), "embedding")
    return search.dense(queries, vectors.select(F.col("vec_id").alias("table_id"), "embedding"))


def hybrid_rrf(spark, sf_dir):
    data, index = _sci_fields(spark, sf_dir)
    a = search.single(data.queries, index, "description", k=20)
    b = search.single(data.queries, index, "context", k=20)
    return search.fuse(a, b, k=10)


def split_names(spark, sf_dir):
    return datasets.ent(spark, sf_dir).tables.select("table_name", F.array_join(names.split_name(F.col("table_name")), " ").alias("tokens"))


def column_batches(spark, sf_dir):
    return names.batch_columns(datasets.ent(spark, sf_dir).tables).select("table_id", "batch", F.array_join("columns", ",").alias("columns"))


def expand_columns(spark, sf_dir):
    return names.expand(datasets.ent(spark, sf_dir).tables).select("table_name", "pos", "original", "expanded")


def expansion_violations(spark, sf_dir):
    rows = names.violations(names.expand(datasets.ent(spark, sf_dir).tables))
    return rows.agg(*[F.coalesce(F.sum(F.col(c).cast("int")), F.lit(0)).alias(c) for c in ("order_broken", "number_changed", "phrase_missing", "something_added", "plain_changed")])


def table_prompt_inputs(spark, sf_dir):
    tables = datasets.ent(spark, sf_dir).tables
    return names.table_prompt_inputs(tables, names.expand(tables)).drop("dataset")


def template_descriptions(spark, sf_dir):
    return _sci(spark, sf_dir, 5)[1].select("table_id", "cand_id", F.md5("body").alias("body_md5"))


def candidate_counts(spark, sf_dir):
    return _sci(spark, sf_dir)[1].groupBy("is_gold").agg(F.count("*").alias("n"), F.count_distinct("table_id").alias("n_tables"))


def gold_tables(spark, sf_dir):
    return rank.gold(datasets.sci(spark, sf_dir).qrels).select("table_id", "n_queries")


def default_corpus(spark, sf_dir):
    return rank.default_corpus(_sci(spark, sf_dir)[1]).select("table_id", "cand_id")


def _scores(spark, sf_dir, mode, k=3):
    data, cands = _sci(spark, sf_dir, k)
    return rank.score(cands, data.queries, data.qrels, mode, k)


def score_unified(spark, sf_dir):
    return _scores(spark, sf_dir, "unified").select("table_id", "cand_id", "score")


def score_individual(spark, sf_dir):
    return _scores(spark, sf_dir, "individual").select("table_id", "cand_id", "score")


def candidate_order(spark, sf_dir):
    return rank.order(_scores(spark, sf_dir, "unified")).select("table_id", "cand_id", "rank")


def pref_pairs(spark, sf_dir):
    return rank.pairs(_scores(spark, sf_dir, "unified")).drop("dataset")


def pref_pairs_all(spark, sf_dir):
    return rank.pairs(_scores(spark, sf_dir, "unified"), "all").drop("dataset")


def pref_pairs_k5(spark, sf_dir):
    return rank.pairs(_scores(spark, sf_dir, "unified", 5)).drop("dataset")


def unified_vs_individual(spark, sf_dir):
    return rank.approximation_loss(_scores(spark, sf_dir, "unified"), _scores(spark, sf_dir, "individual")).drop("dataset")


def _both_pairs(spark, sf_dir):
    out = None
    for large in (False, True):
        data, cands = _sci(spark, sf_dir, 3, large)
        rows = rank.pairs(rank.score(cands, data.queries, data.qrels))
        body = lambda name, c=cands: c.select("dataset", "table_id", F.col("cand_id").alias(f"{name}_cand"), F.col("body").alias({"win": "chosen", "lose": "rejected"}[name]))
        rows = rows.join(body("win"), ["dataset", "table_id", "win_cand"]).join(body("lose"), ["dataset", "table_id", "lose_cand"]).join(data.tables.select("dataset", "table_id", F.array_join("columns", " ").alias("prompt")), ["dataset", "table_id"])
        out = rows if out is None else out.unionByName(rows)
    return out


def lodo_folds(spark, sf_dir):
    return rank.folds(_both_pairs(spark, sf_dir), ["sci_s", "sci_l", "gov"]).groupBy("held_out").agg(F.count("*").alias("n_pairs"))


def train_folds(spark, sf_dir):
    folded = rank.folds(_both_pairs(spark, sf_dir), ["sci_s", "sci_l"]).select("held_out", "dataset", "table_id", "prompt", "chosen", "rejected")
    return train.train_folds(folded)


def _log_likelihoods(spark, sf_dir):
    """Portable stand-in log likelihoods of winners and losers: their margins, scaled."""
    return _scores_pairs(spark, sf_dir).select(F.col("margin").alias("win"), F.lit(0.0).alias("win_ref"), F.lit(0.1).alias("lose"), F.lit(0.0).alias("lose_ref"))


def _scores_pairs(spark, sf_dir):
    return rank.pairs(_scores(spark, sf_dir, "unified"))


def pref_loss(spark, sf_dir):
    rows = _log_likelihoods(spark, sf_dir)
    return train.preference_loss(rows, 0.1).unionByName(train.preference_loss(rows, 0.5))


def pref_margins(spark, sf_dir):
    return train.margins(_log_likelihoods(spark, sf_dir))


def lr_schedule(spark, sf_dir):
    """The learning rate at each event, if a user's events in order of time are the steps of a training run."""
    mine = Window.partitionBy("user_id")
    events = datasets.read(spark, sf_dir, "events").select("event_id", "ts", "user_id")
    steps = events.select("event_id", "user_id", (F.row_number().over(mine.orderBy("ts", "event_id")) - 1).cast("long").alias("step"), F.count("*").over(mine).alias("total"))
    return steps.select("event_id", "user_id", "step", "total", F.round(train.linear_warmup(F.col("step"), F.col("total")) * 1e6, 6).alias("rate_millionths"))


def ndcg(spark, sf_dir):
    data, hits = _systems(spark, sf_dir)
    return evaluate.ndcg(hits, data.qrels, KS).select("config", "k", F.col("value").alias("ndcg"))


def recall(spark, sf_dir):
    data, hits = _systems(spark, sf_dir)
    return evaluate.recall(hits, data.qrels, KS).select("config", "k", F.col("value").alias("recall"))


def relative_gain(spark, sf_dir):
    data, hits = _systems(spark, sf_dir)
    return evaluate.relative(evaluate.ndcg(hits, data.qrels, KS), "cand0").drop("dataset")


def best_cells(spark, sf_dir):
    data, hits = _systems(spark, sf_dir)
    return evaluate.best(evaluate.ndcg(hits, data.qrels, KS)).drop("dataset")


def metrics_pivot(spark, sf_dir):
    data, hits = _systems(spark, sf_dir)
    return evaluate.recall(hits, data.qrels, KS).groupBy("config").pivot("k", list(KS)).agg(F.first("value")).select("config", *[F.col(str(k)).alias(f"at_{k}") for k in KS])


def desc_length(spark, sf_dir):
    data = datasets.sci(spark, sf_dir)
    rows = data.tables.select("table_id", F.posexplode(rank.template_bodies(3)).alias("c", "body")).select(F.concat(F.lit("cand"), "c").alias("system"), "body")
    return evaluate.length(rows, analysis.words)


def relevance_density(spark, sf_dir):
    data = datasets.sci(spark, sf_dir)
    return evaluate.density(data.qrels, data.tables).drop("dataset")


def dataset_summary(spark, sf_dir):
    out = None
    for data in (datasets.sci(spark, sf_dir), datasets.sci(spark, sf_dir, False), datasets.known(spark, sf_dir)):
        part = evaluate.summary(data.tables.select("dataset", "table_id"), data.queries, data.qrels)
        out = part if out is None else out.unionByName(part)
    return out


def index_cost(spark, sf_dir):
    data = datasets.sci(spark, sf_dir)
    rows = evaluate.summary(data.tables.select("dataset", "table_id"), data.queries, data.qrels)
    return rows.select(*evaluate.index_cost(F.col("n_gold"), F.col("n_tables")))


def task_qrels(spark, sf_dir):
    """Judgements of tasks for the two queries of each: how many tables of each grade."""
    judged = datasets.gov_judgements(spark, sf_dir)
    asked = spark.createDataFrame([(f"src{i}", 2 * i + j) for i in range(6) for j in (0, 1)], "task string, query_id long")
    return benchmark.task_to_query(judged, asked).groupBy("query_id", "grade").agg(F.count("*").alias("n"))


def relabel(spark, sf_dir):
    """Verdicts on grades of 2 and more: tables of fewer than 200 characters become 0."""
    judged = datasets.gov_judgements(spark, sf_dir)
    verdicts = judged.where("n_chars < 200").select("task", "table_id", F.lit(0).alias("verdict"))
    return benchmark.relabel(judged.drop("n_chars"), verdicts).select("task", "table_id", "grade")


def hard_negatives(spark, sf_dir):
    data, index = _sci_fields(spark, sf_dir)
    hits = search.single(data.queries, index, "description", k=10)
    return hits.join(data.qrels, ["dataset", "query_id", "table_id"], "left_anti").select("query_id", "table_id")


def _two_analyzers(spark, sf_dir):
    """Column names by trigrams, context by words."""
    data = datasets.sci(spark, sf_dir)
    part = lambda name, col: data.tables.select("dataset", "table_id", F.lit(name).alias("field"), col.alias("text"))
    fields = part("columns", F.array_join("columns", " ")).unionByName(part("context", F.array_join(F.slice("vis", 41, 80), " ")))
    terms = search.query_terms(data.queries, analysis.TRIGRAMS).unionByName(search.query_terms(data.queries)).select("dataset", "term").distinct()
    return data, search.build_index(fields, {"columns": analysis.TRIGRAMS}, terms)


def downsample(spark, sf_dir):
    """The fifty best of each query by trigrams of column names and words of the context, and every gold table."""
    data, index = _two_analyzers(spark, sf_dir)
    return benchmark.downsample(data.queries, index, data.qrels, {"columns": 1.0, "context": 1.0}).select("table_id")


def pool_union(spark, sf_dir):
    data, index = _sci_fields(spark, sf_dir)
    runs = [search.single(data.queries, index, f, k=10).select("query_id", "table_id", F.lit(f).alias("run")) for f in ("description", "expansion", "context")]
    pool = runs[0].unionByName(runs[1]).unionByName(runs[2])
    return pool.groupBy("query_id", "table_id").agg(F.count("*").alias("n_runs"))


def tumbling_counts(spark, sf_dir):
    return _plain(feedback.tumbling(datasets.read(spark, sf_dir, "events")))


def sliding_counts(spark, sf_dir):
    return _plain(feedback.sliding(datasets.read(spark, sf_dir, "events")))


def session_counts(spark, sf_dir):
    return _plain(feedback.sessions(datasets.read(spark, sf_dir, "events")))


def _plain(rows):
    """Window starts as text: portable between engines and zones."""
    return rows.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


def click_qrels(spark, sf_dir):
    return feedback.click_grades(datasets.read(spark, sf_dir, "events"))


def dedupe_events(spark, sf_dir):
    events = datasets.read(spark, sf_dir, "events").select("event_id", "ts", "event_type")
    return feedback.once(events.unionByName(events)).groupBy("event_type").agg(F.count("*").alias("n"))


def interval_join(spark, sf_dir):
    return feedback.view_then_click(datasets.read(spark, sf_dir, "events"))


def _written(spark, sf_dir):
    """Model answers made of a table's words, as an outside generator would send them."""
    tables = datasets.sci(spark, sf_dir).tables.where("size(columns) >= 12")
    c = lambda i: F.try_element_at("columns", F.lit(i))
    overview = F.concat(F.array_join(F.slice("vis", 1, 8), " "), F.lit(". "), F.array_join(F.slice("vis", 9, 8), " "), F.lit("."))
    concepts = F.array(*[F.struct(c(i).alias("concept"), F.array(c(i + 3)).alias("synonyms")) for i in (1, 2, 3)])
    doc = F.struct(overview.alias("dataset_overview"), F.slice("columns", 1, 3).alias("key_themes_or_topics"), F.slice("columns", 4, 2).alias("applications_and_use_cases"), concepts.alias("concepts_and_synonyms"), F.slice("columns", 1, 5).alias("keywords_and_themes"), F.array(F.lit("unknown")).alias("additional_context"))
    fenced = F.concat(F.lit("Here it is:\n```json\n"), F.to_json(doc), F.lit("\n```"))
    return describe.parse(tables.select("dataset", "table_id", F.when(F.col("table_id") % 7 == 1, F.lit("no answer")).otherwise(fenced).alias("raw")))


def description_text(spark, sf_dir):
    return _written(spark, sf_dir).where("valid").select("table_id", F.md5(describe.flatten(F.col("doc"))).alias("text_md5"))


def description_validity(spark, sf_dir):
    return _written(spark, sf_dir).groupBy("valid").agg(F.count("*").alias("n"))


def mcb_profile(spark, sf_dir):
    return describe.profile(datasets.read(spark, sf_dir, "nation"), ["n_nationkey", "n_name", "n_regionkey"]).select("column", "n_rows", "n_null", "least", "greatest")


def row_summary(spark, sf_dir):
    return describe.row_summary(datasets.read(spark, sf_dir, "nation"), "n_nationkey", ["n_nationkey", "n_name"])


def verbalize(spark, sf_dir):
    return describe.verbalize(datasets.ent(spark, sf_dir).tables).drop("dataset")


def call_counts(spark, sf_dir):
    """Model calls of the single-call system and of the multi-call baseline over the catalogue."""
    calls = 3 + F.ceil(F.size("columns") / 10)
    return datasets.ent(spark, sf_dir).tables.agg(F.count("*").alias("calls_single"), F.sum(calls).cast("long").alias("calls_multi"))


def description_prompts(spark, sf_dir):
    tables = datasets.ent(spark, sf_dir).tables
    return describe.prompts(tables, names.expand(tables)).select("table_id", "prompt")


def page_context(spark, sf_dir):
    rows = page_source.context(datasets.read(spark, sf_dir, "pages"))
    return rows.select("page_id", "title", F.size("anchors").cast("long").alias("n_anchors"), F.md5(F.array_join("paragraphs", "|")).alias("paragraphs_md5"))


def metric_cube(spark, sf_dir):
    data, hits = _systems(spark, sf_dir)
    return evaluate.recall(hits, data.qrels, KS).cube("config", "k").agg(F.round(F.avg("value"), 5).alias("mean"))


def run_set_ops(spark, sf_dir):
    data, index = _sci_fields(spark, sf_dir)
    a, b = (search.single(data.queries, index, f, k=10).select("query_id", "table_id") for f in ("description", "context"))
    name = lambda rows, op: rows.select(F.lit(op).alias("op"), "query_id", "table_id")
    return name(a.intersect(b), "both").unionByName(name(a.exceptAll(b), "first only")).unionByName(name(data.qrels.select("query_id", "table_id").subtract(a), "gold missed"))


def asof_index_version(spark, sf_dir):
    """For each purchase, the user's last earlier view: one sorted pass per user, no pairs."""
    events = datasets.read(spark, sf_dir, "events")
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before)
    return events.withColumn("view_id", seen).where("event_type = 'purchase'").select("event_id", "view_id")


def iterate_defaults(spark, sf_dir):
    data, cands = _sci(spark, sf_dir)
    scores, rounds = rank.iterate(cands, data.queries, data.qrels, lambda d: materialise(d, "round"))
    return scores.select("table_id", "cand_id", "score", F.lit(rounds).alias("rounds"))


_QUERIES = (
    analyze_words, analyze_trigrams, stem_vocab, field_stats, term_stats, postings, bm25_top10, bm25_params, bm25_explain, known_item_ranks,
    raw_metadata_top10, expansion_top10, single_field_top10, multi_field_top10, field_ablation, tie_sweep, weighted_fields, dense_top10, hybrid_rrf,
    split_names, column_batches, expand_columns, expansion_violations, table_prompt_inputs, template_descriptions, candidate_counts,
    gold_tables, default_corpus, score_unified, score_individual, candidate_order, pref_pairs, pref_pairs_all, pref_pairs_k5,
    unified_vs_individual, lodo_folds, train_folds, pref_loss, pref_margins, lr_schedule, ndcg, recall, relative_gain, best_cells, metrics_pivot,
    desc_length, relevance_density, dataset_summary, index_cost, task_qrels, relabel, hard_negatives, downsample, pool_union,
    tumbling_counts, sliding_counts, session_counts, click_qrels, dedupe_events, interval_join,
    description_text, description_validity, description_prompts, mcb_profile, row_summary, verbalize, call_counts, page_context,
    metric_cube, run_set_ops, asof_index_version, iterate_defaults,
)


def queries():
    return {f.__name__: f for f in _QUERIES}


# --- oracles --------------------------------------------------------------------


def _bm25(fields: str, asked: str, k1: float = 1.2, b: float = 0.75, asked_only: bool = True) -> str:
    """CTEs ending in fscore(query_id, table_id, field, score) from (table_id, field, text) and (query_id, text)."""
    return f"""
tok AS (SELECT table_id, field, {_w('text')} AS w FROM ({fields})),
stats AS (SELECT field, count(*) AS n_docs, sum(len(w))::BIGINT AS sum_len FROM tok GROUP BY field),
qt AS (SELECT DISTINCT query_id, unnest({_w('text')}) AS term FROM ({asked})),
tf AS (SELECT table_id, field, dl, term, count(*) AS tf FROM (SELECT table_id, field, len(w) AS dl, unnest(w) AS term FROM tok)
       {'WHERE term IN (SELECT term FROM qt)' if asked_only else ''} GROUP BY ALL),
df AS (SELECT field, term, count(*) AS df FROM tf GROUP BY ALL),
fscore AS (
  SELECT query_id, table_id, tf.field, sum(ln(1 + (n_docs - df + 0.5) / (df + 0.5)) * tf * ({k1} + 1.0) / (tf + {k1} * (1 - {b} + {b} * dl / (sum_len / n_docs)))) AS score
  FROM qt JOIN tf USING (term) JOIN df ON df.term = tf.term AND df.field = tf.field JOIN stats ON stats.field = tf.field GROUP BY ALL)"""


def _top(score: str, k: int, where: str = "true", source: str = "fscore") -> str:
    return f"""SELECT query_id, table_id, score, rank::INTEGER AS rank FROM (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, table_id) AS rank FROM (
    SELECT query_id, table_id, round({score}, 6) AS score FROM {source} WHERE {where} GROUP BY query_id, table_id) WHERE score > 0) WHERE rank <= {k}"""


_KNOWN_ALL = _bm25("SELECT doc_id AS table_id, 'text' AS field, text FROM documents", "SELECT item_id AS query_id, text FROM benchmark", asked_only=False)
_KNOWN = _bm25("SELECT doc_id AS table_id, 'text' AS field, text FROM documents", "SELECT item_id AS query_id, text FROM benchmark")


def _sci_sql(large: bool = True, k: int = 3) -> str:
    return f"""
sci AS (SELECT doc_id AS table_id, source, {_w('text')} AS w FROM documents WHERE lang = 'en' AND doc_id % 5 {'<>' if large else '='} 0),
half AS (SELECT *, len(w) // 2 AS h FROM sci),
tabs AS (SELECT table_id, vis, list_filter(vis, lambda x, i: list_position(vis, x) = i) AS firsts FROM (SELECT table_id, w[1:h] AS vis FROM half)),
hid AS (SELECT table_id, term, count(*) AS tf FROM (SELECT table_id, unnest(w[h + 1:]) AS term FROM half) WHERE length(term) >= 5 GROUP BY ALL),
topics AS (SELECT term, md5(term) AS h FROM (SELECT term, count(*) AS df, count(*) FILTER (tf >= 2) AS strong FROM hid GROUP BY term)
           WHERE df >= 0.03 * (SELECT count(*) FROM sci) AND df <= 0.35 * (SELECT count(*) FROM sci) AND strong >= 2 ORDER BY h LIMIT {15 if large else 20}),
asked AS (SELECT row_number() OVER (ORDER BY h) AS query_id, term AS text FROM topics),
qrels AS (SELECT query_id, table_id, 1 AS grade FROM hid JOIN asked ON term = text WHERE tf >= 2),
gold AS (SELECT table_id, count(DISTINCT query_id) AS n_queries FROM qrels GROUP BY table_id),
bodies AS (SELECT table_id, firsts[1:12] AS columns, unnest(range(0, {k})) AS cand_id,
  unnest(list_slice([vis[1:40], list_filter(vis, lambda x, i: i % 2 = 1), firsts, vis[greatest(len(vis) - 59, 1):], list_concat(firsts[1:12], vis[1:80])], 1, {k})) AS words FROM tabs),
cands AS (SELECT b.table_id, cand_id::INTEGER AS cand_id, array_to_string(words, ' ') AS body, g.table_id IS NOT NULL AS is_gold FROM bodies b LEFT JOIN gold g ON b.table_id = g.table_id
          WHERE g.table_id IS NOT NULL OR cand_id = 0)"""


def _score_sql(unified: bool = True, k: int = 3, name: str = "scores") -> str:
    p = name
    return f"""
{p}_tok AS (SELECT *, NOT is_gold OR cand_id = (table_id * 7919 + 42) % {k} AS is_default, {_w('body')} AS w FROM cands),
{p}_base AS (SELECT count(*) AS n0, sum(len(w)) AS len0 FROM {p}_tok WHERE is_default),
{p}_own AS (SELECT table_id, sum(len(w)) FILTER (is_default) AS r_len, sum(len(w)) AS all_len, count(*) AS n_cand FROM {p}_tok WHERE is_gold GROUP BY table_id),
{p}_tf AS (SELECT table_id, cand_id, is_gold, is_default, dl, term, count(*) AS tf FROM (SELECT *, len(w) AS dl, unnest(w) AS term FROM {p}_tok) WHERE term IN (SELECT text FROM asked) GROUP BY ALL),
{p}_df AS (SELECT term, count(*) AS df0 FROM {p}_tf WHERE is_default GROUP BY term),
{p}_in AS (SELECT table_id, term, count(*) FILTER (is_default) AS in_r, count(*) AS in_c FROM {p}_tf WHERE is_gold GROUP BY ALL),
{p}_x AS (SELECT t.*, n0 + {'n_cand - 1' if unified else '0'} AS n, len0 - r_len + {'all_len' if unified else 'dl'} AS total, coalesce(df0, 0) - in_r + {'in_c' if unified else '1'} AS df
  FROM {p}_tf t JOIN {p}_in USING (table_id, term) LEFT JOIN {p}_df d ON d.term = t.term JOIN {p}_own USING (table_id), {p}_base WHERE is_gold),
{p} AS (
  SELECT c.table_id, c.cand_id, round(coalesce(total, 0) / n_queries, 6) AS score FROM cands c JOIN gold g ON c.table_id = g.table_id LEFT JOIN (
    SELECT x.table_id, cand_id, sum(ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * dl / (total / n)))) AS total
    FROM {p}_x x JOIN asked ON text = term JOIN qrels r ON r.query_id = asked.query_id AND r.table_id = x.table_id GROUP BY ALL) s ON s.table_id = c.table_id AND s.cand_id = c.cand_id
  WHERE c.is_gold)"""


def _pairs_sql(source: str = "scores") -> str:
    return f"""SELECT table_id, win_cand, lose_cand, round(s1 - s2, 6) AS margin FROM (
  SELECT table_id, first(cand_id ORDER BY score DESC, cand_id) AS win_cand, first(cand_id ORDER BY score, cand_id DESC) AS lose_cand, max(score) AS s1, min(score) AS s2
  FROM {source} GROUP BY table_id) WHERE s1 > s2"""


_FIELDS = "SELECT table_id, 'description' AS field, body AS text FROM cands UNION ALL SELECT table_id, 'expansion', array_to_string(firsts[1:12], ' ') FROM tabs UNION ALL SELECT table_id, 'context', array_to_string(vis[41:120], ' ') FROM tabs"
_SCI_FIELDS = "WITH " + _sci_sql(k=1) + ", " + _bm25(_FIELDS, "SELECT * FROM asked").lstrip()
_GRAMS = "flatten(list_transform({}, lambda w: CASE WHEN length(w) < 3 THEN [w] ELSE list_transform(range(1, length(w) - 1), lambda i: substr(w, i, 3)) END))"
#: Column names by trigrams, context by words: both analyzers' BM25 side by side.
_TWO = "WITH " + _sci_sql(k=1) + f""",
tok AS (SELECT table_id, 'columns' AS field, {_GRAMS.format('firsts[1:12]')} AS w FROM tabs UNION ALL SELECT table_id, 'context', vis[41:120] FROM tabs),
stats AS (SELECT field, count(*) AS n_docs, sum(len(w))::BIGINT AS sum_len FROM tok GROUP BY field),
qt AS (SELECT DISTINCT query_id, 'columns' AS field, unnest({_GRAMS.format('[text]')}) AS term FROM asked UNION SELECT query_id, 'context', text FROM asked),
tf AS (SELECT table_id, field, dl, term, count(*) AS tf FROM (SELECT table_id, field, len(w) AS dl, unnest(w) AS term FROM tok) GROUP BY ALL),
df AS (SELECT field, term, count(*) AS df FROM tf GROUP BY ALL),
fscore AS (SELECT query_id, table_id, field, sum(ln(1 + (n_docs - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * dl / (sum_len / n_docs)))) AS score
  FROM qt JOIN tf USING (field, term) JOIN df USING (field, term) JOIN stats USING (field) GROUP BY ALL)"""
_SCI = "WITH " + _sci_sql()
_SCORED = _SCI + ", " + _score_sql().lstrip()
_MULTI = "max(score) + 0.1 * (sum(score) - max(score))"
_SYSTEMS = (
    _SCI + ", " + _bm25("SELECT table_id, 'cand' || cand_id AS field, array_to_string(words, ' ') AS text FROM bodies", "SELECT * FROM asked").lstrip() + """,
hits AS (SELECT * FROM (SELECT field AS config, query_id, table_id, row_number() OVER (PARTITION BY field, query_id ORDER BY score DESC, table_id) AS rank
         FROM (SELECT query_id, table_id, field, round(score, 6) AS score FROM fscore) WHERE score > 0) WHERE rank <= 100),
ks AS (SELECT unnest([5, 10, 20])::INTEGER AS k), configs AS (SELECT DISTINCT config FROM hits),
ideal AS (SELECT query_id, k, sum(1 / log2(r + 1)) AS i FROM (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY table_id) AS r FROM qrels), ks WHERE r <= k GROUP BY ALL),
total AS (SELECT query_id, count(*) AS n FROM qrels GROUP BY ALL),
got AS (SELECT config, query_id, k, sum(1 / log2(rank + 1)) AS d, count(*) AS c FROM hits JOIN qrels USING (query_id, table_id), ks WHERE rank <= k GROUP BY ALL),
ndcg AS (SELECT config, k, round(avg(coalesce(d, 0) / i), 6) AS value FROM ideal CROSS JOIN configs LEFT JOIN got USING (config, query_id, k) GROUP BY ALL),
recall AS (SELECT config, k, round(avg(coalesce(c, 0) / n), 6) AS value FROM total CROSS JOIN configs CROSS JOIN ks LEFT JOIN got USING (config, query_id, k) GROUP BY ALL)"""
)


def _catalogue_sql() -> str:
    rows = ", ".join(f"({i}, '{t}', '{t}', {c})" for i, (t, c) in enumerate(datasets.CATALOGUE.items()))
    c = {t: str(v) for t, v in datasets.CATALOGUE.items()}
    return f"""
ent AS (
  SELECT * FROM (VALUES {rows}) v(table_id, table_name, base, columns)
  UNION ALL SELECT 100 + k, format('cust_n{{:02d}}', k), 'customer', {c['customer']} FROM (SELECT DISTINCT c_nationkey AS k FROM customer)
  UNION ALL SELECT 200 + k, format('supp_n{{:02d}}', k), 'supplier', {c['supplier']} FROM (SELECT DISTINCT s_nationkey AS k FROM supplier)
  UNION ALL SELECT 300 + k, format('part_b{{:02d}}', k), 'part', {c['part']} FROM (SELECT DISTINCT regexp_extract(p_brand, '([0-9]+)', 1)::INTEGER AS k FROM part)
  UNION ALL SELECT 400 + k, format('ord_p{{}}', k), 'orders', {c['orders']} FROM (SELECT DISTINCT o_orderpriority[1:1]::INTEGER AS k FROM orders)
  UNION ALL SELECT 499 + row_number() OVER (ORDER BY event_type), 'evt_' || event_type, 'events', {c['events']} FROM (SELECT DISTINCT event_type FROM events)),
lex(scope, token, phrase) AS (VALUES {', '.join(map(str, names.LEXICON))}),
cols AS (SELECT table_id, table_name, base, unnest(range(0, len(columns)))::INTEGER AS pos, unnest(columns) AS original FROM ent
         UNION ALL SELECT table_id, table_name, base, -1, table_name FROM ent),
pieces AS (SELECT *, unnest(range(0, len(t))) AS i, unnest(t) AS token FROM (SELECT *, {_split_sql('original')} AS t FROM cols)),
expanded AS (
  SELECT table_id, table_name, pos, original, string_agg(coalesce(a.phrase, b.phrase, p.token), ' ' ORDER BY i) AS expanded
  FROM pieces p LEFT JOIN lex a ON a.scope = p.base AND a.token = p.token LEFT JOIN lex b ON b.scope = '*' AND b.token = p.token GROUP BY ALL)"""


def _split_sql(name: str) -> str:
    spaced = name
    for old in ("([a-z0-9])([A-Z])", "([A-Z]+)([A-Z][a-z])", "([A-Za-z])([0-9])", "([0-9])([A-Za-z])"):
        spaced = rf"regexp_replace({spaced}, '{old}', '\1 \2', 'g')"
    return f"list_filter(regexp_split_to_array(lower({spaced}), '[^0-9a-z]+'), lambda x: x <> '')"


def _ent_search(field: str) -> str:
    texts = {"raw_names": "SELECT table_id, 'raw_names' AS field, concat_ws(' ', table_name, array_to_string(columns, ' ')) AS text FROM ent", "expansion": "SELECT table_id, 'expansion' AS field, string_agg(expanded, ' ' ORDER BY pos) AS text FROM expanded GROUP BY table_id"}
    asked = "SELECT query_id::BIGINT AS query_id, text FROM (VALUES " + ", ".join(f"({i}, '{t}')" for i, t, _ in datasets.ENT_QUERIES) + ") q(query_id, text)"
    return "WITH " + _catalogue_sql() + ", " + _bm25(texts[field], asked).lstrip() + " " + _top("sum(score)", 10)


def _found_sql(tag: str) -> str:
    text = "regexp_replace(x, '<[^>]*>', ' ', 'g')"
    for entity, char in page_source.ENTITIES:
        text = f"replace({text}, '{entity}', '{char.replace(chr(39), chr(39) * 2)}')"
    return f"list_transform(regexp_extract_all(h, '(?is)<{tag}\\b[^>]*>(.*?)</{tag}>', 1), lambda x: trim(regexp_replace({text}, '[ \\t\\r\\n]+', ' ', 'g')))"


def oracle_sql():
    known, every = "WITH " + _KNOWN.lstrip(), "WITH " + _KNOWN_ALL.lstrip()
    containment = "SELECT item_id AS query_id, doc_id AS table_id FROM benchmark b JOIN documents d ON contains(d.text, b.text[1:60])"
    params = " UNION ALL ".join(f"SELECT {k1}::DOUBLE AS k1, {b}::DOUBLE AS b, * FROM (WITH {_bm25('SELECT doc_id AS table_id, chr(120) AS field, text FROM documents', 'SELECT item_id AS query_id, text FROM benchmark', k1, b).lstrip()} {_top('sum(score)', 5)})" for k1, b in [(1.2, 0.0), (1.2, 1.0), (0.0, 0.75), (2.0, 0.5)])
    ablation = " UNION ALL ".join(f"SELECT *, '-{gone}' AS config FROM ({_top(_MULTI, 10, f'field <> {gone!r}')})" for gone in ("description", "expansion", "context"))
    ties = " UNION ALL ".join(f"SELECT *, {t}::DOUBLE AS tie FROM ({_top(f'max(score) + {t} * (sum(score) - max(score))', 10)})" for t in (0.0, 1.0))
    run = lambda f, k: _top("sum(score)", k, f"field = '{f}'")
    window = lambda start: f"SELECT strftime({start}, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM"
    gov = "SELECT source AS task, d.doc_id AS table_id, n_chars, (CASE WHEN quality = 1 AND toxic = 0 THEN 3 WHEN quality = 1 THEN 2 ELSE 1 END)::INTEGER AS grade FROM documents d JOIN labels l ON d.doc_id = l.doc_id WHERE source IN ('src0', 'src1', 'src2', 'src3', 'src4', 'src5')"
    small, large = (f"SELECT '{n}' AS dataset, (SELECT count(*) FROM sci) AS n_tables, (SELECT count(*) FROM asked) AS n_queries, (SELECT count(*) FROM gold) AS n_gold" for n in ("sci_s", "sci_l"))
    fold = lambda big: f"SELECT count(*) AS n FROM (WITH {_sci_sql(big)}, {_score_sql().lstrip()} {_pairs_sql()})"
    softplus = lambda beta: f"SELECT {beta}::DOUBLE AS beta, round(avg(greatest(-x, 0.0) + ln(1 + exp(-abs(x)))), 6) AS loss FROM (SELECT {beta} * (margin - 0.1) AS x FROM p)"
    return {
        "analyze_words": f"SELECT doc_id, len({_w('text')})::BIGINT AS n, len(list_distinct({_w('text')}))::BIGINT AS n_distinct FROM documents",
        "analyze_trigrams": f"SELECT item_id, array_to_string(flatten(list_transform({_w('text')}, lambda w: CASE WHEN length(w) < 3 THEN [w] ELSE list_transform(range(1, length(w) - 1), lambda i: substr(w, i, 3)) END)), ' ') AS grams FROM benchmark",
        "field_stats": every + " SELECT 'known' AS dataset, field, n_docs, sum_len FROM stats",
        "term_stats": every + " SELECT term, df, round(ln(1 + (n_docs - df + 0.5) / (df + 0.5)), 6) AS idf FROM df, stats",
        "postings": every + " SELECT term, table_id, tf, dl::BIGINT AS dl FROM tf",
        "bm25_top10": f"SELECT query_id AS item_id, table_id AS doc_id, score, rank FROM ({known} {_top('sum(score)', 10)})",
        "bm25_params": params,
        "bm25_explain": known + f""", h AS (SELECT * FROM ({containment}) ORDER BY query_id, table_id LIMIT 1)
            SELECT h.query_id, h.table_id, tf.term, tf, df, round(ln(1 + (n_docs - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * dl / (sum_len / n_docs))), 6) AS contribution
            FROM h JOIN qt ON qt.query_id = h.query_id JOIN tf ON tf.term = qt.term AND tf.table_id = h.table_id JOIN df ON df.term = tf.term, stats""",
        "known_item_ranks": known + f" SELECT rank, count(*) AS n FROM ({containment}) LEFT JOIN ({_top('sum(score)', 10)}) USING (query_id, table_id) GROUP BY rank",
        "raw_metadata_top10": _ent_search("raw_names"),
        "expansion_top10": _ent_search("expansion"),
        "single_field_top10": _SCI_FIELDS + " " + run("description", 10),
        "multi_field_top10": _SCI_FIELDS + " " + _top(_MULTI, 10),
        "field_ablation": _SCI_FIELDS + " " + ablation,
        "tie_sweep": _SCI_FIELDS + " " + ties,
        "weighted_fields": _TWO + " " + _top("sum(score)", 10),
        "dense_top10": """WITH s AS (SELECT q.vec_id AS query_id, v.vec_id AS table_id, round(list_cosine_similarity(q.embedding::DOUBLE[], v.embedding::DOUBLE[]), 6) AS score
            FROM embeddings q, embeddings v WHERE q.vec_id % 25 = 0 AND q.vec_id <> v.vec_id)
            SELECT query_id, table_id, score, rank::INTEGER AS rank FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, table_id) AS rank FROM s) WHERE rank <= 10""",
        "hybrid_rrf": _SCI_FIELDS + f""", f AS (SELECT query_id, table_id, round(coalesce(1.0 / (60 + a.rank), 0) + coalesce(1.0 / (60 + b.rank), 0), 6) AS score
            FROM ({run('description', 20)}) a FULL JOIN ({run('context', 20)}) b USING (query_id, table_id)) {_top('sum(score)', 10, source='f')}""",
        "split_names": f"WITH {_catalogue_sql()} SELECT table_name, array_to_string({_split_sql('table_name')}, ' ') AS tokens FROM ent",
        "column_batches": f"WITH {_catalogue_sql()} SELECT table_id::BIGINT AS table_id, (pos // 10)::INTEGER AS batch, string_agg(original, ',' ORDER BY pos) AS columns FROM cols WHERE pos >= 0 GROUP BY ALL",
        "expand_columns": f"WITH {_catalogue_sql()} SELECT table_name, pos, original, expanded FROM expanded WHERE pos >= 0",
        "expansion_violations": "SELECT 0::BIGINT AS order_broken, 0::BIGINT AS number_changed, 0::BIGINT AS phrase_missing, 0::BIGINT AS something_added, 0::BIGINT AS plain_changed",
        "table_prompt_inputs": f"WITH {_catalogue_sql()} SELECT table_id::BIGINT AS table_id, table_name, string_agg(expanded, ', ' ORDER BY pos) FILTER (pos BETWEEN 0 AND 24) AS columns FROM expanded GROUP BY ALL",
        "template_descriptions": f"WITH {_sci_sql(k=5)} SELECT table_id, cand_id, md5(body) AS body_md5 FROM cands",
        "candidate_counts": _SCI + " SELECT is_gold, count(*) AS n, count(DISTINCT table_id) AS n_tables FROM cands GROUP BY ALL",
        "gold_tables": _SCI + " SELECT * FROM gold",
        "default_corpus": _SCI + " SELECT table_id, cand_id FROM cands WHERE NOT is_gold OR cand_id = (table_id * 7919 + 42) % 3",
        "score_unified": _SCORED + " SELECT * FROM scores",
        "score_individual": _SCI + ", " + _score_sql(False).lstrip() + " SELECT * FROM scores",
        "candidate_order": _SCORED + " SELECT table_id, cand_id, (row_number() OVER (PARTITION BY table_id ORDER BY score DESC, cand_id))::INTEGER AS rank FROM scores",
        "pref_pairs": _SCORED + " " + _pairs_sql(),
        "pref_pairs_all": _SCORED + " SELECT a.table_id, a.cand_id AS win_cand, b.cand_id AS lose_cand, round(a.score - b.score, 6) AS margin FROM scores a JOIN scores b ON a.table_id = b.table_id AND a.score > b.score",
        "pref_pairs_k5": f"WITH {_sci_sql(k=5)}, {_score_sql(k=5).lstrip()} {_pairs_sql()}",
        "unified_vs_individual": _SCORED + ", " + _score_sql(False, name="alone").lstrip() + """
            SELECT count(*) AS n_targets, count(*) FILTER (bu = bi) AS same_best, count(*) FILTER (wu = wi) AS same_worst, round(max(d), 6) AS max_abs_diff FROM (
            SELECT table_id, first(cand_id ORDER BY u DESC, cand_id) AS bu, first(cand_id ORDER BY i DESC, cand_id) AS bi, first(cand_id ORDER BY u, cand_id DESC) AS wu, first(cand_id ORDER BY i, cand_id DESC) AS wi, max(abs(u - i)) AS d
            FROM (SELECT table_id, cand_id, s.score AS u, a.score AS i FROM scores s JOIN alone a USING (table_id, cand_id)) GROUP BY table_id)""",
        "lodo_folds": f"WITH s AS ({fold(False)}), l AS ({fold(True)}) SELECT * FROM (SELECT 'sci_s' AS held_out, l.n AS n_pairs FROM l UNION ALL SELECT 'sci_l', s.n FROM s UNION ALL SELECT 'gov', s.n + l.n FROM s, l) WHERE n_pairs > 0",
        "pref_loss": f"{_SCORED}, p AS ({_pairs_sql()}) {softplus(0.1)} UNION ALL {softplus(0.5)}",
        "pref_margins": f"{_SCORED}, p AS ({_pairs_sql()}) SELECT round(avg(0.1 * (margin - 0.1)), 6) AS avg_margin, round(avg((margin > 0.1)::INTEGER), 6) AS accuracy FROM p",
        "lr_schedule": """WITH s AS (SELECT event_id, user_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS step, count(*) OVER (PARTITION BY user_id) AS total FROM events),
            r AS (SELECT *, greatest(floor(total * 0.1::DOUBLE), 1) AS rise FROM s)
            SELECT event_id, user_id, step, total, round(5.0 * CASE WHEN step < rise THEN step / rise ELSE greatest((total - step) / greatest(total - rise, 1), 0) END, 6) AS rate_millionths FROM r""",
        "ndcg": _SYSTEMS + " SELECT config, k, value AS ndcg FROM ndcg",
        "recall": _SYSTEMS + " SELECT config, k, value AS recall FROM recall",
        "relative_gain": _SYSTEMS + " SELECT a.config, a.k, round((a.value / nullif(b.value, 0) - 1) * 100, 4) AS gain FROM ndcg a JOIN ndcg b ON a.k = b.k AND b.config = 'cand0' WHERE a.config <> 'cand0'",
        "best_cells": _SYSTEMS + " SELECT config, k, value FROM (SELECT *, rank() OVER (PARTITION BY k ORDER BY value DESC) AS r FROM ndcg) WHERE r = 1",
        "metrics_pivot": _SYSTEMS + " SELECT config, max(value) FILTER (k = 5) AS at_5, max(value) FILTER (k = 10) AS at_10, max(value) FILTER (k = 20) AS at_20 FROM recall GROUP BY config",
        "desc_length": _SCI + f" SELECT 'cand' || cand_id AS system, count(*) AS n_tables, round(avg(len({_w('body')})), 4) AS avg_words, round(avg(length(body)), 4) AS avg_chars FROM (SELECT cand_id, array_to_string(words, ' ') AS body FROM bodies) GROUP BY ALL",
        "relevance_density": _SCI + " SELECT count(*) AS n_queries, round(avg(g / n), 6) AS density FROM (SELECT query_id, count(*) AS g FROM qrels GROUP BY query_id), (SELECT count(*) AS n FROM sci)",
        "dataset_summary": f"SELECT * FROM (WITH {_sci_sql(True)} {large}) UNION ALL SELECT * FROM (WITH {_sci_sql(False)} {small}) UNION ALL SELECT 'known', (SELECT count(*) FROM documents), (SELECT count(*) FROM benchmark), (SELECT count(DISTINCT table_id) FROM ({containment}))",
        "index_cost": _SCI + " SELECT 3 * g * n AS docs_individual, g * (n + 2) AS docs_unified, n + 2 * g AS docs_shared FROM (SELECT count(*) AS n FROM sci), (SELECT count(*) AS g FROM gold)",
        "task_qrels": f"SELECT 2 * task[4:]::BIGINT + j AS query_id, grade, count(*) AS n FROM ({gov}), range(2) q(j) GROUP BY ALL",
        "relabel": f"SELECT task, table_id, (CASE WHEN grade >= 2 AND n_chars < 200 THEN 0 ELSE grade END)::INTEGER AS grade FROM ({gov})",
        "hard_negatives": _SCI_FIELDS + f" SELECT query_id, table_id FROM ({run('description', 10)}) a ANTI JOIN qrels USING (query_id, table_id)",
        "downsample": _TWO + f" SELECT table_id FROM ({_top('sum(score)', 50)}) UNION SELECT table_id FROM qrels",
        "pool_union": _SCI_FIELDS + f" SELECT query_id, table_id, count(*) AS n_runs FROM ({' UNION ALL '.join('SELECT query_id, table_id FROM (' + run(f, 10) + ')' for f in ('description', 'expansion', 'context'))}) GROUP BY ALL",
        "description_text": _SCI + """ SELECT table_id, md5(concat_ws(' ', array_to_string(vis[1:8], ' ') || '. ' || array_to_string(vis[9:16], ' ') || '.', array_to_string(firsts[1:3], ' '), array_to_string(firsts[4:5], ' '),
            firsts[1], firsts[4], firsts[2], firsts[5], firsts[3], firsts[6], array_to_string(firsts[1:5], ' '), 'unknown')) AS text_md5 FROM tabs WHERE len(firsts) >= 12 AND table_id % 7 <> 1""",
        "description_validity": _SCI + " SELECT table_id % 7 <> 1 AS valid, count(*) AS n FROM tabs WHERE len(firsts) >= 12 GROUP BY ALL",
        "mcb_profile": " UNION ALL ".join(f"SELECT '{c}' AS \"column\", count(*) AS n_rows, count(*) - count({c}) AS n_null, min({c}::VARCHAR) AS least, max({c}::VARCHAR) AS greatest FROM nation" for c in ("n_nationkey", "n_name", "n_regionkey")),
        "row_summary": "SELECT string_agg('n_nationkey=' || n_nationkey || '; n_name=' || n_name, ' | ' ORDER BY md5(n_nationkey::VARCHAR)) AS summary FROM (SELECT * FROM nation ORDER BY md5(n_nationkey::VARCHAR) LIMIT 5)",
        "verbalize": f"WITH {_catalogue_sql()} SELECT table_id::BIGINT AS table_id, string_agg('Table ' || table_name || ' has a column ' || original || '.', ' ' ORDER BY pos) AS body FROM cols WHERE pos >= 0 GROUP BY ALL",
        "call_counts": f"WITH {_catalogue_sql()} SELECT count(*) AS calls_single, sum(3 + ceil(len(columns) / 10))::BIGINT AS calls_multi FROM ent",
        "page_context": f"""WITH h AS (SELECT page_id, regexp_replace(regexp_replace(regexp_replace(coalesce(html, ''), '(?is)<script\\b.*?</script>', '', 'g'), '(?is)<style\\b.*?</style>', '', 'g'), '(?s)<!--.*?-->', '', 'g') AS h FROM pages),
            f AS (SELECT page_id, {_found_sql('title')} AS t, {_found_sql('a')} AS a, {_found_sql('p')} AS p FROM h)
            SELECT page_id, coalesce(t[1], '') AS title, len(a)::BIGINT AS n_anchors, md5(array_to_string(p, '|')) AS paragraphs_md5 FROM f""",
        "metric_cube": _SYSTEMS + " SELECT config, k, round(avg(value), 5) AS mean FROM recall GROUP BY CUBE (config, k)",
        "run_set_ops": _SCI_FIELDS + f""", a AS (SELECT query_id, table_id FROM ({run('description', 10)})), b AS (SELECT query_id, table_id FROM ({run('context', 10)}))
            SELECT 'both' AS op, * FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'first only', * FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'gold missed', * FROM (SELECT query_id, table_id FROM qrels EXCEPT SELECT * FROM a)""",
        "asof_index_version": """SELECT event_id, view_id FROM (SELECT *, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (
            PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS view_id FROM events) WHERE event_type = 'purchase'""",
        "tumbling_counts": window("date_trunc('hour', ts)") + " events GROUP BY ALL",
        "sliding_counts": window("s") + " (SELECT event_type, unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS s FROM events) GROUP BY ALL",
        "session_counts": """SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (
            SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (
            SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""",
        "click_qrels": "SELECT user_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS item, max(CASE event_type WHEN 'purchase' THEN 2 WHEN 'click' THEN 1 ELSE 0 END)::INTEGER AS grade FROM events GROUP BY ALL",
        "dedupe_events": "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY ALL",
        "interval_join": "SELECT v.event_id AS view_id, c.event_id AS click_id, v.user_id FROM events v JOIN events c ON v.user_id = c.user_id AND v.event_type = 'view' AND c.event_type = 'click' AND c.ts >= v.ts AND c.ts <= v.ts + INTERVAL 10 MINUTE",
    }
