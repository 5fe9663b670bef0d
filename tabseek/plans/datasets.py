"""Stand-in datasets: tables, queries and relevance judgements from the given tables.

``known``: documents searched by benchmark passages, containment as relevance.
``sci_s`` / ``sci_l``: English documents whose first half is visible and whose
hidden second half judges topic words. ``ent``: the catalogue of the given
tables and slices of them, with fixed queries. ``gov``: labelled documents by
tasks. ``web_a`` / ``web_b``: documents and pages by page titles, without names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..functions.analysis import tally, words
from ..operators.search import hinted
from ..sources.pages import context as page_context
from .scratch import materialise, stands

#: The catalogue, in id order, and its columns.
CATALOGUE = {
    "region": ["r_regionkey", "r_name"],
    "nation": ["n_nationkey", "n_name", "n_regionkey"],
    "customer": ["c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"],
    "supplier": ["s_suppkey", "s_name", "s_nationkey", "s_acctbal"],
    "part": ["p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"],
    "orders": ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"],
    "lineitem": ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"],
    "events": ["event_id", "ts", "user_id", "event_type", "value", "props"],
    "documents": ["doc_id", "text", "lang", "source", "n_chars"],
    "embeddings": ["vec_id", "embedding", "label"],
    "pages": ["page_id", "url", "html"],
    "benchmark": ["item_id", "text"],
    "labels": ["doc_id", "quality", "toxic"],
    "conversations": ["conv_id", "turn", "role", "text"],
}
#: Query texts and the base tables relevant to them.
ENT_QUERIES = [
    (1, "customer account balance", ["customer"]),
    (2, "supplier account balance", ["supplier"]),
    (3, "part retail price", ["part"]),
    (4, "total price of an order", ["orders"]),
    (5, "line item discount and tax", ["lineitem"]),
    (6, "shipping date of line items", ["lineitem"]),
    (7, "market segment of customers", ["customer"]),
    (8, "names of nations and regions", ["nation", "region"]),
    (9, "click events by user", ["events"]),
    (10, "purchase event value", ["events"]),
    (11, "part brand and type", ["part"]),
    (12, "order priority and status", ["orders"]),
    (13, "document language and source", ["documents"]),
    (14, "quality and toxicity label", ["labels"]),
    (15, "web page address and content", ["pages"]),
]


@dataclass
class Dataset:
    """tables (dataset, table_id, ...), queries (dataset, query_id, text), qrels (dataset, query_id, table_id, grade)."""

    tables: DataFrame
    queries: DataFrame
    qrels: DataFrame


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def known(spark: SparkSession, sf_dir: str) -> Dataset:
    """Documents by benchmark passages; relevant are documents that contain a passage's first 60 characters."""
    docs, items = read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark")
    tables = docs.select(F.lit("known").alias("dataset"), F.col("doc_id").alias("table_id"), F.lit("text").alias("field"), "text")
    queries = items.select(F.lit("known").alias("dataset"), F.col("item_id").alias("query_id"), "text")
    pairs = containing(docs, items.select("item_id", F.substring("text", 1, 60).alias("head")))
    return Dataset(tables, queries, pairs.select(F.lit("known").alias("dataset"), F.col("item_id").alias("query_id"), F.col("doc_id").alias("table_id"), F.lit(1).alias("grade")))


def containing(docs: DataFrame, heads: DataFrame) -> DataFrame:
    """(doc_id, item_id) of documents whose text contains a head (item_id, head).

    A head's longest inner word stands whole in such a text, so words are joined
    by equality and only what they bring together is compared. A head of fewer
    than three words has no inner word: only such heads meet every text.
    """
    inner = F.split("head", " ")
    inner = F.filter(F.slice(inner, 2, F.greatest(F.size(inner) - 2, F.lit(0))), lambda w: w != "")
    keyed = heads.where("head <> ''").withColumn("word", F.array_max(F.transform(inner, lambda w: F.struct(F.length(w).alias("n"), w.alias("w"))))["w"])
    whole = keyed.where("word IS NOT NULL")
    words_of = docs.select("doc_id", "text", F.explode(F.array_distinct(F.split("text", " "))).alias("word"))
    found = words_of.join(hinted(whole), "word").where(F.contains("text", "head")).select("doc_id", "item_id")
    short = keyed.where("word IS NULL")
    if short.isEmpty():
        return found
    return found.unionByName(docs.join(hinted(short), F.contains(docs["text"], F.col("head"))).select("doc_id", "item_id"))


_cut: dict[tuple, DataFrame] = {}


def _once(spark: SparkSession, sf_dir: str, name: str, make) -> DataFrame:
    """What ``make`` gives, written once a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _cut or not stands(_cut[key]):
        _cut[key] = materialise(make(), name)
    return _cut[key]


def document_words(spark: SparkSession, sf_dir: str, english: bool = False) -> DataFrame:
    """(doc_id, lang, source, line, body): the words of each document's first line and of the rest, cut once a session; ``english`` needs no others."""
    every = _cut.get((spark.sparkContext.applicationId, sf_dir, "document-words"))
    if english and every is not None and stands(every):
        return every.where("lang = 'en'")
    docs = read(spark, sf_dir, "documents")
    lines = F.split("text", "\n", 2)
    make = lambda: spread(docs.where("lang = 'en'") if english else docs).select("doc_id", "lang", "source", words(lines[0]).alias("line"), words(F.get(lines, F.lit(1))).alias("body"))
    return _once(spark, sf_dir, "english-words" if english else "document-words", make)


def page_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, title, line, body): each page's title, its words, and those of paragraphs without it, cut once a session."""

    def make():
        body = F.array_join(F.filter("paragraphs", lambda p: ~F.contains(p, F.col("title"))), " ")
        rows = page_context(spread(read(spark, sf_dir, "pages")))
        return rows.select("page_id", "title", words(F.col("title")).alias("line"), words(body).alias("body"))

    return _once(spark, sf_dir, "page-words", make)


def sci(spark: SparkSession, sf_dir: str, large: bool = True, cut: DataFrame | None = None) -> Dataset:
    """English documents by topic words; a word counted twice or more in the hidden half makes one relevant.

    ``cut`` (doc_id, source, w) has the English documents' words, if they are cut already.
    """
    name, limit = ("sci_l", 15) if large else ("sci_s", 20)
    if cut is None:
        cut = read(spark, sf_dir, "documents").where("lang = 'en'").select("doc_id", "source", words(F.col("text")).alias("w"))
    docs = cut.where(f"doc_id % 5 {'<>' if large else '='} 0")
    split = docs.select(F.lit(name).alias("dataset"), F.col("doc_id").alias("table_id"), "source", "w").withColumn("half", F.floor(F.size("w") / 2).cast("int"))
    visible = F.slice("w", 1, F.col("half"))
    tables = split.select("dataset", "table_id", F.col("source").alias("table_name"), F.slice(F.array_distinct(visible), 1, 12).alias("columns"), visible.alias("vis"))
    unseen = F.slice("w", F.col("half") + 1, F.greatest(F.size("w"), F.lit(1)))
    # a document's words are counted where it lies
    hidden = lambda keep: split.select("table_id", F.explode(tally(F.filter(unseen, keep))).alias("h")).select("table_id", "h.term", "h.tf")
    n = tables.agg(F.count("*").alias("n"))
    stats = hidden(lambda w: F.length(w) >= 5).groupBy("term").agg(F.count("*").alias("df"), F.sum((F.col("tf") >= 2).cast("int")).alias("strong")).crossJoin(F.broadcast(n))
    topics = stats.where("df >= 0.03 * n AND df <= 0.35 * n AND strong >= 2").select("term", F.md5("term").alias("h")).orderBy("h").limit(limit)
    # a top-k report of fixed size: as literals it selects before anything is grouped, and is found once
    found = [r.term for r in topics.collect()]
    queries = spark.createDataFrame([(name, i, t) for i, t in enumerate(found, 1)], "dataset string, query_id long, text string")
    qrels = hidden(lambda w: w.isin(found)).where("tf >= 2").join(F.broadcast(queries), F.col("term") == F.col("text")).select("dataset", "query_id", "table_id", F.lit(1).alias("grade"))
    return Dataset(tables, queries, qrels)


def abbreviate(word):
    """A cryptic form of a word, as a column name has it: its first four letters and its last two."""
    return F.when(F.length(word) <= 6, word).otherwise(F.concat(F.substring(word, 1, 4), F.substring(word, -2, 2)))


def glossary(words_: DataFrame) -> DataFrame:
    """(short, word) of (word, n): the most frequent word of each abbreviation, of equals the first."""
    best = F.max(F.struct("n", F.expr("transform(split(word, ''), c -> -ascii(c))").alias("o"), "word"))
    return words_.withColumn("short", abbreviate(F.col("word"))).groupBy("short").agg(best["word"].alias("word"))


def named(texts: DataFrame, n_names: int = 60) -> DataFrame:
    """``texts`` (dataset, table_id, table_name, visible, context, rows) as tables with cryptic and expanded names.

    A table's columns are its first distinct visible words, abbreviated; they are
    expanded by the glossary of all visible words, which picks one word an
    abbreviation and so errs as a model does. ``cryptic`` and ``expanded`` hold
    the words of columns that a description may use, ``around`` those of name and
    context, which it restates. Of the rows, ``seen`` has the first words and
    ``topics`` the ten most frequent of all.
    """
    none = F.array().cast("array<string>")
    around = F.concat(F.coalesce(words(F.col("table_name")), none), F.coalesce(words(F.col("context")), none))
    short = F.transform(F.slice(F.array_distinct("visible"), 1, n_names), abbreviate)
    counted = F.sort_array(F.transform(tally(F.col("rows")), lambda x: F.struct((-x["tf"]).alias("n"), x["term"].alias("w"))))
    rows = texts.select("dataset", "table_id", "table_name", "context", F.slice("rows", 1, 20).alias("seen"), F.transform(F.slice(counted, 1, 10), lambda x: x["w"]).alias("topics"), short.alias("columns"), around.alias("around"))
    # whole texts are read twice, once for this and once for the glossary, and shuffled never
    rows = materialise(rows, "named")
    known = materialise(glossary(texts.select(F.explode("visible").alias("word")).groupBy("word").agg(F.count("*").alias("n"))), "glossary")
    meant = rows.select("dataset", "table_id", F.posexplode("columns").alias("pos", "short")).join(hinted(known), "short")
    expanded = meant.groupBy("dataset", "table_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "word"))), lambda x: x["word"]).alias("meaning"))
    joined = rows.join(expanded, ["dataset", "table_id"], "left")
    return joined.select("*", F.col("columns").alias("cryptic"), F.coalesce("meaning", none).alias("expanded"))


def gov(spark: SparkSession, sf_dir: str) -> Dataset:
    """Labelled documents of six sources by two queries a source, with grades 1 to 3; the first line is context."""
    judged = materialise(gov_judgements(spark, sf_dir), "judged")
    docs = document_words(spark, sf_dir).join(judged.select(F.col("table_id").alias("doc_id")), "doc_id", "left_semi")
    docs = materialise(docs.select("doc_id", "source", "line", F.concat("line", "body").alias("w")), "gov-words")
    w = F.col("w")
    tables = named(docs.select(F.lit("gov").alias("dataset"), F.col("doc_id").alias("table_id"), F.col("source").alias("table_name"), w.alias("visible"), F.array_join("line", " ").alias("context"), w.alias("rows")))
    # twenty wordings a task from words of its documents, of which the two most distinct ask
    picked = docs.select(F.col("source").alias("task"), F.explode(F.array_distinct(w)).alias("word")).where("length(word) >= 5").groupBy("task", "word").agg(F.count("*").alias("n"))
    r = F.row_number().over(Window.partitionBy("task").orderBy(F.desc("n"), F.md5("word"))) - 1
    wordings = picked.withColumn("r", r).where("r < 40").groupBy("task", F.floor(F.col("r") / 2).alias("i")).agg(F.concat_ws(" ", "task", F.array_join(F.array_sort(F.collect_list("word")), " ")).alias("text"))
    wordings = materialise(wordings.select("task", (F.substring("task", 4, 2).cast("long") * 100 + F.col("i")).alias("query_id"), "text"), "wordings")
    # computed in the library, which builds on this module
    from ..operators.benchmark import distinct_pair, task_to_query

    pair = distinct_pair(wordings).select("task", F.explode(F.array("query_id", "other_id")).alias("query_id"))
    asked = materialise(wordings.join(pair, ["task", "query_id"], "left_semi"), "asked")
    qrels = task_to_query(judged, asked).select(F.lit("gov").alias("dataset"), "query_id", "table_id", "grade")
    return Dataset(tables, asked.select(F.lit("gov").alias("dataset"), "query_id", "text"), qrels)


def _titles(spark: SparkSession, sf_dir: str, n: int = 60) -> DataFrame:
    """(query_id, text) of the first distinct page titles of 20 characters and more; a query set of fixed size."""
    titles = page_words(spark, sf_dir).where("length(title) >= 20").groupBy(F.col("title").alias("text")).agg(F.min("page_id").alias("query_id"))
    return titles.orderBy("query_id").limit(n).select("query_id", "text")


def titles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``_titles``, found once a session."""
    return _once(spark, sf_dir, "titles", lambda: _titles(spark, sf_dir))


def _odd(words_):
    return F.array_join(F.filter(words_, lambda _, i: i % 2 == 0), " ")


def _runs(words_, n: int = 5, begins: list[str] | None = None):
    """Distinct runs of five words, as text; with ``begins`` only those that begin with one of these words."""
    at = F.sequence(F.lit(1), F.greatest(F.size(words_) - n + 1, F.lit(1)))
    if begins is not None:
        at = F.filter(at, lambda i: F.get(words_, i - 1).isin(begins))
    return F.array_distinct(F.transform(at, lambda i: F.array_join(F.slice(words_, i, n), " ")))


def spread(rows: DataFrame) -> DataFrame:
    """``rows``, dealt to all cores if they come in fewer partitions, as a single file's do."""
    cores = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(cores) if rows.rdd.getNumPartitions() < cores else rows


def _web(spark: SparkSession, sf_dir: str, name: str, texts: DataFrame) -> Dataset:
    """Tables without names from words (table_id, line, body): grade 2 if a title opens the line, 1 if a run of five words of it stands in line or body."""
    asked = titles(spark, sf_dir)
    queries = asked.select(F.lit(name).alias("dataset"), "query_id", "text")
    line, body = F.col("line"), F.col("body")
    tables = named(texts.select(F.lit(name).alias("dataset"), "table_id", F.lit(None).cast("string").alias("table_name"), body.alias("visible"), _odd(line).alias("context"), body.alias("rows")))
    wanted = asked.select("query_id", words(F.col("text")).alias("w")).where("size(w) >= 2")
    heads = wanted.select("query_id", F.size("w").alias("n"), F.array_join("w", " ").alias("head"))
    opening = texts.select("table_id", line.alias("w")).join(hinted(heads.select("n").distinct()), F.col("n") <= F.size("w"))
    two = opening.select("table_id", "n", F.array_join(F.slice("w", F.lit(1), F.col("n")), " ").alias("head")).join(hinted(heads), ["n", "head"]).select("query_id", "table_id", F.lit(2).alias("grade"))
    runs = wanted.where("size(w) >= 5").select("query_id", F.explode(_runs(F.col("w"))).alias("run"))
    # the first words of a query set of fixed size: only runs that begin with one of them can be a title's
    begins = [r.word for r in runs.select(F.substring_index("run", " ", 1).alias("word")).distinct().collect()]
    one = texts.select("table_id", F.concat(line, body).alias("w")).where("size(w) >= 5").select("table_id", F.explode(_runs(F.col("w"), begins=begins)).alias("run")).join(hinted(runs), "run").select("query_id", "table_id", F.lit(1).alias("grade"))
    qrels = two.unionByName(one).groupBy("query_id", "table_id").agg(F.max("grade").alias("grade")).select(F.lit(name).alias("dataset"), "query_id", "table_id", "grade")
    return Dataset(tables, queries, qrels)


def web_a(spark: SparkSession, sf_dir: str) -> Dataset:
    """All documents by page titles: the thinned first line is context, the rest the table."""
    return _web(spark, sf_dir, "web_a", document_words(spark, sf_dir).select(F.col("doc_id").alias("table_id"), "line", "body"))


def web_b(spark: SparkSession, sf_dir: str) -> Dataset:
    """All pages by their titles: the thinned title is context, paragraphs without it the table."""
    return _web(spark, sf_dir, "web_b", page_words(spark, sf_dir).select(F.col("page_id").alias("table_id"), "line", "body"))


def sci_named(spark: SparkSession, sf_dir: str, large: bool = True) -> Dataset:
    """A topic dataset with cryptic names; there is no context."""
    cut = document_words(spark, sf_dir, english=True).select("doc_id", "source", F.concat("line", "body").alias("w"))
    data = sci(spark, sf_dir, large, cut)
    texts = data.tables.select("dataset", "table_id", "table_name", F.col("vis").alias("visible"), F.lit(None).cast("string").alias("context"), F.col("vis").alias("rows"))
    return Dataset(named(texts), data.queries, data.qrels)


def ent_named(spark: SparkSession, sf_dir: str) -> Dataset:
    """The catalogue, its names expanded by the lexicon; rows are the values of no table, so there are none."""
    from ..operators import names

    data = ent(spark, sf_dir)
    columns, heads = names.expand(data.tables), names.expand(data.tables, "table")
    text = names.expansion_field(heads.withColumn("pos", F.col("pos") - 1).unionByName(columns))
    raw = F.flatten(F.transform(F.concat(F.array("table_name"), F.col("columns")), names.split_name))
    tables = data.tables.withColumn("cryptic", raw).join(text, ["dataset", "table_id"], "left").withColumn("expanded", words(F.col("text")))
    return Dataset(tables.select("dataset", "table_id", "table_name", F.lit(None).cast("string").alias("context"), F.array().cast("array<string>").alias("seen"), F.array().cast("array<string>").alias("topics"), F.array().cast("array<string>").alias("around"), "columns", "cryptic", "expanded"), data.queries, data.qrels)


#: The six stand-ins, by name.
SIX = {
    "ent": ent_named,
    "sci_s": lambda spark, sf_dir: sci_named(spark, sf_dir, False),
    "sci_l": sci_named,
    "gov": gov,
    "web_a": web_a,
    "web_b": web_b,
}


def gov_judgements(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Task judgements (task, table_id, grade): same source 1, of quality 2, and not toxic 3."""
    docs, labels = read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")
    tasks = [f"src{i}" for i in range(6)]
    grade = F.when((F.col("quality") == 1) & (F.col("toxic") == 0), 3).when(F.col("quality") == 1, 2).otherwise(1)
    return docs.select("doc_id", "source", "n_chars").join(labels, "doc_id").where(F.col("source").isin(tasks)).select(F.col("source").alias("task"), F.col("doc_id").alias("table_id"), grade.alias("grade"), "n_chars")


def ent(spark: SparkSession, sf_dir: str) -> Dataset:
    """The catalogue and slices of customer, supplier, part, orders and events."""
    base = [(i, t, t, c) for i, (t, c) in enumerate(CATALOGUE.items())]
    rows = spark.createDataFrame(base, "table_id long, table_name string, base string, columns array<string>")

    def slices(table: str, column, offset: int, prefix: str) -> DataFrame:
        keys = read(spark, sf_dir, table).select(column.alias("k")).distinct()
        columns = F.array(*map(F.lit, CATALOGUE[table]))
        return keys.select((F.lit(offset) + F.col("k")).cast("long").alias("table_id"), F.format_string(f"{prefix}%02d" if prefix[0] != "o" else f"{prefix}%d", F.col("k").cast("int")).alias("table_name"), F.lit(table).alias("base"), columns.alias("columns"))

    event_types = read(spark, sf_dir, "events").select("event_type").distinct().select(F.dense_rank().over(Window.orderBy("event_type")).alias("i"), "event_type")
    event_rows = event_types.select((F.lit(499) + F.col("i")).cast("long").alias("table_id"), F.concat(F.lit("evt_"), "event_type").alias("table_name"), F.lit("events").alias("base"), F.array(*map(F.lit, CATALOGUE["events"])).alias("columns"))
    all_rows = (
        rows.unionByName(slices("customer", F.col("c_nationkey"), 100, "cust_n"))
        .unionByName(slices("supplier", F.col("s_nationkey"), 200, "supp_n"))
        .unionByName(slices("part", F.regexp_extract("p_brand", "([0-9]+)", 1).cast("int"), 300, "part_b"))
        .unionByName(slices("orders", F.substring("o_orderpriority", 1, 1).cast("int"), 400, "ord_p"))
        .unionByName(event_rows)
    )
    tables = all_rows.select(F.lit("ent").alias("dataset"), "table_id", "table_name", "base", "columns")
    queries = spark.createDataFrame([("ent", i, t) for i, t, _ in ENT_QUERIES], "dataset string, query_id long, text string")
    judged = spark.createDataFrame([(i, b) for i, _, bases in ENT_QUERIES for b in bases], "query_id long, base string")
    qrels = tables.join(F.broadcast(judged), "base").where(~((F.col("query_id") == 9) & (F.col("table_id") >= 500) & (F.col("table_name") != "evt_click")) & ~((F.col("query_id") == 10) & (F.col("table_id") >= 500) & (F.col("table_name") != "evt_purchase")))
    return Dataset(tables, queries, qrels.select("dataset", "query_id", "table_id", F.lit(1).alias("grade")))
