"""Keyword search: statistics, BM25 over one or several fields, fusion.

Batch search starts from texts: the query terms, few and checked, are broadcast
to the token stream right after it is exploded, so only matching postings are
shuffled; document lengths come from array sizes before that. Statistics are
exact over all documents. ``build_index`` stores postings for interactive use.
"""

from __future__ import annotations

from dataclasses import dataclass, field as dataclass_field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions.analysis import Analyzer, WORDS

K1, B = 1.2, 0.75
#: More distinct query terms than this are joined by shuffle, not broadcast.
BROADCAST_TERMS = 200_000


def hinted(small: DataFrame, limit: int = BROADCAST_TERMS) -> DataFrame:
    """``small`` with a broadcast hint, if counting it up to the limit shows it is small."""
    return F.broadcast(small) if small.limit(limit + 1).count() <= limit else small


def idf(n_docs: Column, df: Column) -> Column:
    return F.log(F.lit(1.0) + (n_docs - df + F.lit(0.5)) / (df + F.lit(0.5)))


def term_score(tf: Column, dl: Column, avgdl: Column, n_docs: Column, df: Column, k1: float = K1, b: float = B) -> Column:
    """One term's share of a document's score."""
    length = F.lit(1.0 - b) + F.lit(b) * dl / F.when(avgdl > 0, avgdl).otherwise(F.lit(1.0))
    return idf(n_docs, df) * tf * F.lit(k1 + 1.0) / (tf + F.lit(k1) * length)


def tokenised(fields: DataFrame, analyzer: Analyzer = WORDS) -> DataFrame:
    """``fields`` (dataset, table_id, field, text) to (dataset, table_id, field, tokens, dl)."""
    return fields.select("dataset", "table_id", "field", analyzer.tokens(F.col("text")).alias("tokens")).withColumn("dl", F.size("tokens").cast("long"))


def field_stats(tokens: DataFrame) -> DataFrame:
    """Per dataset and field: documents and total length, as whole numbers."""
    return tokens.groupBy("dataset", "field").agg(F.count("*").alias("n_docs"), F.sum("dl").alias("sum_len"))


def postings(tokens: DataFrame, terms: DataFrame | None = None, analyzer: Analyzer = WORDS) -> DataFrame:
    """(dataset, field, term, table_id, tf, dl); with ``terms`` (dataset, term) only theirs."""
    rows = tokens.select("dataset", "field", "table_id", "dl", F.explode("tokens").alias("term"))
    if analyzer.kind == "word":
        rows = analyzer.finish(rows)
    if terms is not None:
        rows = rows.join(hinted(terms), ["dataset", "term"], "left_semi")
    return rows.groupBy("dataset", "field", "term", "table_id", "dl").agg(F.count("*").alias("tf"))


def term_stats(posted: DataFrame) -> DataFrame:
    return posted.groupBy("dataset", "field", "term").agg(F.count("*").alias("df"))


def query_terms(queries: DataFrame, analyzer: Analyzer = WORDS, query_tf: str = "distinct") -> DataFrame:
    """(dataset, query_id, term, qtf): each distinct term of a query, once or as often as it stands there."""
    rows = queries.select("dataset", "query_id", F.explode(analyzer.tokens(F.col("text"))).alias("term"))
    rows = analyzer.finish(rows)
    counted = rows.groupBy("dataset", "query_id", "term").agg(F.count("*").alias("qtf"))
    return counted if query_tf == "count" else counted.withColumn("qtf", F.lit(1).cast("long"))


@dataclass
class Index:
    """Postings and statistics of fields, and the analyzers that made them."""

    postings: DataFrame
    term_stats: DataFrame
    field_stats: DataFrame
    analyzers: dict[str, Analyzer] = dataclass_field(default_factory=dict)

    def analyzer(self, field: str) -> Analyzer:
        return self.analyzers.get(field, WORDS)

    def check(self, field: str, analyzer: Analyzer) -> None:
        if self.analyzer(field).id != analyzer.id:
            raise ValueError(f"field {field} was indexed by {self.analyzer(field).id}, not {analyzer.id}")


def build_index(fields: DataFrame, analyzers: dict[str, Analyzer] | None = None, terms: DataFrame | None = None) -> Index:
    """Index ``fields`` (dataset, table_id, field, text), each field by its analyzer."""
    analyzers = analyzers or {}
    parts = []
    kinds: dict[Analyzer, list[str]] = {}
    for name, analyzer in analyzers.items():
        kinds.setdefault(analyzer, []).append(name)
    others = fields.where(~F.col("field").isin(list(analyzers))) if analyzers else fields
    groups = [(others, WORDS)] + [(fields.where(F.col("field").isin(names)), a) for a, names in kinds.items()]
    for rows, analyzer in groups:
        tokens = tokenised(rows, analyzer)
        parts.append((postings(tokens, terms, analyzer), field_stats(tokens)))
    posted, stats = parts[0]
    for p, s in parts[1:]:
        posted, stats = posted.unionByName(p), stats.unionByName(s)
    return Index(posted, term_stats(posted), stats, analyzers)


def field_scores(queries: DataFrame, index: Index, fields: list[str] | None = None, k1: float = K1, b: float = B, query_tf: str = "distinct") -> DataFrame:
    """(dataset, query_id, table_id, field, score): BM25 of every matching document in every field."""
    names = fields or ["text"]
    kinds: dict[Analyzer, list[str]] = {}
    for name in names:
        kinds.setdefault(index.analyzer(name), []).append(name)
    out = None
    for analyzer, own in kinds.items():
        terms = query_terms(queries, analyzer, query_tf)
        hits = index.postings.where(F.col("field").isin(own)).join(hinted(terms), ["dataset", "term"])
        # one row per dataset and field; one per field and query term
        stats = index.field_stats.withColumn("avgdl", F.col("sum_len") / F.col("n_docs"))
        scored = hits.join(index.term_stats, ["dataset", "field", "term"]).join(hinted(stats, 10_000), ["dataset", "field"])
        value = term_score(F.col("tf"), F.col("dl"), F.col("avgdl"), F.col("n_docs"), F.col("df"), k1, b) * F.col("qtf")
        part = scored.groupBy("dataset", "query_id", "table_id", "field").agg(F.sum(value).alias("score"))
        out = part if out is None else out.unionByName(part)
    return out


def top_k(scores: DataFrame, k: int) -> DataFrame:
    """The k best documents of each query: score rounded, then smaller id."""
    best = Window.partitionBy("dataset", "query_id").orderBy(F.desc("score"), "table_id")
    rounded = scores.withColumn("score", F.round("score", 6)).where("score > 0")
    return rounded.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("dataset", "query_id", "table_id", "score", "rank")


def single(queries: DataFrame, index: Index, field: str = "text", k: int = 100, k1: float = K1, b: float = B, query_tf: str = "distinct") -> DataFrame:
    """Search of one field."""
    return top_k(field_scores(queries, index, [field], k1, b, query_tf), k)


def multi(queries: DataFrame, index: Index, fields=("description", "expansion", "context"), tie: float = 0.1, k: int = 100, k1: float = K1, b: float = B) -> DataFrame:
    """The best field's score plus ``tie`` times the sum of the others', in one aggregation."""
    scores = field_scores(queries, index, list(fields), k1, b)
    best, total = F.max("score"), F.sum("score")
    return top_k(scores.groupBy("dataset", "query_id", "table_id").agg((best + F.lit(tie) * (total - best)).alias("score")), k)


@dataclass(frozen=True)
class Run:
    """One configuration of a search: its fields, the tie-breaking share of all but the best, and the parameters."""

    fields: tuple[str, ...] = ("text",)
    tie: float = 0.1
    k1: float = K1
    b: float = B


#: Distinct queries held against all documents at once, documents scored at once, and postings a task collects for that.
QUERY_BLOCK, DOC_BLOCK, POSTING_BLOCK = 1 << 15, 1 << 12, 1 << 20


def runs_top_k(queries: DataFrame, index: Index, runs: dict[str, Run], k: int = 100, query_block: int = QUERY_BLOCK) -> DataFrame:
    """(dataset, config, query_id, table_id, score, rank): the k best of every query in every run, from one pass over the postings.

    Postings of the query terms are dealt by table, each once, so a task has
    whole documents. It scores a block of them against a block of distinct
    queries, whose terms are broadcast, and keeps k of each: no pair of query
    and document leaves it. Queries of the same terms are scored once.
    """
    names = sorted({f for run in runs.values() for f in run.fields})
    if len({index.analyzer(f) for f in names}) != 1:
        raise ValueError("fields of one pass share an analyzer")
    asked = query_terms(queries, index.analyzer(names[0]))
    bags = asked.groupBy("dataset", "query_id").agg(F.array_sort(F.collect_list("term")).alias("terms"))
    distinct = bags.groupBy("dataset", "terms").agg(F.min("query_id").alias("query_id"))
    n_blocks = max(1, -(-distinct.count() // query_block))
    parts = [_scored_block(distinct.where(F.pmod(F.xxhash64("dataset", "query_id"), F.lit(n_blocks)) == i), index, names, runs, k) for i in range(n_blocks)]
    best = Window.partitionBy("dataset", "config", "query_id").orderBy(F.desc("score"), "table_id")
    found = reduce(DataFrame.unionByName, parts).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    alike = bags.join(distinct.withColumnRenamed("query_id", "asked_id"), ["dataset", "terms"]).select("dataset", "query_id", "asked_id")
    return found.withColumnRenamed("query_id", "asked_id").join(alike, ["dataset", "asked_id"]).select("dataset", "config", "query_id", "table_id", "score", "rank")


def _scored_block(queries: DataFrame, index: Index, names: list[str], runs: dict[str, Run], k: int) -> DataFrame:
    """(dataset, config, query_id, table_id, score): each block of documents' k best of every query of a bounded block."""
    spark = queries.sparkSession
    held = queries.select("dataset", "query_id", "terms").toArrow()
    keys: dict[tuple, int] = {}
    asked = [(d, q, np.array([keys.setdefault((d, t), len(keys)) for t in terms], np.int64)) for d, q, terms in zip(*(held.column(c).to_pylist() for c in ("dataset", "query_id", "terms")))]
    numbered = spark.createDataFrame(pa.table({"dataset": pa.array([d for d, _ in keys], pa.string()), "term": pa.array([t for _, t in keys], pa.string()), "key": pa.array(list(keys.values()), pa.int64())}))
    posted = index.postings.where(F.col("field").isin(names)).join(hinted(numbered), ["dataset", "term"])
    number = F.create_map(*[F.lit(x) for i, f in enumerate(names) for x in (f, i)])
    tasks = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows = posted.select("dataset", number[F.col("field")].alias("field"), "key", "table_id", F.col("tf").cast("int").alias("tf"), F.col("dl").cast("int").alias("dl"))
    dealt = rows.repartition(tasks, "dataset", "table_id").sortWithinPartitions("dataset", "table_id")
    # one number a field and query term; one row a field
    df = index.term_stats.where(F.col("field").isin(names)).join(hinted(numbered), ["dataset", "term"]).select(number[F.col("field")].alias("field"), "key", "df").toArrow()
    size = {(r.dataset, names.index(r.field)): (r.n_docs, r.sum_len) for r in index.field_stats.where(F.col("field").isin(names)).collect()}
    frequency = np.ones((len(names), max(1, len(keys))))
    frequency[df.column("field").to_numpy(), df.column("key").to_numpy()] = df.column("df").to_numpy()
    shared = spark.sparkContext.broadcast((asked, frequency, size))
    places = sorted({(names.index(f), run.k1, run.b) for run in runs.values() for f in run.fields})
    wanted = [(name, [places.index((names.index(f), run.k1, run.b)) for f in run.fields], run.tie) for name, run in runs.items()]

    def score(dataset, part):
        asked, frequency, size = shared.value
        ids, doc = np.unique(part["table_id"], return_inverse=True)
        weights = {}
        for at, (field, k1, b) in enumerate(places):
            own = np.flatnonzero(part["field"] == field)
            if not len(own):
                continue
            own = own[np.argsort(part["key"][own], kind="stable")]
            n_docs, total = size[dataset, field]
            tf, dl, df = part["tf"][own].astype(float), part["dl"][own], frequency[field, part["key"][own]]
            average = (total or 0) / n_docs
            length = (1.0 - b) + b * dl / (average if average > 0 else 1.0)
            value = np.log(1.0 + (n_docs - df + 0.5) / (df + 0.5)) * tf * (k1 + 1.0) / (tf + k1 * length)
            terms, first = np.unique(part["key"][own], return_index=True)
            for t, x, y in zip(terms.tolist(), first.tolist(), [*first[1:].tolist(), len(own)]):
                weights.setdefault(t, []).append((at, doc[own[x:y]], value[x:y]))
        out = [[], [], [], []]
        for query, (d, _, terms) in enumerate(asked):
            if d != dataset:
                continue
            scores = np.zeros((len(places), len(ids)))
            for t in terms.tolist():
                for at, where, value in weights.get(t, ()):
                    scores[at, where] += value  # a term stands once in a document's field
            for config, (_, parts, tie) in enumerate(wanted):
                total = scores[parts[0]] if len(parts) == 1 else (lambda s: s.max(0) + tie * (s.sum(0) - s.max(0)))(scores[parts])
                # what may be among the k best once rounded
                least = max(5e-7, np.partition(total, -k)[-k] - 1e-6 if len(total) > k else 0.0)
                at = np.flatnonzero(total >= least)
                rounded = np.round(total[at], 6)
                order = np.lexsort((ids[at], -rounded))[:k]
                order = order[rounded[order] > 0]
                for column, x in zip(out, (np.full(len(order), config), np.full(len(order), query), ids[at[order]], rounded[order])):
                    column.append(x)
        config, query, table, value = (np.concatenate(x) if x else np.zeros(0, int) for x in out)
        return pa.RecordBatch.from_arrays([pa.array([dataset] * len(query), pa.string()), pa.array([wanted[c][0] for c in config.tolist()], pa.string()), pa.array([asked[q][1] for q in query.tolist()], pa.int64()), pa.array(table, pa.int64()), pa.array(value, pa.float64())], ["dataset", "config", "query_id", "table_id", "score"])

    def run(batches):
        for dataset, part in _document_blocks(batches):
            yield score(dataset, part)

    return dealt.mapInArrow(run, "dataset string, config string, query_id long, table_id long, score double")


def _document_blocks(batches):
    """(dataset, columns) of whole documents, from postings sorted by dataset and table, at most ``DOC_BLOCK`` tables each."""
    columns = ("field", "key", "table_id", "tf", "dl")

    def cut(rows: pa.Table, last: bool):
        """Blocks of ``rows``, and the rows of the last document, which may go on."""
        rows = rows.combine_chunks()
        code = rows.column("dataset").chunk(0).dictionary_encode().indices.to_numpy()
        ids = rows.column("table_id").to_numpy()
        begins = np.flatnonzero(np.r_[True, (ids[1:] != ids[:-1]) | (code[1:] != code[:-1])])
        end = rows.num_rows if last else int(begins[-1])
        begins = begins[begins < end]
        blocks, start = [], 0
        while start < len(begins):
            stop = min(start + DOC_BLOCK, len(begins))
            other = np.flatnonzero(code[begins[start:stop]] != code[begins[start]])
            stop = start + int(other[0]) if len(other) else stop
            x, y = int(begins[start]), int(begins[stop]) if stop < len(begins) else end
            blocks.append((rows.column("dataset")[x].as_py(), {c: rows.column(c).slice(x, y - x).to_numpy() for c in columns}))
            start = stop
        return blocks, rows.slice(end)

    held, n = [], 0
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            n += batch.num_rows
        if n >= POSTING_BLOCK:
            blocks, rest = cut(pa.Table.from_batches(held), False)
            yield from blocks
            held, n = rest.combine_chunks().to_batches(), rest.num_rows
    if n:
        yield from cut(pa.Table.from_batches(held), True)[0]


def multi_runs(queries: DataFrame, index: Index, runs: dict[str, tuple[list[str], float]], k: int = 100, k1: float = K1, b: float = B) -> DataFrame:
    """``multi`` for many configurations (name: fields, tie) from one pass: (dataset, config, query_id, table_id, score, rank)."""
    found = runs_top_k(queries, index, {name: Run(tuple(fields), tie, k1, b) for name, (fields, tie) in runs.items()}, k)
    return found.select("dataset", "config", "query_id", "table_id", "score", "rank")


def weighted(queries: DataFrame, index: Index, weights: dict[str, float], k: int = 50) -> DataFrame:
    """Sum of field scores by weight; the fields may have different analyzers."""
    weight = F.create_map(*[F.lit(x) for pair in weights.items() for x in pair])
    scores = field_scores(queries, index, list(weights)).withColumn("score", F.col("score") * weight[F.col("field")])
    return top_k(scores.groupBy("dataset", "query_id", "table_id").agg(F.sum("score").alias("score")), k)


def explain(queries: DataFrame, index: Index, query_id: int, table_id: int, field: str = "text", k1: float = K1, b: float = B) -> DataFrame:
    """Each term's contribution to one hit."""
    terms = query_terms(queries.where(F.col("query_id") == query_id), index.analyzer(field))
    stats = index.field_stats.withColumn("avgdl", F.col("sum_len") / F.col("n_docs"))
    rows = index.postings.where((F.col("table_id") == table_id) & (F.col("field") == field)).join(terms, ["dataset", "term"]).join(index.term_stats, ["dataset", "field", "term"]).join(stats, ["dataset", "field"])
    value = term_score(F.col("tf"), F.col("dl"), F.col("avgdl"), F.col("n_docs"), F.col("df"), k1, b)
    return rows.select("query_id", "table_id", "term", "tf", "df", F.round(value, 6).alias("contribution"))


def dense(queries: DataFrame, vectors: DataFrame, k: int = 10, block: int = 8_192) -> DataFrame:
    """Exact cosine search: (query_id, embedding) against (table_id, embedding); a query's own id is no answer.

    Queries go in blocks of at most about ``block``, each of which is broadcast
    and held against all vectors; a task keeps the k best of each query, so no
    other pair leaves it. Vectors that are null, zero, of another length, or hold
    nulls take no part; rows of one query id count once, the least in array order.
    """
    usable = lambda rows, key: rows.where(f"{key} IS NOT NULL AND size(embedding) > 0").where(~F.exists("embedding", lambda x: x.isNull() | F.isnan(x)) & F.exists("embedding", lambda x: x != 0))
    asked = usable(queries, "query_id").groupBy("query_id").agg(F.min("embedding").alias("embedding"))
    n_blocks = max(1, -(-asked.count() // block))
    parts = [_dense_block(asked.where(F.pmod(F.xxhash64("query_id"), F.lit(n_blocks)) == i), usable(vectors, "table_id"), k) for i in range(n_blocks)]
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "table_id")
    return reduce(DataFrame.unionByName, parts).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)


def _dense_block(queries: DataFrame, vectors: DataFrame, k: int) -> DataFrame:
    """(query_id, table_id, score): each task's k best of every query of a bounded block."""
    rows = queries.toArrow()
    sizes = rows.column("embedding").combine_chunks().value_lengths().to_numpy()
    lists = rows.column("embedding").to_pylist()
    ids = rows.column("query_id").to_numpy()
    by_size = {}
    for n in set(sizes.tolist()):
        at = np.flatnonzero(sizes == n)
        data = np.array([lists[i] for i in at], float)
        by_size[n] = ids[at], data / np.linalg.norm(data, axis=1, keepdims=True)
    shared = vectors.sparkSession.sparkContext.broadcast(by_size)

    def run(batches):
        held = {n: (np.full((len(q), k), -np.inf), np.full((len(q), k), -1, np.int64)) for n, (q, _) in shared.value.items()}
        for batch in batches:
            lists = batch.column("embedding")
            sizes = lists.value_lengths().to_numpy(zero_copy_only=False)
            for n, (q, unit) in shared.value.items():
                at = np.flatnonzero(sizes == n)
                for start in range(0, len(at), 2_048):
                    part = at[start : start + 2_048]
                    data = lists.take(pa.array(part)).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(part), n)
                    own = batch.column("table_id").take(pa.array(part)).to_numpy(zero_copy_only=False)
                    scores = np.round(unit @ (data / np.linalg.norm(data, axis=1, keepdims=True)).T, 6)
                    scores[q[:, None] == own[None, :]] = -np.inf
                    scores = np.concatenate((held[n][0], scores), 1)
                    names = np.concatenate((held[n][1], np.broadcast_to(own, (len(q), len(own)))), 1)
                    order = np.lexsort((names, -scores), axis=1)[:, :k]
                    held[n] = np.take_along_axis(scores, order, 1), np.take_along_axis(names, order, 1)
        for n, (scores, names) in held.items():
            found = np.isfinite(scores)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(shared.value[n][0], found.sum(1))), pa.array(names[found]), pa.array(scores[found])], ["query_id", "table_id", "score"])

    return vectors.select(F.col("table_id").cast("long").alias("table_id"), "embedding").mapInArrow(run, "query_id long, table_id long, score double")


def fuse(first: DataFrame, second: DataFrame, how: str = "rrf", k: int = 10, constant: int = 60, weight: float = 0.5) -> DataFrame:
    """Two hit lists (query_id, table_id, score, rank) as one: reciprocal ranks or a weighted sum."""
    a = first.select("query_id", "table_id", F.col("score").alias("s1"), F.col("rank").alias("r1"))
    b = second.select("query_id", "table_id", F.col("score").alias("s2"), F.col("rank").alias("r2"))
    zero = F.lit(0.0)
    if how == "rrf":
        value = F.coalesce(1.0 / (constant + F.col("r1")), zero) + F.coalesce(1.0 / (constant + F.col("r2")), zero)
    else:
        value = F.lit(weight) * F.coalesce("s1", zero) + F.lit(1 - weight) * F.coalesce("s2", zero)
    scored = a.join(b, ["query_id", "table_id"], "full").select("query_id", "table_id", F.round(value, 6).alias("score"))
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "table_id")
    return scored.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
