"""Candidate descriptions, their ranking, and preference pairs.

Every gold table has K candidates; all others have one. A candidate is scored by
the mean BM25 over the queries its table is relevant to. The corpora in which
the candidates compete differ from one shared default corpus by a few documents
only, so their statistics are the shared ones plus a correction per table:
nothing is indexed twice.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions.analysis import WORDS, Analyzer
from ..plans.scratch import materialise
from .search import B, K1, hinted, query_terms, term_score

DEFAULT_SEED = 42


def gold(qrels: DataFrame) -> DataFrame:
    """(dataset, table_id, n_queries) of tables relevant to some query."""
    return qrels.where("grade > 0").groupBy("dataset", "table_id").agg(F.count_distinct("query_id").alias("n_queries"))


def template_bodies(k: int) -> Column:
    """The first ``k`` template candidates from columns ``vis`` and ``columns``, as an array."""
    vis = F.col("vis")
    every = [
        F.slice(vis, 1, 40),
        F.filter(vis, lambda _, i: i % 2 == 0),
        F.array_distinct(vis),
        F.slice(vis, F.greatest(F.size(vis) - 59, F.lit(1)), F.lit(60)),
        F.concat(F.col("columns"), F.slice(vis, 1, 80)),
    ]
    return F.array(*[F.array_join(x, " ") for x in every[:k]])


def candidates(tables: DataFrame, qrels: DataFrame, k: int = 3) -> DataFrame:
    """(dataset, table_id, cand_id, body, is_gold): K candidates of gold tables, the first one of others."""
    golden = gold(qrels).select("dataset", "table_id", F.lit(True).alias("is_gold"))
    marked = tables.join(golden, ["dataset", "table_id"], "left").withColumn("is_gold", F.coalesce("is_gold", F.lit(False)))
    bodies = F.posexplode(F.slice(template_bodies(k), F.lit(1), F.when(F.col("is_gold"), k).otherwise(1))).alias("cand_id", "body")
    return marked.select("dataset", "table_id", "is_gold", bodies)


def default_pick(table_id: Column, k: int, seed: int = DEFAULT_SEED) -> Column:
    """Which candidate of a gold table stands in the default corpus: portable integer arithmetic."""
    return (table_id * 7919 + seed) % k


def default_corpus(cands: DataFrame, k: int = 3, seed: int = DEFAULT_SEED) -> DataFrame:
    """One candidate a table."""
    return cands.where(F.when(F.col("is_gold"), F.col("cand_id") == default_pick(F.col("table_id"), k, seed)).otherwise(True))


def score(cands: DataFrame, queries: DataFrame, qrels: DataFrame, mode: str = "unified", k: int = 3, seed: int = DEFAULT_SEED, picks: DataFrame | None = None, k1: float = K1, b: float = B, analyzer: Analyzer = WORDS) -> DataFrame:
    """(dataset, table_id, cand_id, score, n_queries): mean BM25 of each candidate over its table's queries.

    ``unified``: a table's candidates stand in one corpus with all defaults;
    ``individual``: each stands alone in the default's place. ``picks``
    (dataset, table_id, pick) overrides the default candidates.
    """
    wanted = qrels.where("grade > 0").select("dataset", "query_id", "table_id").distinct()
    terms = query_terms(queries.join(wanted.select("dataset", "query_id").distinct(), ["dataset", "query_id"], "left_semi"), analyzer)
    chosen = cands.withColumn("pick", default_pick(F.col("table_id"), k, seed))
    if picks is not None:
        chosen = cands.join(picks, ["dataset", "table_id"], "left").withColumn("pick", F.coalesce("pick", F.lit(0)))
    tokens = chosen.select("dataset", "table_id", "cand_id", "is_gold", (~F.col("is_gold") | (F.col("cand_id") == F.col("pick"))).alias("is_default"), analyzer.tokens(F.col("body")).alias("tokens")).withColumn("dl", F.size("tokens").cast("long"))
    base = tokens.where("is_default").groupBy("dataset").agg(F.count("*").alias("n0"), F.sum("dl").alias("len0"))
    own = tokens.where("is_gold").groupBy("dataset", "table_id").agg(F.sum(F.when(F.col("is_default"), F.col("dl"))).alias("r_len"), F.sum("dl").alias("all_len"), F.count("*").alias("n_cand"))
    # only the terms of judged queries are counted
    posted = tokens.select("dataset", "table_id", "cand_id", "is_gold", "is_default", "dl", F.explode("tokens").alias("term")).join(hinted(terms.select("dataset", "term").distinct()), ["dataset", "term"], "left_semi").groupBy("dataset", "table_id", "cand_id", "is_gold", "is_default", "dl", "term").agg(F.count("*").alias("tf"))
    df0 = posted.where("is_default").groupBy("dataset", "term").agg(F.count("*").alias("df0"))
    in_own = posted.where("is_gold").groupBy("dataset", "table_id", "term").agg(F.sum(F.col("is_default").cast("int")).alias("in_r"), F.count("*").alias("in_c"))
    # the shared statistics less the default, plus the candidates
    golden = posted.where("is_gold").join(in_own, ["dataset", "table_id", "term"]).join(df0, ["dataset", "term"], "left").join(F.broadcast(base), "dataset").join(own, ["dataset", "table_id"])
    unified = mode == "unified"
    n = F.col("n0") + (F.col("n_cand") - 1 if unified else F.lit(0))
    total = F.col("len0") - F.col("r_len") + (F.col("all_len") if unified else F.col("dl"))
    df = F.coalesce("df0", F.lit(0)) - F.col("in_r") + (F.col("in_c") if unified else F.lit(1))
    value = term_score(F.col("tf"), F.col("dl"), total / n, n, df, k1, b)
    asked = wanted.join(terms, ["dataset", "query_id"])
    summed = golden.withColumn("value", value).join(asked, ["dataset", "table_id", "term"]).groupBy("dataset", "table_id", "cand_id").agg(F.sum("value").alias("total"))
    n_queries = wanted.groupBy("dataset", "table_id").agg(F.count("*").alias("n_queries"))
    # candidates that match no query count with 0
    all_of_them = cands.where("is_gold").select("dataset", "table_id", "cand_id").join(n_queries, ["dataset", "table_id"])
    return all_of_them.join(summed, ["dataset", "table_id", "cand_id"], "left").select("dataset", "table_id", "cand_id", F.round(F.coalesce("total", F.lit(0.0)) / F.col("n_queries"), 6).alias("score"), "n_queries")


def position(cands: DataFrame, queries: DataFrame, qrels: DataFrame, k: int = 3, seed: int = DEFAULT_SEED, k1: float = K1, b: float = B, analyzer: Analyzer = WORDS) -> DataFrame:
    """(dataset, table_id, cand_id, mean_rank): where the target stands in its queries' lists with each candidate in its own corpus.

    The other tables are scored with the statistics of the candidate's corpus; of
    equal scores the smaller id stands first. A candidate that matches nothing
    stands behind all tables that match. Tables that hold a query's terms equally
    often and are equally long score the same in any corpus, so a judged table
    meets each such class once, with its size; ids are counted, by class, only
    where scores are equal.
    """
    wanted = qrels.where("grade > 0").select("dataset", "query_id", "table_id").distinct()
    terms = query_terms(queries.join(wanted.select("dataset", "query_id").distinct(), ["dataset", "query_id"], "left_semi"), analyzer)
    default = (~F.col("is_gold")) | (F.col("cand_id") == default_pick(F.col("table_id"), k, seed))
    tokens = cands.select("dataset", "table_id", "cand_id", "is_gold", default.alias("is_default"), analyzer.tokens(F.col("body")).alias("tokens")).withColumn("dl", F.size("tokens").cast("long"))
    posted = tokens.select("dataset", "table_id", "cand_id", "is_gold", "is_default", "dl", F.explode("tokens").alias("term")).join(hinted(terms.select("dataset", "term").distinct()), ["dataset", "term"], "left_semi").groupBy("dataset", "table_id", "cand_id", "is_gold", "is_default", "dl", "term").agg(F.count("*").alias("tf"))
    posted = materialise(posted, "posted")
    base = tokens.where("is_default").groupBy("dataset").agg(F.count("*").alias("n0"), F.sum("dl").alias("len0"))
    own = tokens.where("is_gold AND is_default").select("dataset", "table_id", F.col("dl").alias("r_len"))
    df0 = posted.where("is_default").groupBy("dataset", "term").agg(F.count("*").alias("df0"))
    in_r = posted.where("is_gold AND is_default").select("dataset", "table_id", "term", F.lit(1).alias("in_r"))
    tf = posted.where("is_gold").select("dataset", "table_id", "cand_id", "term", "tf")
    targets = tokens.where("is_gold").select("dataset", "table_id", "cand_id", "dl").join(own, ["dataset", "table_id"]).join(F.broadcast(base), "dataset")
    asked = targets.join(wanted.join(terms.select("dataset", "query_id", "term"), ["dataset", "query_id"]), ["dataset", "table_id"])
    need = asked.join(df0, ["dataset", "term"], "left").join(in_r, ["dataset", "table_id", "term"], "left").join(tf, ["dataset", "table_id", "cand_id", "term"], "left")
    has = F.col("tf").isNotNull().cast("int")
    need = need.select("dataset", "table_id", "cand_id", "query_id", "term", "dl", F.coalesce("tf", F.lit(0)).alias("tf"), F.col("n0").alias("n"), ((F.col("len0") - F.col("r_len") + F.col("dl")) / F.col("n0")).alias("avg"), (F.coalesce("df0", F.lit(0)) - F.coalesce("in_r", F.lit(0)) + has).alias("df"))
    score_of = lambda tf_, dl_: F.round(F.sum(term_score(tf_, dl_, F.col("avg"), F.col("n"), F.col("df"), k1, b)), 6)
    key = ["dataset", "table_id", "cand_id", "query_id"]
    need = materialise(need, "needed")  # a row a candidate and query term
    mine = need.groupBy(*key).agg(score_of(F.col("tf"), F.col("dl")).alias("own"))
    terms_of = wanted.select("dataset", "query_id").distinct().join(terms.select("dataset", "query_id", "term"), ["dataset", "query_id"])
    others = posted.where("is_default").select("dataset", "term", F.col("table_id").alias("other"), "tf", "dl").join(hinted(terms_of), ["dataset", "term"])
    # each table's class in each query's list: how often the query's terms stand in it, and its length
    classed = others.groupBy("dataset", "query_id", "other", "dl").agg(F.array_sort(F.collect_list(F.struct("term", "tf"))).alias("held"))
    classed = materialise(classed, "classes")
    sizes = classed.groupBy("dataset", "query_id", "dl", "held").agg(F.count("*").alias("size"))
    meeting = sizes.select("dataset", "query_id", F.col("dl").alias("other_dl"), "held", "size", F.explode("held").alias("h")).select("*", F.col("h.term").alias("term"), F.col("h.tf").alias("other_tf"))
    rivals = need.join(meeting, ["dataset", "query_id", "term"]).groupBy(*key, "other_dl", "held").agg(score_of(F.col("other_tf"), F.col("other_dl")).alias("score"), F.max("size").alias("size"))
    rivals = materialise(rivals, "rivals")
    met = mine.join(rivals, key, "left")
    # the target's own default is no rival of it
    itself = mine.join(classed.select("dataset", "query_id", F.col("other").alias("table_id"), F.col("dl").alias("other_dl"), "held"), ["dataset", "query_id", "table_id"])
    ahead = met.groupBy(*key).agg(F.coalesce(F.sum(F.when(F.col("score") > F.col("own"), F.col("size"))), F.lit(0)).alias("above"))
    own_above = itself.join(rivals.select(*key, "other_dl", "held", "score"), [*key, "other_dl", "held"]).groupBy(*key).agg(F.count_if(F.col("score") > F.col("own")).alias("itself"))
    # of equal score: members of the class with smaller ids, by one running count of members and targets
    equal = met.where("score = own").select(*key, "other_dl", "held")
    members = classed.select("dataset", "query_id", F.col("dl").alias("other_dl"), "held", F.col("other").alias("table_id"), F.lit(None).cast("int").alias("cand_id"), F.lit(1).alias("one"))
    tied = members.join(equal.select("dataset", "query_id", "other_dl", "held").distinct(), ["dataset", "query_id", "other_dl", "held"], "left_semi")
    lined = tied.unionByName(equal.withColumn("one", F.lit(0)))
    before = Window.partitionBy("dataset", "query_id", "other_dl", "held").orderBy("table_id").rangeBetween(Window.unboundedPreceding, -1)
    smaller = lined.withColumn("n", F.coalesce(F.sum("one").over(before), F.lit(0))).where("one = 0").groupBy(*key).agg(F.sum("n").alias("smaller"))
    none = F.lit(0)
    places = ahead.join(own_above, key, "left").join(smaller, key, "left").select(*key, (F.col("above") - F.coalesce("itself", none) + F.coalesce("smaller", none) + 1).alias("place"))
    return places.groupBy("dataset", "table_id", "cand_id").agg(F.round(F.avg("place"), 6).alias("mean_rank"))


def order(scores: DataFrame) -> DataFrame:
    """``scores`` with each candidate's ``rank`` in its table."""
    return scores.withColumn("rank", F.row_number().over(Window.partitionBy("dataset", "table_id").orderBy(F.desc("score"), "cand_id")))


def pairs(scores: DataFrame, policy: str = "extremes") -> DataFrame:
    """(dataset, table_id, win_cand, lose_cand, margin); pairs of equal score are dropped.

    ``extremes``: best against worst, in one aggregation; ``all`` and
    ``adjacent``: every ordered pair, or neighbours in the order.
    """
    if policy == "extremes":
        best, worst = F.max(F.struct("score", (-F.col("cand_id")).alias("c"))), F.min(F.struct("score", (-F.col("cand_id")).alias("c")))
        rows = scores.groupBy("dataset", "table_id").agg(best.alias("b"), worst.alias("w"))
        rows = rows.select("dataset", "table_id", (-F.col("b.c")).alias("win_cand"), (-F.col("w.c")).alias("lose_cand"), F.round(F.col("b.score") - F.col("w.score"), 6).alias("margin"))
    else:
        ranked = order(scores)
        win = ranked.select("dataset", "table_id", F.col("cand_id").alias("win_cand"), F.col("score").alias("s1"), F.col("rank").alias("r1"))
        lose = ranked.select("dataset", "table_id", F.col("cand_id").alias("lose_cand"), F.col("score").alias("s2"), F.col("rank").alias("r2"))
        near = F.col("r2") == F.col("r1") + 1 if policy == "adjacent" else F.col("r1") < F.col("r2")
        rows = win.join(lose, ["dataset", "table_id"]).where(near).select("dataset", "table_id", "win_cand", "lose_cand", F.round(F.col("s1") - F.col("s2"), 6).alias("margin"))
    return rows.where("margin > 0")


def approximation_loss(unified: DataFrame, individual: DataFrame) -> DataFrame:
    """How the two corpora differ: targets, equal best and worst, largest difference."""
    a = unified.select("dataset", "table_id", "cand_id", F.col("score").alias("u"))
    both = a.join(individual.select("dataset", "table_id", "cand_id", F.col("score").alias("i")), ["dataset", "table_id", "cand_id"])
    neg = (-F.col("cand_id")).alias("c")
    per = both.groupBy("dataset", "table_id").agg(*[f(F.struct(s, neg))["c"].alias(f"{n}_{s}") for f, n in ((F.max, "best"), (F.min, "worst")) for s in ("u", "i")], F.max(F.abs(F.col("u") - F.col("i"))).alias("d"))
    return per.groupBy("dataset").agg(F.count("*").alias("n_targets"), F.sum((F.col("best_u") == F.col("best_i")).cast("int")).alias("same_best"), F.sum((F.col("worst_u") == F.col("worst_i")).cast("int")).alias("same_worst"), F.round(F.max("d"), 6).alias("max_abs_diff"))


def iterate(cands: DataFrame, queries: DataFrame, qrels: DataFrame, materialise, max_rounds: int = 5, mode: str = "unified", k: int = 3) -> tuple[DataFrame, int]:
    """Score again with the best candidates as defaults until none changes: (scores, rounds).

    Each round's scores are materialised, which cuts the lineage; only a count
    of changed defaults comes to the driver.
    """
    picks = cands.where("is_gold").select("dataset", "table_id").distinct().withColumn("pick", default_pick(F.col("table_id"), k).cast("int"))
    for done in range(1, max_rounds + 1):
        scores = materialise(score(cands, queries, qrels, mode, k, picks=picks))
        best = scores.groupBy("dataset", "table_id").agg((-F.max(F.struct("score", (-F.col("cand_id")).alias("c")))["c"]).cast("int").alias("pick"))
        changed = best.join(picks.withColumnRenamed("pick", "old"), ["dataset", "table_id"]).where("pick <> old").limit(1).count()
        picks = best
        if not changed:
            break
    return scores, done


def folds(pair_rows: DataFrame, names: list[str]) -> DataFrame:
    """Leave one dataset out: each pair once for every other dataset held out."""
    held = F.explode(F.array(*map(F.lit, names))).alias("held_out")
    return pair_rows.select("*", held).where("held_out <> dataset")
