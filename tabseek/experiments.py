"""The experiments over the six stand-in datasets.

A system describes every table of a dataset; the descriptions of all systems
become fields of one index, so a grid over all datasets costs one pass over their texts.
Training leaves one dataset out: the generator that describes it has seen the
preference pairs of all others. Candidates are sampled from the untrained
generator, scored in the unified corpus, and the best and the worst make a pair.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, functions as F

from .operators import benchmark, evaluate, rank, search, train
from .plans import datasets
from .plans.scratch import materialise, stands

TOPICS = ("sci_s", "sci_l")
#: Words that a single call says of the columns.
SLOTS = 30
#: Stand-ins that are made at once.
SIDE_BY_SIDE = 3


@dataclass(frozen=True)
class Setting:
    """One system: its names expanded or as they are, ``trained`` or not, K candidates, base model ``prior``, training configuration."""

    name: str
    expand: bool = True
    trained: bool = True
    k: int = 3
    prior: int = 0
    cfg: train.TrainConfig = field(default_factory=train.TrainConfig)


_BASE = train.TrainConfig()
FULL = Setting("FULL")
#: One change at a time from FULL.
ABLATION = (FULL, Setting("FULL-pref", trained=False), Setting("FULL-exp", expand=False), Setting("FULL-exp-pref", expand=False, trained=False))
GRID = (FULL, Setting("FULL-pref", trained=False), Setting("FULL beta 0.5", cfg=replace(_BASE, beta=0.5)), Setting("FULL K 5", k=5), Setting("FULL 3 epochs", cfg=replace(_BASE, epochs=3)))
MODELS = (FULL, Setting("FULL other model", prior=1))
BASELINES = {"MCB": 0, "MCB other model": 1}


_made: dict[tuple, datasets.Dataset] = {}
_trained: dict[tuple, dict[str, tuple]] = {}


def load(spark, sf_dir, name: str) -> datasets.Dataset:
    """A stand-in, made once a session: every system, fold and experiment reads it."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    data = _made.get(key)
    if data is None or not all(map(stands, (data.tables, data.queries, data.qrels))):
        data = datasets.SIX[name](spark, sf_dir)
        data = _made[key] = datasets.Dataset(*(materialise(part, f"{name}-{what}") for part, what in ((data.tables, "tables"), (data.queries, "queries"), (data.qrels, "qrels"))))
    return data


def loaded(spark, sf_dir, names) -> datasets.Dataset:
    """The named stand-ins as one: every step takes them together, by ``dataset``."""
    if {"gov", "web_a"} & set(names):  # the topic sets read these words too
        datasets.document_words(spark, sf_dir)
    if {"web_a", "web_b"} & set(names):
        datasets.titles(spark, sf_dir)
    if set(TOPICS) & set(names):
        datasets.document_words(spark, sf_dir, english=True)
    # what they share is written; the rest is many short jobs, which run side by side
    with ThreadPoolExecutor(SIDE_BY_SIDE) as pool:
        made = list(pool.map(lambda name: load(spark, sf_dir, name), names))
    columns = ("dataset", "table_id", "context", "around", "cryptic", "expanded", "seen", "topics")
    together = lambda parts: reduce(DataFrame.unionByName, parts)
    grade = lambda d: d.qrels.select("dataset", "query_id", "table_id", F.col("grade").cast("int").alias("grade"))
    return datasets.Dataset(together([d.tables.select(*columns) for d in made]), together([d.queries for d in made]), together([grade(d) for d in made]))


def one_call(expand: bool):
    """(prompt, words, said): what the one call sees, names and context but no rows.

    A description's overview restates name and context; of the columns it says what is sampled.
    """
    words = F.col("expanded" if expand else "cryptic")
    return F.array_join(F.slice(F.concat("around", words), 1, 100), " ").alias("prompt"), words.alias("words"), F.col("around").alias("said")


def shown(data: datasets.Dataset, expand: bool) -> DataFrame:
    """(dataset, table_id, prompt, words, said) of ``one_call``."""
    return data.tables.select("dataset", "table_id", *one_call(expand))


def many_calls():
    """(prompt, words, said) of the multi-call baseline, which sees names as they are and some rows.

    Statistics, topics and column summaries are calls of their own, whose answers
    are cut to a length; the last call says what these told, name and context
    among them, and is about twice as long as the single call's. The model
    chooses the words.
    """
    words = F.concat("around", F.slice("cryptic", 1, 40), "topics", "seen")
    return F.array_join(F.slice(F.concat("around", "cryptic"), 1, 40), " ").alias("prompt"), words.alias("words"), F.array().cast("array<string>").alias("said")


def asked(tables: DataFrame, calls: dict, k=None) -> DataFrame:
    """(dataset, table_id, voice, prompt, words, said, k): a row a table and call, from one pass; ``calls`` has each voice's (name, call)."""
    k = k or {}
    one = lambda key, name, call: F.struct(name.alias("voice"), *call, k.get(key, F.lit(1)).alias("k"))
    return tables.select("dataset", "table_id", F.explode(F.array(*[one(key, *x) for key, x in calls.items()])).alias("c")).select("dataset", "table_id", "c.*")


def _drawn(setting: Setting) -> Setting:
    """What decides a setting's pairs: neither beta nor epochs nor rate do."""
    cfg = train.TrainConfig(bits=setting.cfg.bits, features=setting.cfg.features, vocabulary=setting.cfg.vocabulary)
    return Setting("", setting.expand, True, setting.k, setting.prior, cfg)


def pairs_of(data: datasets.Dataset, kinds: list[Setting]) -> list[DataFrame]:
    """(dataset, table_id, prompt, chosen, rejected) of the best and worst sampled candidates, for each kind of setting.

    All datasets' candidates of all kinds are drawn in one pass.
    """
    golden = rank.gold(data.qrels).select("dataset", "table_id", F.lit(True).alias("is_gold"))
    marked = data.tables.join(golden, ["dataset", "table_id"], "left")
    # one candidate of the other tables
    wanted = asked(marked, {i: (F.lit(str(i)), one_call(s.expand)) for i, s in enumerate(kinds)}, {i: F.when(F.col("is_gold"), s.k).otherwise(1) for i, s in enumerate(kinds)})
    drawn = train.describe(wanted, {str(i): train.Voice(train.base_weights(s.cfg, s.prior), s.cfg) for i, s in enumerate(kinds)})
    every = materialise(drawn.join(golden, ["dataset", "table_id"], "left").withColumn("is_gold", F.coalesce("is_gold", F.lit(False))), "candidates")
    out = []
    for i, s in enumerate(kinds):
        cands = every.where(F.col("voice") == str(i)).drop("voice")
        scores = rank.score(cands, data.queries, data.qrels, k=s.k)
        # a pair's two texts come from one pass over the judged tables' candidates
        body = F.map_from_entries(F.collect_list(F.struct("cand_id", "body"))).alias("bodies")
        bodies = cands.where("is_gold").groupBy("dataset", "table_id").agg(body)
        pairs = rank.pairs(scores).join(bodies, ["dataset", "table_id"]).select("dataset", "table_id", F.col("bodies")[F.col("win_cand")].alias("chosen"), F.col("bodies")[F.col("lose_cand")].alias("rejected"))
        out.append(pairs.join(shown(data, s.expand).select("dataset", "table_id", "prompt"), ["dataset", "table_id"]).select("dataset", "table_id", "prompt", "chosen", "rejected"))
    return out


def training_pairs(data: datasets.Dataset, setting: Setting) -> DataFrame:
    """(dataset, table_id, prompt, chosen, rejected) of a setting's best and worst sampled candidates."""
    return pairs_of(data, [_drawn(setting)])[0]


def adapters(spark, sf_dir, names, settings, held_out: list[str]) -> dict[str, dict[str, tuple]]:
    """Each setting's adapters (a, b) by held-out dataset, once a session; adapters alone, of fixed size, come to the driver.

    Settings that draw the same candidates share their pairs; all runs train side by side, a task each.
    """
    key = lambda s: (spark.sparkContext.applicationId, sf_dir, tuple(names), replace(s, name=""), tuple(held_out))
    wanted = [s for s in settings if s.trained and key(s) not in _trained]
    if wanted:
        data, kinds = loaded(spark, sf_dir, names), list(dict.fromkeys(map(_drawn, wanted)))
        drawn = materialise(reduce(DataFrame.unionByName, [p.withColumn("kind", F.lit(i)) for i, p in enumerate(pairs_of(data, kinds))]), "pairs")
        runs = F.array(*[F.struct(F.lit(kinds.index(_drawn(s))).alias("kind"), F.lit(s.name).alias("run")) for s in wanted])
        each = drawn.select("*", F.explode(F.filter(runs, lambda r: r["kind"] == F.col("kind"))["run"]).alias("run")).drop("kind")
        rows = train.many_adapters(rank.folds(each, held_out), {s.name: (s.cfg, s.prior) for s in wanted}).collect()
        for s in wanted:
            _trained[key(s)] = {r.held_out: (r.a, r.b) for r in rows if r.run == s.name}
    return {s.name: _trained[key(s)] if s.trained else {} for s in settings}


def descriptions(data: datasets.Dataset, held_out, settings, tuned: dict, baselines=()) -> DataFrame:
    """(dataset, table_id, field, text): what every setting and baseline says of each table, from one pass; a setting's generator follows from the dataset."""
    voice = lambda name: F.concat(F.lit(f"{name}|"), "dataset")
    calls = {s.name: (voice(s.name), one_call(s.expand)) for s in settings} | {b: (F.lit(f"{b}|"), many_calls()) for b in baselines}
    voices = {f"{s.name}|{name}": train.Voice(train.trained_weights(*tuned[s.name].get(name, (None, None)), s.cfg, s.prior), s.cfg) for s in settings for name in held_out}
    cfg = train.TrainConfig()
    voices |= {f"{b}|": train.Voice(train.base_weights(cfg, BASELINES[b]), cfg, 2 * SLOTS) for b in baselines}
    said = train.describe(asked(data.tables, calls), voices)
    return said.select("dataset", "table_id", F.substring_index("voice", "|", 1).alias("field"), F.col("body").alias("text"))


def indexed(data: datasets.Dataset, fields: DataFrame) -> search.Index:
    """The index of ``fields`` over the terms of the queries; texts and postings are made once, whatever reads them."""
    index = search.build_index(materialise(fields, "fields"), terms=search.query_terms(data.queries).select("dataset", "term").distinct())
    posted = materialise(index.postings, "postings")
    return search.Index(posted, search.term_stats(posted), materialise(index.field_stats, "field-stats"), index.analyzers)


def search_all(data: datasets.Dataset, fields: DataFrame, names, k: int = 100) -> DataFrame:
    """(dataset, config, query_id, table_id, rank) of every system ``names``, a field each, from one index of all datasets."""
    hits = search.runs_top_k(data.queries, indexed(data, fields), {name: search.Run((name,)) for name in names}, k)
    return hits.select("dataset", "config", "query_id", "table_id", "rank")


def run(spark, sf_dir, settings, baselines=("MCB",), names=tuple(datasets.SIX), held_out=None) -> tuple[datasets.Dataset, DataFrame]:
    """The held-out datasets, as one, and the hits of every setting and baseline on them."""
    held_out = list(held_out or names)
    loaded(spark, sf_dir, names)
    tuned = adapters(spark, sf_dir, names, settings, held_out)
    data = loaded(spark, sf_dir, held_out)
    hits = search_all(data, descriptions(data, held_out, settings, tuned, baselines), [*(s.name for s in settings), *baselines])
    return data, materialise(hits, "hits")


def measured(found, ks=evaluate.KS) -> DataFrame:
    """(measure, dataset, config, k, value): NDCG and recall of every run."""
    data, hits = found  # hits are at most 100 a query, configuration and dataset
    parts = (("ndcg", evaluate.ndcg(hits, data.qrels, ks)), ("recall", evaluate.recall(hits, data.qrels, ks)))
    return reduce(DataFrame.unionByName, [rows.select(F.lit(name).alias("measure"), "dataset", "config", "k", "value") for name, rows in parts])


def exp_overall(spark, sf_dir):
    """FULL against the multi-call baseline on all six datasets."""
    return measured(run(spark, sf_dir, (FULL,)))


def exp_ablation(spark, sf_dir):
    """FULL, without training, without expansion, without both, and the baseline, on all six."""
    return measured(run(spark, sf_dir, ABLATION), (10, 50))


def exp_alt_model(spark, sf_dir):
    """FULL and the baseline with either base model, on all six."""
    return measured(run(spark, sf_dir, MODELS, tuple(BASELINES)), (10, 50))


def exp_grid(spark, sf_dir):
    """Beta, candidates and epochs against FULL on the larger topic dataset."""
    return measured(run(spark, sf_dir, GRID, names=TOPICS, held_out=("sci_l",)))


def lodo_metrics(spark, sf_dir):
    """FULL, untrained, and the baseline on each topic dataset, trained on the other."""
    return measured(run(spark, sf_dir, ABLATION[:2], names=TOPICS)).where("measure = 'ndcg'").drop("measure")


def exp_lengths(spark, sf_dir):
    """Words and characters of FULL's and the baseline's descriptions, by dataset (W2); FULL is trained on the other five."""
    names = list(datasets.SIX)
    tuned = adapters(spark, sf_dir, names, (FULL,), names)
    return lengths(descriptions(loaded(spark, sf_dir, names), names, (FULL,), tuned, ("MCB",)))


def lengths(said: DataFrame) -> DataFrame:
    """(dataset, system, avg_words, avg_chars) of (dataset, table_id, field, text); an empty description has no words."""
    n_words = F.when(F.col("text") == "", 0).otherwise(F.size(F.split("text", " ")))
    return said.groupBy("dataset", F.col("field").alias("system")).agg(F.round(F.avg(n_words), 4).alias("avg_words"), F.round(F.avg(F.length("text")), 4).alias("avg_chars"))


def exp_expansion(spark, sf_dir):
    """Search by expanded names against names as they are, over the catalogue; no description is generated."""
    from .workloads import _ent_fields

    data, fields = _ent_fields(spark, sf_dir)
    systems = {name: fields.where(F.col("field") == key).select("dataset", "table_id", F.col("text").alias("body")) for name, key in (("names as they are", "raw_names"), ("expanded names", "expansion"))}
    bodies = reduce(DataFrame.unionByName, (rows.select("dataset", "table_id", F.lit(name).alias("field"), F.col("body").alias("text")) for name, rows in systems.items()))
    return evaluate.ndcg(search_all(data, bodies, list(systems)), data.qrels)


def exp_multi_field(spark, sf_dir):
    """All three fields and each left out, against the description alone, where there is context."""
    names = ["gov", "web_a", "web_b"]
    data = loaded(spark, sf_dir, names)
    tuned = adapters(spark, sf_dir, names, (FULL,), names)
    every = ("description", "expansion", "context")
    runs = {"FULL": (every[:1], 0.1), "MULTI": (every, 0.1), "MULTI-desc": (every[1:], 0.1), "MULTI-exp": (("description", "context"), 0.1), "MULTI-ctx": (every[:2], 0.1)}
    part = lambda name, text: data.tables.select("dataset", "table_id", F.lit(name).alias("field"), text.alias("text"))
    full = descriptions(data, names, (FULL,), tuned).withColumn("field", F.lit("description"))
    fields = full.unionByName(part("expansion", F.array_join(F.concat("around", "expanded"), " "))).unionByName(part("context", F.coalesce("context", F.lit(""))))
    return evaluate.ndcg(materialise(search.multi_runs(data.queries, indexed(data, fields), runs), "hits"), data.qrels, (10, 50))


def exp_bootstrap(spark, sf_dir):
    """The middle 95 % of the resampled mean difference between FULL and the baseline, on each of the six datasets."""
    data, hits = run(spark, sf_dir, (FULL,))
    return benchmark.bootstrap(benchmark.by_query(hits, data.qrels, configs=("FULL", "MCB")), "FULL", "MCB")


def pair_likelihoods(spark, sf_dir):
    """Loss and margins from the generator's own likelihoods: a run's pairs before and after training on them."""
    data = load(spark, sf_dir, "sci_l")
    pairs = materialise(training_pairs(data, FULL), "pairs")
    row = train.adapters(pairs.withColumn("held_out", F.lit("none")), FULL.cfg).first()
    rows = train.likelihoods(pairs, train.trained_weights(*((row.a, row.b) if row else (None, None)), FULL.cfg), FULL.cfg)
    return train.preference_loss(rows, FULL.cfg.beta).crossJoin(train.margins(rows, FULL.cfg.beta))


def describe_new_tables(spark, sf_dir):
    """A new corpus described by a generator trained on others: one description a table, no rows read."""
    tuned = adapters(spark, sf_dir, ("sci_l", "ent"), (FULL,), ["ent"])
    weights = train.trained_weights(*tuned["FULL"].get("ent", (None, None)), FULL.cfg)
    return train.generate(shown(load(spark, sf_dir, "ent"), True), weights, FULL.cfg).select("table_id", "body")


def queries():
    return {f.__name__: f for f in (exp_overall, exp_ablation, exp_alt_model, exp_grid, lodo_metrics, exp_lengths, exp_expansion, exp_multi_field, exp_bootstrap, pair_likelihoods, describe_new_tables)}
