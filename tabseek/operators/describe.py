"""Descriptions: prompts, the six-field schema, validity, and the baselines."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

SCHEMA = (
    "dataset_overview STRING, key_themes_or_topics ARRAY<STRING>, applications_and_use_cases ARRAY<STRING>, "
    "concepts_and_synonyms ARRAY<STRUCT<concept: STRING, synonyms: ARRAY<STRING>>>, keywords_and_themes ARRAY<STRING>, additional_context ARRAY<STRING>"
)
FIELDS = ["dataset_overview", "key_themes_or_topics", "applications_and_use_cases", "concepts_and_synonyms", "keywords_and_themes", "additional_context"]

INSTRUCTIONS = """Describe a table for people who search for it by keywords.
Answer with one JSON object that has exactly these fields: dataset_overview (two to five sentences), key_themes_or_topics, applications_and_use_cases, concepts_and_synonyms (three to six concepts, each with one to four synonyms), keywords_and_themes, additional_context.
Write "unknown" where the names do not tell. Do not invent values."""
EXAMPLE = 'Name: monthly rainfall\nColumns: station name, month, rainfall millimetres\nAnswer: {"dataset_overview": "Rain measured at weather stations. Each row is a month.", "key_themes_or_topics": ["weather"], "applications_and_use_cases": ["water planning"], "concepts_and_synonyms": [{"concept": "rainfall", "synonyms": ["precipitation"]}, {"concept": "station", "synonyms": ["site"]}, {"concept": "month", "synonyms": ["period"]}], "keywords_and_themes": ["rain", "climate"], "additional_context": ["unknown"]}'


def prompts(tables: DataFrame, expanded: DataFrame | None = None) -> DataFrame:
    """(dataset, table_id, prompt): one call a table, by expanded names or, without ``expanded``, by names as they are."""
    rows = tables.withColumn("shown", F.array_join("columns", ", "))
    if expanded is not None:
        columns = expanded.groupBy("dataset", "table_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "expanded"))), lambda x: x["expanded"]), ", ").alias("e"))
        rows = rows.join(columns, ["dataset", "table_id"], "left").withColumn("shown", F.coalesce("e", "shown"))
    context = F.concat(F.lit("Context: "), F.col("context")) if "context" in tables.columns else F.lit(None).cast("string")
    name = F.concat(F.lit("Name: "), F.col("table_name"))
    return rows.select("dataset", "table_id", F.concat_ws("\n", F.lit(INSTRUCTIONS), F.lit(EXAMPLE), name, F.concat(F.lit("Columns: "), "shown"), context, F.lit("Answer:")).alias("prompt"))


def json_part(raw: Column) -> Column:
    """The object in an answer, with or without a fence and words around it."""
    return F.regexp_extract(F.coalesce(raw, F.lit("")), r"(?s)(\{.*\})", 1)


def parse(answers: DataFrame) -> DataFrame:
    """``answers`` (raw, ...) with ``doc`` and ``valid``; what is no description keeps a null doc."""
    body = json_part(F.col("raw"))
    doc = F.from_json(body, SCHEMA)
    keys = F.array_sort(F.json_object_keys(body))
    exact = F.coalesce(keys == F.array(*[F.lit(f) for f in sorted(FIELDS)]), F.lit(False))
    parsed = answers.withColumn("doc", F.when(F.json_object_keys(body).isNotNull(), doc)).withColumn("_exact", exact)
    return parsed.withColumn("valid", F.col("_exact") & F.coalesce(well_formed(F.col("doc")), F.lit(False))).drop("_exact")


def well_formed(doc: Column) -> Column:
    """Two to five sentences; three to six concepts of one to four synonyms."""
    sentences = F.size(F.filter(F.split(doc["dataset_overview"], r"[.!?]+\s*"), lambda s: s != ""))
    concepts = doc["concepts_and_synonyms"]
    return sentences.between(2, 5) & F.size(concepts).between(3, 6) & F.forall(concepts, lambda c: F.size(c["synonyms"]).between(1, 4))


def flatten(doc: Column, include_keys: bool = False) -> Column:
    """The text that is indexed: values in order, with the field names if asked."""
    lists = {f: F.array_join(doc[f], " ") for f in FIELDS if f not in ("dataset_overview", "concepts_and_synonyms")}
    concepts = F.array_join(F.transform(doc["concepts_and_synonyms"], lambda c: F.concat_ws(" ", c["concept"], F.array_join(c["synonyms"], " "))), " ")
    values = {"dataset_overview": doc["dataset_overview"], "concepts_and_synonyms": concepts} | lists
    return F.concat_ws(" ", *[x for f in FIELDS for x in ([F.lit(f)] if include_keys else []) + [values[f]]])


def profile(rows: DataFrame, columns: list[str]) -> DataFrame:
    """Per column: rows, nulls, distinct (estimated), least and greatest value; one scan for all columns."""
    stats = [F.struct(F.lit(c).alias("column"), F.count("*").alias("n_rows"), F.sum(F.col(c).isNull().cast("long")).alias("n_null"), F.approx_count_distinct(c).alias("n_distinct"), F.min(F.col(c).cast("string")).alias("least"), F.max(F.col(c).cast("string")).alias("greatest")) for c in columns]
    return rows.agg(F.array(*stats).alias("s")).select(F.explode("s").alias("s")).select("s.*")


def multicall(tables: DataFrame, profiles: DataFrame, batch: int = 10) -> DataFrame:
    """The earlier multi-call baseline: name, columns, statistics, frequent words and a head of the text, and its calls.

    ``tables`` carries ``vis``; ``profiles`` (dataset, table_id, stats) the statistics as text.
    """
    spaced = F.explode("vis").alias("w")
    counted = tables.select("dataset", "table_id", spaced).groupBy("dataset", "table_id", "w").agg(F.count("*").alias("n"))
    topics = counted.groupBy("dataset", "table_id").agg(F.array_join(F.transform(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("n")).alias("n"), "w"))), 1, 10), lambda x: x["w"]), " ").alias("topics"))
    rows = tables.join(topics, ["dataset", "table_id"], "left").join(profiles, ["dataset", "table_id"], "left")
    body = F.concat_ws(" ", "table_name", F.array_join("columns", " "), "stats", "topics", F.array_join(F.slice("vis", 1, 120), " "))
    return rows.select("dataset", "table_id", body.alias("body"), (3 + F.ceil(F.size("columns") / batch)).cast("long").alias("n_calls"))


def row_summary(rows: DataFrame, key: str, columns: list[str], n: int = 5) -> DataFrame:
    """One text from a schema and ``n`` rows, taken by hash order: the same rows on every run."""
    text = F.concat_ws("; ", *[F.concat_ws("=", F.lit(c), F.col(c).cast("string")) for c in columns])
    return rows.select(F.md5(F.col(key).cast("string")).alias("h"), text.alias("t")).orderBy("h").limit(n).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("h", "t"))), lambda x: x["t"]), " | ").alias("summary"))


def verbalize(tables: DataFrame) -> DataFrame:
    """A sentence a column, by template."""
    sentence = F.transform("columns", lambda c: F.concat(F.lit("Table "), F.coalesce("table_name", F.lit("unknown")), F.lit(" has a column "), c, F.lit(".")))
    return tables.select("dataset", "table_id", F.array_join(sentence, " ").alias("body"))
