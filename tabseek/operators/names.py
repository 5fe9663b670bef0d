"""Name expansion: splitting, batching, prompts, the lexicon, parsing and rules."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

#: Fixed values: (scope table or *, token, phrase).
LEXICON = [
    ("customer", "c", "customer"), ("supplier", "s", "supplier"), ("part", "p", "part"), ("orders", "o", "order"),
    ("lineitem", "l", "line item"), ("nation", "n", "nation"), ("region", "r", "region"),
    ("*", "acctbal", "account balance"), ("*", "mktsegment", "market segment"), ("*", "custkey", "customer key"),
    ("*", "suppkey", "supplier key"), ("*", "partkey", "part key"), ("*", "orderkey", "order key"),
    ("*", "nationkey", "nation key"), ("*", "regionkey", "region key"), ("*", "retailprice", "retail price"),
    ("*", "totalprice", "total price"), ("*", "extendedprice", "extended price"), ("*", "orderdate", "order date"),
    ("*", "shipdate", "ship date"), ("*", "orderstatus", "order status"), ("*", "orderpriority", "order priority"),
    ("*", "linenumber", "line number"), ("*", "returnflag", "return flag"), ("*", "linestatus", "line status"),
    ("*", "ts", "timestamp"), ("*", "props", "properties"), ("*", "lang", "language"), ("*", "doc", "document"),
    ("*", "conv", "conversation"), ("*", "vec", "vector"), ("*", "id", "identifier"), ("*", "chars", "characters"),
    ("*", "url", "web address"), ("*", "cust", "customer"), ("*", "supp", "supplier"), ("*", "ord", "order"), ("*", "evt", "event"),
]


#: Tokens of the catalogue that are plain words.
PLAIN = ["name", "size", "brand", "type", "price", "tax", "quantity", "discount", "comment", "event", "user", "value", "text", "source", "embedding", "label", "html", "page", "quality", "toxic", "turn", "role", "item"]


def split_name(name: Column) -> Column:
    """Tokens of a name: breaks at separators, case changes, and between letters and digits."""
    spaced = F.regexp_replace(name, "([a-z0-9])([A-Z])", "$1 $2")
    spaced = F.regexp_replace(spaced, "([A-Z]+)([A-Z][a-z])", "$1 $2")
    spaced = F.regexp_replace(spaced, "([A-Za-z])([0-9])", "$1 $2")
    spaced = F.regexp_replace(spaced, "([0-9])([A-Za-z])", "$1 $2")
    return F.filter(F.split(F.lower(spaced), "[^0-9a-z]+"), lambda t: t != "")


def batch_columns(tables: DataFrame, size: int = 10) -> DataFrame:
    """(dataset, table_id, batch, columns): a table's columns in runs of ``size``, in order."""
    runs = F.transform(F.sequence(F.lit(0), F.greatest(F.ceil(F.size("columns") / size).cast("int") - 1, F.lit(0))), lambda i: F.slice("columns", i * size + 1, F.lit(size)))
    return tables.where(F.size("columns") > 0).select("dataset", "table_id", F.posexplode(runs).alias("batch", "columns"))


RULES = [
    "Expand every token of every name; keep the order of the tokens.",
    "Give one phrase for each token and leave numbers as they are.",
    "A token that is a plain word stays unchanged.",
    "Use the table to decide what a short token means.",
    "Do not add words that no token stands for.",
    "Do not translate names.",
    "Chemical symbols and units of measure become the full name of the substance or the unit.",
    "Keep each phrase as short as its meaning allows.",
    "First reason in a few sentences on what the table holds, then write \"Final answer:\" and one line per name.",
    "Write each line as name: token → phrase, token → phrase",
]
EXAMPLES = [
    ("emp_nm, hire_dt", "emp_nm: emp → employee, nm → name\nhire_dt: hire → hire, dt → date"),
    ("addr_ln_2", "addr_ln_2: addr → address, ln → line, 2 → 2"),
    ("qtySold", "qtySold: qty → quantity, sold → sold"),
    ("avg_temp_c", "avg_temp_c: avg → average, temp → temperature, c → celsius"),
]


def _prompt(ask: Column) -> Column:
    rules = "\n".join(f"{i}. {r}" for i, r in enumerate(RULES, 1))
    shots = "\n\n".join(f"Names: {q}\nFinal answer:\n{a}" for q, a in EXAMPLES)
    return F.concat(F.lit(f"You expand abbreviated names of database tables and columns.\n{rules}\n\n{shots}\n\n"), ask)


def column_prompt(batches: DataFrame, tables: DataFrame) -> DataFrame:
    """One prompt per batch of columns."""
    named = batches.join(tables.select("dataset", "table_id", "table_name"), ["dataset", "table_id"])
    ask = F.concat(F.lit("Table: "), F.coalesce("table_name", F.lit("unknown")), F.lit("\nNames: "), F.array_join("columns", ", "))
    return named.select("dataset", "table_id", "batch", _prompt(ask).alias("prompt"))


def table_prompt_inputs(tables: DataFrame, expanded: DataFrame, max_cols: int = 25) -> DataFrame:
    """(dataset, table_id, table_name, columns): named tables with their first expanded columns."""
    columns = expanded.groupBy("dataset", "table_id").agg(F.array_sort(F.collect_list(F.struct("pos", "expanded"))).alias("c"))
    return tables.where("table_name IS NOT NULL").join(columns, ["dataset", "table_id"], "left").select("dataset", "table_id", "table_name", F.array_join(F.slice(F.transform("c", lambda c: c["expanded"]), 1, max_cols), ", ").alias("columns"))


def table_prompt(tables: DataFrame, expanded: DataFrame, max_cols: int = 25) -> DataFrame:
    rows = table_prompt_inputs(tables, expanded, max_cols)
    return rows.select("dataset", "table_id", _prompt(F.concat(F.lit("Columns: "), "columns", F.lit("\nNames: "), "table_name")).alias("prompt"))


def lexicon(spark) -> DataFrame:
    return spark.createDataFrame(LEXICON, "scope string, token string, phrase string")


def expand(tables: DataFrame, kind: str = "columns") -> DataFrame:
    """(dataset, table_id, table_name, pos, original, mapping, expanded) by the lexicon.

    A token's phrase in the scope of its base table comes before that for any
    table; a token without one stays. The lexicon is a fixed list.
    """
    spark = tables.sparkSession
    names = F.posexplode("columns").alias("pos", "original") if kind == "columns" else F.posexplode(F.array("table_name")).alias("pos", "original")
    rows = tables.select("dataset", "table_id", "table_name", "base", names)
    tokens = rows.select("*", F.posexplode(split_name(F.col("original"))).alias("i", "token"))
    words = lexicon(spark)
    scoped = F.broadcast(words.where("scope <> '*'").select(F.col("scope").alias("base"), "token", F.col("phrase").alias("p1")))
    anywhere = F.broadcast(words.where("scope = '*'").select("token", F.col("phrase").alias("p2")))
    found = tokens.join(scoped, ["base", "token"], "left").join(anywhere, "token", "left").withColumn("phrase", F.coalesce("p1", "p2", "token"))
    pieces = F.array_sort(F.collect_list(F.struct("i", "token", "phrase")))
    out = found.groupBy("dataset", "table_id", "table_name", "pos", "original").agg(pieces.alias("t"))
    mapping = F.transform("t", lambda x: F.struct(x["token"].alias("token"), x["phrase"].alias("phrase")))
    return out.select("dataset", "table_id", "table_name", "pos", "original", mapping.alias("mapping"), F.array_join(F.transform("t", lambda x: x["phrase"]), " ").alias("expanded"))


def expansion_field(expanded: DataFrame) -> DataFrame:
    """(dataset, table_id, text): all expansions of a table in one string, in order."""
    return expanded.groupBy("dataset", "table_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "expanded"))), lambda x: x["expanded"]), " ").alias("text"))


def parse_expansion(answers: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """(answer) of one line to (original, mapping, expanded), after the columns ``keys``; pairs without an arrow are dropped."""
    body = F.trim(F.regexp_replace("answer", "^[^:]*:", ""))
    pairs = F.filter(F.split(body, ","), lambda p: F.contains(p, F.lit("→")))
    mapping = F.transform(pairs, lambda p: F.struct(F.trim(F.split(p, "→")[0]).alias("token"), F.trim(F.split(p, "→")[1]).alias("phrase")))
    return answers.select(*(keys or []), F.trim(F.split("answer", ":")[0]).alias("original"), mapping.alias("mapping"), F.array_join(F.transform(mapping, lambda m: m["phrase"]), " ").alias("expanded"))


def parse_answer(answers: DataFrame) -> DataFrame:
    """``answers`` (..., answer) of many lines to a row a name: what stands after the last "Final answer:", or everything without one.

    Lines without a colon are dropped; a null answer gives no rows.
    """
    final = F.regexp_extract("answer", r"(?si)^(?:.*final answer:)?(.*)$", 1)
    lines = F.filter(F.split(final, "\\r?\\n"), lambda l: F.contains(l, F.lit(":")))
    keys = [c for c in answers.columns if c != "answer"]
    rows = answers.where("answer IS NOT NULL").select(*keys, F.explode(lines).alias("answer"))
    return parse_expansion(rows, keys)


def violations(expanded: DataFrame) -> DataFrame:
    """Rows with the rules a mapping breaks: order, changed numbers, empty phrases, more than one row a token, a changed plain word."""
    tokens = F.transform("mapping", lambda m: m["token"])
    return expanded.select(
        "*",
        (tokens != split_name(F.col("original"))).alias("order_broken"),
        F.exists("mapping", lambda m: m["token"].rlike("^[0-9]+$") & (m["token"] != m["phrase"])).alias("number_changed"),
        F.exists("mapping", lambda m: F.trim(m["phrase"]) == "").alias("phrase_missing"),
        (F.size("mapping") > F.size(split_name(F.col("original")))).alias("something_added"),
        F.exists("mapping", lambda m: m["token"].isin(PLAIN) & (m["token"] != m["phrase"])).alias("plain_changed"),
    )
