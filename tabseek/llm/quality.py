"""Quality rules as a bitmask ledger, in DataFrame expressions only.

Every rule is evaluated once per document; its failure sets a bit. Measurements
and bits form the ledger. A policy is a versioned mask of the bits that reject,
so policies are applied, compared and ablated later by bitwise operations on
the ledger alone, without reading a text again.

Words are runs of characters outside space and 0x09-0x0D. Defined cases: a null
text has no words and no lines; repeated rows are judged each for themselves; an
empty table gives no rows. Arrays of a text stay inside its row: nothing is
exploded or shuffled.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

WORD = r"[^\x20\x09-\x0D]+"
_SPACES = " \t\n\x0b\f\r"
_SYMBOLS = "#*$%&|<>"
_WINDOW = 3

#: Bits in order. The first two are the base rules.
RULES = {
    "too_few_words": "n_words < 50",
    "repeated_windows": "100 * n_repeat_words > 50 * n_words",
    "symbols": "10 * n_symbols > n_words",
    "duplicate_lines": "n_dup_lines >= 3 AND 10 * n_dup_lines > 3 * n_lines",
    "short_words": "word_chars < 2 * n_words",
    "long_words": "word_chars > 20 * n_words",
    "too_many_words": "n_words > 100000",
}
BIT = {name: 1 << i for i, name in enumerate(RULES)}
BASE_MASK = BIT["too_few_words"] | BIT["repeated_windows"]

#: Versioned policies: which failures reject.
POLICIES = {
    "base": BASE_MASK,
    "v1": BASE_MASK | BIT["symbols"] | BIT["duplicate_lines"] | BIT["short_words"] | BIT["long_words"],
    "strict": (1 << len(RULES)) - 1,
}
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def measure(docs: DataFrame) -> DataFrame:
    """``docs`` with the measurements; columns of those names are replaced."""
    text = F.coalesce(F.col("text"), F.lit(""))
    kept = [c for c in docs.columns if c not in (*MEASURES, "n_lines") and not c.startswith("_q_")]
    words = docs.select(*kept, F.regexp_extract_all(text, F.lit(WORD), F.lit(0)).alias("_q_words"), F.filter(F.split(text, "\n", -1), lambda line: line.rlike(WORD)).alias("_q_lines"))
    counts = words.select(
        *kept,
        F.size("_q_words").cast("long").alias("n_words"),
        F.length(F.translate(text, _SPACES, "")).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, _SYMBOLS, ""))).cast("long").alias("n_symbols"),
        F.size("_q_lines").cast("long").alias("n_lines"),
        (F.size("_q_lines") - F.size(F.array_distinct("_q_lines"))).cast("long").alias("n_dup_lines"),
        # word hashes first: a window's hash then mixes three numbers, not three strings
        F.transform("_q_words", lambda w: F.xxhash64(w)).alias("_q_hashes"),
    )
    windows = counts.withColumn(
        "_q_windows",
        F.when(F.size("_q_hashes") >= _WINDOW, F.zip_with(F.zip_with("_q_hashes", F.slice("_q_hashes", 2, F.greatest(F.size("_q_hashes"), F.lit(1))), lambda a, b: F.xxhash64(a, b)), F.slice("_q_hashes", 3, F.greatest(F.size("_q_hashes"), F.lit(1))), lambda ab, c: F.when(c.isNotNull(), F.xxhash64(ab, c)))),
    ).drop("_q_hashes")
    # zip_with pads the shorter side with nulls: the last two windows are null
    windows = windows.withColumn("_q_windows", F.array_compact("_q_windows"))
    repeats = windows.withColumn(
        "_q_sorted",
        F.when(F.size(F.array_distinct("_q_windows")) < F.size("_q_windows"), F.array_sort(F.transform("_q_windows", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))),
    ).drop("_q_windows")
    equal_next = F.zip_with("_q_sorted", F.slice("_q_sorted", 2, F.greatest(F.size("_q_sorted"), F.lit(1))), lambda a, b: F.coalesce(a["h"] == b["h"], F.lit(False)))
    flagged = repeats.withColumn("_q_next", equal_next)
    # a window repeats if its hash equals that of its neighbour on either side
    shifted = F.concat(F.array(F.lit(False)), F.col("_q_next"))
    marked = F.zip_with("_q_sorted", F.zip_with("_q_next", shifted, lambda a, b: F.coalesce(a, F.lit(False)) | b), lambda w, again: F.when(again & w.isNotNull(), w["i"]))
    places = flagged.withColumn("_q_places", F.sort_array(F.array_compact(marked))).drop("_q_sorted", "_q_next")
    covered = F.aggregate(
        "_q_places",
        F.struct(F.lit(0).cast("long").alias("n"), F.lit(-_WINDOW).alias("last")),
        lambda s, i: F.struct((s["n"] + F.least(i - s["last"], F.lit(_WINDOW))).alias("n"), i.alias("last")),
        lambda s: s["n"],
    )
    return places.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long")).drop("_q_places")


def ledger(docs: DataFrame) -> DataFrame:
    """``docs`` with measurements and ``fail_bits``: bit i is set if rule i fails."""
    bits = F.lit(0).cast("long")
    for name, failed in RULES.items():
        bits = bits.bitwiseOR(F.when(F.expr(failed), BIT[name]).otherwise(0).cast("long"))
    return measure(docs).withColumn("fail_bits", bits)


def apply_policy(entries: DataFrame, policy: str = "v1") -> DataFrame:
    """Ledger rows with ``base_failed`` and the policy's verdict ``kept``."""
    return entries.withColumn("base_failed", F.col("fail_bits").bitwiseAND(F.lit(BASE_MASK)) != 0).withColumn("kept", F.col("fail_bits").bitwiseAND(F.lit(POLICIES[policy])) == 0)


def ablations(entries: DataFrame, policy: str = "v1") -> DataFrame:
    """Per rule of a policy: documents failing it, failing it alone, and kept without it.

    One aggregation over the distinct failure patterns, of which there are at
    most two to the number of rules.
    """
    mask = POLICIES[policy]
    patterns = entries.groupBy("fail_bits").count()
    hit = F.col("fail_bits").bitwiseAND(F.lit(mask))
    rows = F.explode(F.array(*[F.struct(F.lit(n).alias("rule"), F.lit(b).cast("long").alias("bit")) for n, b in BIT.items() if b & mask])).alias("r")
    return patterns.select("count", hit.alias("hit"), rows).groupBy(F.col("r.rule").alias("rule")).agg(
        F.sum(F.when(F.col("hit").bitwiseAND(F.col("r.bit")) != 0, F.col("count")).otherwise(0)).alias("n_failed"),
        F.sum(F.when(F.col("hit") == F.col("r.bit"), F.col("count")).otherwise(0)).alias("n_failed_alone"),
        F.sum(F.when(F.col("hit").bitwiseAND(F.bitwise_not(F.col("r.bit"))) == 0, F.col("count")).otherwise(0)).alias("n_kept_without"),
    )


def judge(docs: DataFrame, policy: str = "v1") -> DataFrame:
    """Per row: doc_id, the measurements, the bits, ``base_failed`` and ``kept``."""
    return apply_policy(ledger(docs.select("doc_id", "text")), policy).select("doc_id", *MEASURES, "fail_bits", "base_failed", "kept")


ORACLE = r"""
WITH t AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT *, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words,
             list_filter(string_split(text, chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]+')) AS lines FROM t),
win AS (SELECT r, i, words[i] || chr(32) || words[i + 1] || chr(32) || words[i + 2] AS g
        FROM (SELECT r, words, unnest(range(1, greatest(len(words) - 1, 1))) AS i FROM w)),
twice AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, g) AS c FROM win) WHERE c > 1),
cover AS (SELECT r, count(DISTINCT i + o) AS n FROM twice, (SELECT unnest([0, 1, 2]) AS o) GROUP BY r),
m AS (
  SELECT doc_id, len(words)::BIGINT AS n_words,
         length(regexp_replace(text, '[\x20\x09-\x0D]+', '', 'g'))::BIGINT AS word_chars,
         (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
         len(lines)::BIGINT AS n_lines,
         (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
         coalesce(n, 0)::BIGINT AS n_repeat_words
  FROM w LEFT JOIN cover USING (r)),
b AS (
  SELECT *, (CASE WHEN n_words < 50 THEN 1 ELSE 0 END + CASE WHEN 100 * n_repeat_words > 50 * n_words THEN 2 ELSE 0 END
     + CASE WHEN 10 * n_symbols > n_words THEN 4 ELSE 0 END
     + CASE WHEN n_dup_lines >= 3 AND 10 * n_dup_lines > 3 * n_lines THEN 8 ELSE 0 END
     + CASE WHEN word_chars < 2 * n_words THEN 16 ELSE 0 END + CASE WHEN word_chars > 20 * n_words THEN 32 ELSE 0 END
     + CASE WHEN n_words > 100000 THEN 64 ELSE 0 END)::BIGINT AS fail_bits FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, fail_bits,
       (fail_bits & 3) <> 0 AS base_failed, (fail_bits & 63) = 0 AS kept FROM b
"""
