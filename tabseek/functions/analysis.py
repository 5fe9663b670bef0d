"""Text analysis: words, trigrams, and the classic English suffix stemmer (A1-A5).

All analyzers are Column expressions. Stemming works on the distinct vocabulary
and is joined back, so its regex chain runs once per term, not once per token.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, functions as F

#: Letters and digits of the languages served; one explicit class for all engines.
WORD = "[0-9a-zà-öø-ÿß]+"


def words(text: Column) -> Column:
    """Lower-case word tokens; a null text has none."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(WORD), F.lit(0))


def tally(terms: Column) -> Column:
    """(tf, term) of each distinct term of an array, by term: counted in the row, so nothing is shuffled."""

    def counted(ordered):
        begins = F.filter(F.transform(ordered, lambda w, i: F.when((i == 0) | (F.get(ordered, i - 1) != w), i).otherwise(-1)), lambda i: i >= 0)
        ends = lambda at: F.transform(at, lambda i, j: F.struct((F.coalesce(F.get(at, j + 1), F.size(ordered)) - i).alias("tf"), F.get(ordered, i).alias("term")))
        return F.get(F.transform(F.array(begins), ends), F.lit(0))

    # arrays of one element bind what is used more than once
    return F.get(F.transform(F.array(F.sort_array(terms)), counted), F.lit(0))


def trigrams(text: Column) -> Column:
    """Character 3-grams of each word; shorter words stay whole."""
    grams = F.transform(
        words(text),
        lambda w: F.when(F.length(w) < 3, F.array(w)).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(F.length(w) - 2, F.lit(1))), lambda i: F.substr(w, i, F.lit(3)))),
    )
    return F.flatten(grams)


@dataclass(frozen=True)
class Analyzer:
    """How a field's text becomes terms; ``id`` is stored with an index built by it."""

    kind: str = "word_nostem"  # word | word_nostem | trigram

    @property
    def id(self) -> str:
        return f"{self.kind}/1"

    def tokens(self, text: Column) -> Column:
        """Tokens before stemming."""
        return trigrams(text) if self.kind == "trigram" else words(text)

    def finish(self, terms: DataFrame, column: str = "term") -> DataFrame:
        """Stem the term column if this analyzer stems."""
        if self.kind != "word":
            return terms
        vocabulary = stem_terms(terms.select(column).distinct(), column)
        return terms.join(vocabulary, column).drop(column).withColumnRenamed("stem", column)


WORDS, STEMMED, TRIGRAMS = Analyzer(), Analyzer("word"), Analyzer("trigram")

# The measure of a stem counts vowel-consonant sequences; y after a consonant is a vowel.
_C, _V = "(?:[^aeiouy]|(?<![^aeiou])y|^y)", "(?:[aeiou]|(?<=[^aeiou])y)"
_M_GT_0 = f"^{_C}*{_V}+{_C}"
_M_GT_1 = f"^{_C}*{_V}+{_C}+{_V}+{_C}"
_M_EQ_1 = f"^{_C}*{_V}+{_C}+{_V}*$"
_HAS_VOWEL = _V
_DOUBLE = r"([^aeiouy])\1$"
_CVC = f"{_C}{_V}[^aeiouwxy]$"

#: Suffixes and replacements of steps 2, 3 and 4.
STEP2 = [("ational", "ate"), ("tional", "tion"), ("enci", "ence"), ("anci", "ance"), ("izer", "ize"), ("abli", "able"), ("alli", "al"), ("entli", "ent"), ("eli", "e"), ("ousli", "ous"), ("ization", "ize"), ("ation", "ate"), ("ator", "ate"), ("alism", "al"), ("iveness", "ive"), ("fulness", "ful"), ("ousness", "ous"), ("aliti", "al"), ("iviti", "ive"), ("biliti", "ble")]
STEP3 = [("icate", "ic"), ("ative", ""), ("alize", "al"), ("iciti", "ic"), ("ical", "ic"), ("ful", ""), ("ness", "")]
STEP4 = ["al", "ance", "ence", "er", "ic", "able", "ible", "ant", "ement", "ment", "ent", "ion", "ou", "ism", "ate", "iti", "ous", "ive", "ize"]


def _drop(word: Column, suffix: str) -> Column:
    return F.substring(word, 1, F.length(word) - len(suffix)) if suffix else word


def _first(word: Column, cases: list[tuple[Column, Column]]) -> Column:
    """The value of the first case that holds, else the word."""
    chain = None
    for holds, value in cases:
        chain = F.when(holds, value) if chain is None else chain.when(holds, value)
    return chain.otherwise(word)


def step1a(word: Column) -> Column:
    return _first(word, [(word.endswith("sses"), _drop(word, "es")), (word.endswith("ies"), _drop(word, "es")), (word.endswith("ss"), word), (word.endswith("s"), _drop(word, "s"))])


def step1b(word: Column) -> Column:
    def mended(stem: Column) -> Column:
        return _first(
            stem,
            [
                (stem.endswith("at") | stem.endswith("bl") | stem.endswith("iz"), F.concat(stem, F.lit("e"))),
                (stem.rlike(_DOUBLE) & ~stem.rlike("[lsz]$"), _drop(stem, "x")),
                (stem.rlike(_M_EQ_1) & stem.rlike(_CVC), F.concat(stem, F.lit("e"))),
            ],
        )

    return _first(
        word,
        [
            (word.endswith("eed"), F.when(_drop(word, "eed").rlike(_M_GT_0), _drop(word, "d")).otherwise(word)),
            (word.endswith("ed") & _drop(word, "ed").rlike(_HAS_VOWEL), mended(_drop(word, "ed"))),
            (word.endswith("ing") & _drop(word, "ing").rlike(_HAS_VOWEL), mended(_drop(word, "ing"))),
        ],
    )


def step1c(word: Column) -> Column:
    return F.when(word.endswith("y") & _drop(word, "y").rlike(_HAS_VOWEL), F.concat(_drop(word, "y"), F.lit("i"))).otherwise(word)


def _replace(word: Column, pairs: list[tuple[str, str]]) -> Column:
    """The longest suffix that matches decides; it is replaced if the measure before it is above 0."""
    return _first(word, [(word.endswith(old), F.when(_drop(word, old).rlike(_M_GT_0), F.concat(_drop(word, old), F.lit(new))).otherwise(word)) for old, new in sorted(pairs, key=lambda p: -len(p[0]))])


def step4(word: Column) -> Column:
    def cut(suffix: str) -> Column:
        stem = _drop(word, suffix)
        fits = stem.rlike(_M_GT_1) & (stem.rlike("[st]$") if suffix == "ion" else F.lit(True))
        return F.when(fits, stem).otherwise(word)

    return _first(word, [(word.endswith(s), cut(s)) for s in sorted(STEP4, key=len, reverse=True)])


def step5(word: Column) -> Column:
    stem = _drop(word, "e")
    without_e = F.when(word.endswith("e") & (stem.rlike(_M_GT_1) | (stem.rlike(_M_GT_0) & ~(stem.rlike(_M_EQ_1) & stem.rlike(_CVC)))), stem).otherwise(word)
    return without_e


def step5b(word: Column) -> Column:
    return F.when(word.endswith("ll") & _drop(word, "l").rlike(_M_GT_1), _drop(word, "l")).otherwise(word)


_STEPS = [step1a, step1b, step1c, lambda w: _replace(w, STEP2), lambda w: _replace(w, STEP3), step4, step5, step5b]


def stem_terms(vocabulary: DataFrame, column: str = "term") -> DataFrame:
    """Distinct terms with their ``stem``; words of one or two letters and non-ASCII words stay.

    One projection per step keeps every generated method small.
    """
    plain = F.col(column).rlike("^[a-z]{3,}$")
    out = vocabulary.withColumn("stem", F.col(column))
    for step in _STEPS:
        out = out.withColumn("stem", F.when(plain, step(F.col("stem"))).otherwise(F.col("stem")))
    return out
