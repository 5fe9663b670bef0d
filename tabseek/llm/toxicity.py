"""Toxicity by a factorization machine over hashed terms.

Terms are words (runs of letters, lower case) and their first 4, 5 and 6 bytes,
so that inflected forms of one stem share a term. The machine scores a document
by a bias, a weight for each of its terms, and the products of the terms' factor
vectors: pairs such as an insult and whom it names get weight together that
neither has alone.

The model is fitted on a bounded sample of labelled rows: at most
``sample_per_label`` ids of either label, by hash order, outside the held-out
third. Two kinds of terms are kept, so that what is broadcast has a fixed bound:
at most ``max_terms`` whose share differs between the labels, and at most
``max_paired`` terms of pairs that stand together more often under one label
than their own shares explain, found among the ``pair_terms`` most variable terms
whatever those tell alone. Terms are counted where the sample lies; the driver
gets the counts of those two kinds and the sample's rows cut to them. Every
document's whole text is scored.

Defined cases: a null or empty text has no terms and gets the bias alone; without
rows of both labels every score is that of a margin of -30, next to 0; repeated
rows are scored each for themselves, and of the rows of a sampled doc_id one is
learnt from, with the larger of its labels; an empty table gives no rows; a text
of any length is read in slices. A null label or doc_id is not learnt from.
``score`` replaces columns named ``score`` and ``predicted``; ``keep_clean``
keeps all columns as they are, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from .store import discard, materialise
from .words import mix, text_slices, word_hashes
from .workers import lean

PREFIXES = (4, 5, 6)
FACTORS = 4
HASH_BITS = 24
THRESHOLD = 0.7
#: From so many standard errors on a term, or a pair of the terms that vary most, is learnt from.
TERM_Z, PAIR_Z = 3.5, 6.0

_LETTER = np.zeros(256, dtype=bool)
_LETTER[65:91] = _LETTER[97:123] = _LETTER[128:] = True


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1


def term_hits(column: pa.Array):
    """Yield (first row, rows' numbers, terms): each text's distinct hashed terms, some texts at a time."""
    for row, end, data, offsets in text_slices(column):
        inside = _LETTER[data]
        if not inside.any():
            continue
        edge = np.zeros(len(data) + 1, dtype=bool)
        edge[offsets] = True
        starts = np.flatnonzero(inside & (np.concatenate(([True], ~inside[:-1])) | edge[:-1]))
        ends = np.flatnonzero(inside & (np.concatenate((~inside[1:], [True])) | edge[1:])) + 1
        doc = np.searchsorted(offsets, starts, side="right") - 1
        terms, docs = [word_hashes(data, starts, ends)], [doc]
        for size in PREFIXES:
            longer = np.flatnonzero(ends - starts > size)
            terms.append(mix(word_hashes(data, starts[longer], starts[longer] + size) + np.uint64(size)))
            docs.append(doc[longer])
        folded = np.concatenate(terms) >> np.uint64(64 - HASH_BITS)
        pairs = (np.concatenate(docs).astype(np.uint64) << np.uint64(HASH_BITS)) | folded
        yield row, pairs


def distinct_terms(pairs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    pairs = np.unique(pairs)
    return (pairs >> np.uint64(HASH_BITS)).astype(np.int64), (pairs & np.uint64((1 << HASH_BITS) - 1)).astype(np.int64)


@dataclass
class Model:
    terms: np.ndarray  # ascending
    bias: float
    weights: np.ndarray
    factors: np.ndarray  # terms x FACTORS

    def scores(self, n: int, rows: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Scores of ``n`` documents from (row, place of term) pairs."""
        linear = np.bincount(rows, self.weights[at], n)
        cross = np.zeros(n)
        for f in range(self.factors.shape[1]):
            v = self.factors[at, f]
            cross += np.bincount(rows, v, n) ** 2 - np.bincount(rows, v * v, n)
        margin = np.clip(self.bias + linear + cross / 2, -30, 30)
        return 1 / (1 + np.exp(-margin))


NOTHING_LEARNT = Model(np.zeros(0, np.int64), -30.0, np.zeros(0), np.zeros((0, FACTORS)))


def paired_terms(rows: np.ndarray, at: np.ndarray, n_terms: int, labels: np.ndarray, least: float = PAIR_Z, most: int = 2_000, strip: int = 256) -> np.ndarray:
    """Places of terms that are in a pair whose standing together depends on the label.

    A label's excess is the share of rows with both terms over the product of the
    terms' shares there. A pair counts if the labels' excesses differ by ``least``
    standard errors; the terms of the clearest pairs come first, at most ``most``.
    """
    grams, shares, counts = [], [], []
    for label in (0, 1):
        of = np.flatnonzero(labels == label)
        place = np.full(len(labels), -1)
        place[of] = np.arange(len(of))
        use = np.flatnonzero(place[rows] >= 0)
        own_rows, own_at = place[rows[use]], at[use]  # ascending rows
        gram, table = np.zeros((n_terms, n_terms), np.float32), np.zeros((2 * strip, n_terms), np.float32)
        for start in range(0, len(of), len(table)):
            low, high = np.searchsorted(own_rows, (start, start + len(table)))
            table[:] = 0
            table[own_rows[low:high] - start, own_at[low:high]] = 1
            gram += table.T @ table
        gram /= len(of)
        grams.append(gram)
        shares.append(np.bincount(own_at, minlength=n_terms) / len(of))
        counts.append(len(of))
    best = np.zeros(n_terms)
    for start in range(0, n_terms, strip):
        own = slice(start, start + strip)
        gap, noise = 0.0, 1e-12
        for sign, both, share, count in zip((-1, 1), grams, shares, counts):
            joint = both[own].astype(np.float64)
            gap = gap + sign * (joint - np.outer(share[own], share))
            spread = share * (1 - share)
            noise = noise + (np.maximum(joint * (1 - joint), np.outer(spread[own], spread)) + 1 / count) / count
        z = np.abs(gap) / np.sqrt(noise)
        z[np.arange(z.shape[0]), np.arange(start, start + z.shape[0])] = 0
        best[own] = z.max(1, initial=0)
    found = np.flatnonzero(best > least)
    return np.sort(found[np.argsort(-best[found], kind="stable")[:most]])


def fit(rows: np.ndarray, terms: np.ndarray, labels: np.ndarray, min_steps: int = 1500, epochs: int = 12, rate: float = 0.3, ridge: float = 1e-4, batch: int = 128, factors: int = FACTORS, seed: int = 11) -> Model:
    """Fit on (row, term) pairs, sorted by row, and the rows' labels by adaptive-step gradient descent.

    No ``factors`` make a linear model, for comparison.
    """
    n, positive = len(labels), int(labels.sum())
    if positive in (0, n):
        return NOTHING_LEARNT
    names, at = np.unique(terms, return_inverse=True)
    first = np.searchsorted(rows, np.arange(n + 1))
    random = np.random.default_rng(seed)
    w, v, bias = np.zeros(len(names)), random.normal(0, 0.05, (len(names), factors)), 0.0
    gw, gv, gb = np.full(len(names), 1e-2), np.full(v.shape, 1e-2), 1e-2
    # weight the labels alike whatever the sample holds of each
    worth = np.where(labels == 1, n / (2 * positive), n / (2 * (n - positive)))
    for _ in range(max(epochs, -(-min_steps * batch // n))):
        order = random.permutation(n)
        for start in range(0, n, batch):
            docs = order[start : start + batch]
            sizes = first[docs + 1] - first[docs]
            total = np.cumsum(sizes)
            who = np.repeat(np.arange(len(docs)), sizes)
            ids = at[np.arange(total[-1]) + np.repeat(first[docs] - total + sizes, sizes)]
            vi = v[ids]
            sums = _by_factor(who, vi, len(docs))
            squares = np.bincount(who, (vi * vi).sum(1), len(docs))
            margin = np.clip(bias + np.bincount(who, w[ids], len(docs)) + ((sums**2).sum(1) - squares) / 2, -30, 30)
            step = (1 / (1 + np.exp(-margin)) - labels[docs]) * worth[docs] / len(docs)
            active, pos = np.unique(ids, return_inverse=True)
            dw = np.bincount(pos, step[who], len(active)) + ridge * w[active]
            inner = step[who, None] * (sums[who] - vi)
            dv = _by_factor(pos, inner, len(active)) + ridge * v[active]
            gw[active] += dw * dw
            gv[active] += dv * dv
            gb += step.sum() ** 2
            w[active] -= rate * dw / np.sqrt(gw[active])
            v[active] -= rate / 4 * dv / np.sqrt(gv[active])
            bias -= rate * step.sum() / np.sqrt(gb)
    return Model(names, float(bias), w, v)


def _by_factor(at: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """Sums of the rows of ``values`` by ``at``."""
    out = np.zeros((n, values.shape[1]))
    for f in range(values.shape[1]):
        out[:, f] = np.bincount(at, values[:, f], n)
    return out


def training_rows(labels: DataFrame, sample_per_label: int) -> DataFrame:
    """(_id, _label) of at most ``sample_per_label`` ids of either label outside the held-out third, each id once."""
    usable = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & ~held_out(F.col("doc_id")))
    once = usable.groupBy(F.col("doc_id").cast("long").alias("_id")).agg(F.max(F.col("toxic").cast("int")).alias("_label"))
    parts = [once.where(F.col("_label") == k).orderBy(F.xxhash64("_id"), "_id").limit(sample_per_label) for k in (0, 1)]
    return parts[0].unionByName(parts[1])


def sampled_terms(docs: DataFrame, labels: DataFrame, sample_per_label: int) -> DataFrame:
    """(label, terms) of the sample's whole texts, one row an id, in shared storage."""
    ids = training_rows(labels, sample_per_label)
    sample = docs.select(F.col("doc_id").cast("long").alias("_id"), "text").join(F.broadcast(ids), "_id").select("_id", "_label", "text")

    def terms_of(batches):
        for batch in batches:
            found = [np.zeros(0, np.int32)] * batch.num_rows
            for row, pairs in term_hits(batch.column("text")):
                rows, terms = distinct_terms(pairs)
                for r, part in zip(*_runs(rows, terms)):
                    found[row + r] = part.astype(np.int32)
            yield pa.RecordBatch.from_arrays([batch.column("_id"), batch.column("_label"), pa.array(found, pa.list_(pa.int32()))], ["_id", "label", "terms"])

    # rows of a repeated id meet already where they are read
    once = sample.mapInArrow(terms_of, "_id long, label int, terms array<int>").groupBy("_id").agg(F.min(F.struct("label", "terms")).alias("one"))
    return materialise(once.select("one.label", "one.terms"), "toxicity-sample")


def train(docs: DataFrame, labels: DataFrame, sample_per_label: int = 6_000, max_terms: int = 20_000, pair_terms: int = 2_048, max_paired: int = 2_000, **options) -> Model:
    """Fit on the sample; the driver gets its rows cut to the kept terms and those terms' counts."""
    sample = sampled_terms(docs, labels, sample_per_label)
    n, positive = sample.agg(F.count("*"), F.coalesce(F.sum("label"), F.lit(0))).first()
    if positive in (0, n):
        return NOTHING_LEARNT
    counted = sample.select("label", F.explode("terms").alias("term")).groupBy("term").agg(F.count("*").alias("df"), F.sum("label").alias("seen")).where("df >= 4")
    counted = materialise(counted, "toxicity-terms")
    share1, share0 = (F.col("seen") + 0.5) / (positive + 1), (F.col("df") - F.col("seen") + 0.5) / (n - positive + 1)
    pooled = (F.col("df") + 1) / (n + 2)
    z = F.abs(share1 - share0) / F.sqrt(pooled * (1 - pooled) * (1 / positive + 1 / (n - positive)) + 1e-12)
    alone = counted.where(z > TERM_Z).orderBy(F.desc(z), "term").limit(max_terms)
    variable = counted.orderBy(F.desc(F.col("df") * (n - F.col("df"))), "term").limit(pair_terms)
    alone, variable = (np.sort(np.array([r.term for r in part.select("term").collect()], np.int64)) for part in (alone, variable))
    kept = docs.sparkSession.sparkContext.broadcast(np.union1d(alone, variable).astype(np.int32))

    def cut(batches):
        for batch in batches:
            lists = batch.column("terms")
            held = np.isin(lists.flatten().to_numpy(zero_copy_only=False), kept.value)
            before = np.concatenate(([0], np.cumsum(held)))[np.concatenate(([0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))))]
            values = lists.flatten().filter(pa.array(held))
            yield pa.RecordBatch.from_arrays([batch.column("label"), pa.ListArray.from_arrays(pa.array(before, pa.int32()), values)], ["label", "terms"])

    got = sample.mapInArrow(cut, "label int, terms array<int>").toArrow()
    discard(sample, counted)
    labels_ = np.asarray(got.column("label")).astype(np.int64)
    lists = got.column("terms").combine_chunks()
    # rows come in no fixed order: sort them, so that reruns fit the same model
    flat, ends = np.asarray(lists.flatten()).astype(np.int64), np.concatenate(([0], np.cumsum(np.asarray(lists.value_lengths()))))
    key = [int(np.bitwise_xor.reduce(mix(flat[a:b].astype(np.uint64)), initial=np.uint64(b - a))) for a, b in zip(ends[:-1], ends[1:])]
    order = np.lexsort((np.array(key, np.uint64), labels_))
    rows = np.repeat(np.arange(len(order)), (ends[1:] - ends[:-1])[order])
    terms = np.concatenate([flat[ends[i] : ends[i + 1]] for i in order])
    labels_ = labels_[order]
    if len(variable):
        at = np.minimum(np.searchsorted(variable, terms), len(variable) - 1)
        use = variable[at] == terms
        alone = np.union1d(alone, variable[paired_terms(rows[use], at[use], len(variable), labels_, most=max_paired)])
    use = np.isin(terms, alone)
    return fit(rows[use], terms[use], labels_, **options)


def _runs(rows: np.ndarray, terms: np.ndarray):
    if not len(rows):
        return [], []
    cuts = np.flatnonzero(np.diff(rows)) + 1
    return rows[np.concatenate(([0], cuts))].tolist(), np.split(terms, cuts)


def batch_scores(model: Model, texts: pa.Array) -> np.ndarray:
    """The score of each whole text of an Arrow column."""
    out = np.full(len(texts), float(model.scores(1, np.zeros(0, np.int64), np.zeros(0, np.int64))[0]))
    if not len(model.terms):
        return out
    for row, pairs in term_hits(texts):
        terms = (pairs & np.uint64((1 << HASH_BITS) - 1)).astype(np.int64)
        at = np.minimum(np.searchsorted(model.terms, terms), len(model.terms) - 1)
        rows, terms = distinct_terms(pairs[model.terms[at] == terms])
        if len(rows):
            low, n = rows[0], rows[-1] - rows[0] + 1
            out[row + low : row + low + n] = model.scores(n, rows - low, np.searchsorted(model.terms, terms))
    return out


def score(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` with ``score`` and ``predicted``; columns of those names are replaced."""
    docs = docs.drop("score", "predicted")
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            out = batch_scores(shared.value, batch.column("text"))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out), pa.array((out >= THRESHOLD).astype(np.int32))], [*batch.schema.names, "score", "predicted"])

    schema = T.StructType([*docs.schema.fields, T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])
    return docs.mapInArrow(run, schema)


def report(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """Per row of ``docs``: doc_id, held_out, score, predicted."""
    model = train(docs, labels, **options)
    return score(docs.select("doc_id", "text"), model).select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", "predicted")


def keep_clean(docs: DataFrame, corpus: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that a model fitted on ``corpus`` does not reject, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(train(corpus, labels, **options))

    def run(batches):
        for batch in batches:
            yield batch.filter(pa.array(batch_scores(shared.value, batch.column("text")) < THRESHOLD))

    return docs.mapInArrow(lean(run), docs.schema)
