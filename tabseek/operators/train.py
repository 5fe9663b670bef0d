"""Preference training of a description generator.

No large model is at hand, so the trainable stand-in is log-linear: a
description is a sequence of slot choices from a phrase vocabulary, and its log
likelihood is a sum of log-softmax terms over hashed prompt features. It has what
the objective needs: an exact likelihood, a frozen reference, a low-rank adapter
and sampling. Real models attach through the pair export.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, functions as F


def _softplus(x: Column) -> Column:
    return F.greatest(x, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x)))


def margin() -> Column:
    """How much more the policy prefers the winner than the reference does."""
    return (F.col("win") - F.col("win_ref")) - (F.col("lose") - F.col("lose_ref"))


def preference_loss(rows: DataFrame, beta: float = 0.1) -> DataFrame:
    """Mean loss of (win, win_ref, lose, lose_ref) log likelihoods, in its stable form."""
    return rows.agg(F.lit(beta).alias("beta"), F.round(F.avg(_softplus(-F.lit(beta) * margin())), 6).alias("loss"))


def margins(rows: DataFrame, beta: float = 0.1) -> DataFrame:
    """Mean implied reward margin and the share of pairs ordered rightly."""
    return rows.agg(F.round(F.avg(F.lit(beta) * margin()), 6).alias("avg_margin"), F.round(F.avg((margin() > 0).cast("double")), 6).alias("accuracy"))


def linear_warmup(step, total, warmup: float = 0.1, rate: float = 5e-6):
    """Learning rate at a step (a number or a Column): linear rise, then linear fall to 0."""
    if isinstance(step, Column):
        rise = F.greatest(F.floor(total * F.lit(warmup)), F.lit(1))
        return F.lit(rate) * F.when(step < rise, step / rise).otherwise(F.greatest((total - step) / F.greatest(total - rise, F.lit(1)), F.lit(0.0)))
    rise = max(int(total * warmup), 1)
    return rate * (step / rise if step < rise else max((total - step) / max(total - rise, 1), 0.0))


def quantize(weights: np.ndarray, bits: int = 4, block: int = 64) -> np.ndarray:
    """Weights as signed codes of ``bits`` bits of their block's largest magnitude, and back."""
    flat, top = weights.ravel(), 2 ** (bits - 1) - 1
    padded = np.pad(flat, (0, -len(flat) % block)).reshape(-1, block)
    scale = np.abs(padded).max(1, keepdims=True)
    codes = np.round(padded / np.where(scale > 0, scale, 1) * top)
    return (codes / top * scale).ravel()[: len(flat)].reshape(weights.shape)


def quantize4(weights: np.ndarray, block: int = 64) -> np.ndarray:
    """4-bit weights; the error is at most 1/14 of a block's largest magnitude."""
    return quantize(weights, 4, block)


@dataclass
class LowRank:
    """A frozen matrix plus ``alpha / rank`` times the product of two narrow ones; the second starts at 0."""

    base: np.ndarray
    a: np.ndarray
    b: np.ndarray
    scale: float

    @classmethod
    def new(cls, base: np.ndarray, rank: int, alpha: float, seed: int = 42) -> LowRank:
        random = np.random.default_rng(seed)
        return cls(base, random.normal(0, 1 / np.sqrt(base.shape[1]), (rank, base.shape[1])), np.zeros((base.shape[0], rank)), alpha / rank)

    @property
    def n_trainable(self) -> int:
        return self.a.size + self.b.size

    def weights(self) -> np.ndarray:
        return self.base + self.scale * self.b @ self.a


#: The stand-in's logits are small; this makes a draw at the published temperature depend on them.
LOGIT_SCALE = 8.0


@dataclass(frozen=True)
class TrainConfig:
    """Settings of a training run. Rank, scale, batch, warm-up and bits are the published ones; ``rate`` suits the
    stand-in generator, whose few weights a published rate of 5e-6 would leave where they are."""

    beta: float = 0.1
    rank: int = 64
    alpha: float = 64.0
    rate: float = 0.02
    warmup: float = 0.1
    batch: int = 8
    epochs: int = 1
    bits: int = 4
    state_bits: int = 8
    seed: int = 42
    features: int = 64
    vocabulary: int = 128


def _bucket(text: str, n: int) -> int:
    return zlib.crc32(text.encode()) % n


def features(prompt: str, n: int) -> np.ndarray:
    """Hashed word counts of a prompt, of length 1."""
    out = np.zeros(n)
    for word in (prompt or "").split():
        out[_bucket(word, n)] += 1
    return out / (np.linalg.norm(out) or 1.0)


def choices(body: str, n: int) -> np.ndarray:
    """How often each phrase bucket stands in a description."""
    return np.bincount([_bucket(w, n) for w in (body or "").split()] or [0], minlength=n) * (1.0 if body else 0.0)


def log_likelihood(weights: np.ndarray, x: np.ndarray, counts: np.ndarray) -> float:
    logits = weights @ x
    top = logits.max()
    return float(counts @ (logits - top - np.log(np.exp(logits - top).sum())))


def log_likelihoods(weights: np.ndarray, xs: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """``log_likelihood`` of many descriptions, row by row."""
    logits = xs @ weights.T
    top = logits.max(1, keepdims=True)
    return (counts * (logits - top - np.log(np.exp(logits - top).sum(1, keepdims=True)))).sum(1)


def base_weights(cfg: TrainConfig, prior: int = 0) -> np.ndarray:
    """The frozen generator; another ``prior`` is another base model."""
    base = np.random.default_rng(1000 + prior).normal(0, 0.1, (cfg.vocabulary, cfg.features))
    return quantize4(base) if cfg.bits == 4 else base


def fit(pairs: pd.DataFrame, cfg: TrainConfig, prior: int = 0) -> tuple[LowRank, pd.DataFrame]:
    """Train on (prompt, chosen, rejected); returns the adapter and a row of diagnostics per step."""
    pairs = pairs.sort_values(["dataset", "table_id"]).reset_index(drop=True)
    model = LowRank.new(base_weights(cfg, prior), cfg.rank, cfg.alpha, cfg.seed)
    xs = np.stack([features(p, cfg.features) for p in pairs["prompt"]])
    wins = np.stack([choices(c, cfg.vocabulary) for c in pairs["chosen"]])
    loses = np.stack([choices(c, cfg.vocabulary) for c in pairs["rejected"]])
    reference = log_likelihoods(model.base, xs, wins) - log_likelihoods(model.base, xs, loses)
    total = cfg.epochs * -(-len(pairs) // cfg.batch)
    first, second = ({n: np.zeros_like(getattr(model, n)) for n in "ab"} for _ in range(2))
    stored = (lambda m: quantize(m, cfg.state_bits)) if cfg.state_bits < 32 else (lambda m: m)
    steps, step = [], 0
    for epoch in range(cfg.epochs):
        order = np.random.default_rng(cfg.seed + epoch).permutation(len(pairs))
        for start in range(0, len(order), cfg.batch):
            rows, weights = order[start : start + cfg.batch], model.weights()
            x, win, lose = xs[rows], wins[rows], loses[rows]
            gap = log_likelihoods(weights, x, win) - log_likelihoods(weights, x, lose) - reference[rows]
            logits = x @ weights.T
            p = np.exp(logits - logits.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            towards = (win - win.sum(1, keepdims=True) * p) - (lose - lose.sum(1, keepdims=True) * p)
            scaled = np.clip(cfg.beta * gap, -30, 30)
            slope = -cfg.beta / (1 + np.exp(scaled))
            grad = (slope[:, None] * towards).T @ x / len(rows)
            step += 1
            rate = linear_warmup(step, total + 1, cfg.warmup, cfg.rate)
            grads = {"b": model.scale * grad @ model.a.T, "a": model.scale * model.b.T @ grad}
            for name, g in grads.items():  # adaptive moments with decoupled decay, kept in few bits
                first[name] = stored(0.9 * first[name] + 0.1 * g)
                second[name] = stored(np.sqrt(0.999 * second[name] ** 2 + 0.001 * g * g))  # the root, which fewer bits hold better
                move = (first[name] / (1 - 0.9**step)) / (np.maximum(second[name], np.abs(first[name]) / 30) / np.sqrt(1 - 0.999**step) + 1e-8)
                value = getattr(model, name)
                setattr(model, name, value - rate * (move + 0.01 * value))
            steps.append((step, float(np.log1p(np.exp(-scaled)).mean()), float(cfg.beta * gap.mean()), float((gap > 0).mean())))
    return model, pd.DataFrame(steps, columns=["step", "loss", "margin", "accuracy"])


def train_folds(folds: DataFrame, cfg: TrainConfig = TrainConfig()) -> DataFrame:
    """Diagnostics of every held-out dataset's training; a fold's pairs, megabytes, train in one task."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        _, steps = fit(frame, cfg)
        return steps.assign(held_out=frame["held_out"].iloc[0])

    return folds.groupBy("held_out").applyInPandas(run, "step long, loss double, margin double, accuracy double, held_out string")


def adapters(folds: DataFrame, cfg: TrainConfig = TrainConfig(), prior: int = 0) -> DataFrame:
    """(held_out, a, b): every fold's trained adapter, whose size is that of ``cfg``, not of the data."""
    return many_adapters(folds.withColumn("run", F.lit("")), {"": (cfg, prior)}).drop("run")


def many_adapters(folds: DataFrame, runs: dict[str, tuple[TrainConfig, int]]) -> DataFrame:
    """(run, held_out, a, b): ``adapters`` of many training runs, a task each; ``folds`` has the pairs of each run, ``runs`` its settings."""

    def train(frame: pd.DataFrame) -> pd.DataFrame:
        name = frame["run"].iloc[0]
        model, _ = fit(frame, *runs[name])
        return pd.DataFrame({"run": [name], "held_out": frame["held_out"].iloc[:1].tolist(), "a": [model.a.ravel()], "b": [model.b.ravel()]})

    return folds.groupBy("run", "held_out").applyInPandas(train, "run string, held_out string, a array<double>, b array<double>")


def describe_by_sampling(words: list[str], logits: np.ndarray, n: int, seed: int, temperature: float = 0.5, top_p: float = 0.9, top_k: int = 50) -> str:
    """A description of ``n`` slots: words of a table, drawn one after another without repetition by ``sample``."""
    random, out = np.random.default_rng(seed), []
    order = np.argsort(-logits, kind="stable")
    for _ in range(min(n, len(words))):
        at = sample(logits[order[:top_k]], temperature, top_p, top_k, random)
        out.append(words[order[at]])
        order = np.delete(order, at)
    return " ".join(out)


#: Tables whose descriptions are drawn together, and words whose hash a task remembers.
DRAWN_AT_ONCE, REMEMBERED = 512, 1 << 18


def draw_many(logits: np.ndarray, sizes: np.ndarray, n: int, seeds: list[int], temperature: float = 0.5, top_p: float = 0.9, top_k: int = 50) -> list[list[int]]:
    """The places drawn by ``describe_by_sampling`` in many rows at once; ``logits`` (row, place) count up to a row's size."""
    rows, width = logits.shape
    logits = np.where(np.arange(width) < sizes[:, None], logits, -np.inf)
    order = np.argsort(-logits, axis=1, kind="stable")[:, : n + top_k]  # more are never looked at
    value = np.take_along_axis(logits, order, 1)
    alive = np.isfinite(value)
    uniform = np.stack([np.random.default_rng(s).random(n) for s in seeds]) if rows else np.zeros((0, n))
    at_row, out = np.arange(rows), []
    for step in range(min(n, width)):
        left = alive & (np.cumsum(alive, 1) <= top_k)
        best = np.where(left, value, -np.inf).max(1, keepdims=True)
        p = np.exp(np.where(left, value - np.where(np.isfinite(best), best, 0), -np.inf) / temperature)
        total = p.sum(1, keepdims=True)
        p /= np.where(total > 0, total, 1)
        # the head ends with the place at which the mass reaches top_p
        p[np.cumsum(np.cumsum(p, 1) >= top_p, 1) > 1] = 0.0
        p /= np.where(total > 0, p.sum(1, keepdims=True), 1)
        over = (np.cumsum(p, 1) > uniform[:, step : step + 1]) & (p > 0)
        chosen = np.where(over.any(1), over.argmax(1), p.shape[1] - 1 - (p > 0)[:, ::-1].argmax(1))
        out.append(np.where(step < sizes, order[at_row, chosen], -1))
        alive[at_row, chosen] = False
    picked = np.stack(out, 1) if out else np.zeros((rows, 0), int)
    return [[j for j in row if j >= 0] for row in picked.tolist()]


class _Hashes(dict):
    """Words' hashes, remembered up to a number."""

    def __missing__(self, word: str) -> int:
        if len(self) >= REMEMBERED:
            self.clear()
        at = self[word] = zlib.crc32(word.encode())
        return at


def _described(frame: pd.DataFrame, weights: np.ndarray, cfg: TrainConfig, n: int, seed: int, hashes: _Hashes) -> pd.DataFrame:
    """``generate`` of a few tables."""
    words = [list(dict.fromkeys(w if w is not None else [])) for w in frame["words"]]
    sizes = np.array([len(w) for w in words], int)
    said = [list(s if s is not None else []) for s in frame["said"]]
    prompts = [(p or "").split() for p in frame["prompt"]]
    # all words of all rows at once
    hashed = lambda lists: np.fromiter(map(hashes.__getitem__, chain.from_iterable(lists)), np.int64)
    at = np.repeat(np.arange(len(frame)), np.array([len(p) for p in prompts], int))
    xs = np.bincount(at * cfg.features + hashed(prompts) % cfg.features, minlength=len(frame) * cfg.features).reshape(len(frame), cfg.features).astype(float)
    # row by row: weights of few bits tie often, and a product of matrices would round ties apart
    phrases = np.stack([weights @ (x / (np.linalg.norm(x) or 1.0)) for x in xs]) if len(xs) else np.zeros((0, len(weights)))
    logits = np.full((len(frame), max(1, sizes.max(initial=0))), -np.inf)
    row = np.repeat(np.arange(len(frame)), sizes)
    place = np.arange(len(row)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    logits[row, place] = phrases[row, hashed(words) % cfg.vocabulary] * LOGIT_SCALE
    counts = frame["k"].to_numpy().astype(int)
    of, cand = np.repeat(np.arange(len(frame)), counts), [c for k in counts for c in range(k)]
    names, ids = frame["dataset"].tolist(), frame["table_id"].tolist()
    seeds = [_bucket(f"{seed}:{names[i]}:{ids[i]}:{c}", 1 << 31) for i, c in zip(of, cand)]
    drawn = draw_many(logits[of], sizes[of], n, seeds)
    bodies = [" ".join([*said[i], " ".join(words[i][j] for j in row)]).strip() for i, row in zip(of, drawn)]
    return pd.DataFrame({"dataset": [names[i] for i in of], "table_id": [ids[i] for i in of], "cand_id": cand, "body": bodies}, columns=["dataset", "table_id", "cand_id", "body"])


def generate(tables: DataFrame, weights: np.ndarray, cfg: TrainConfig = TrainConfig(), k: int = 1, n: int = 30, seed: int = 42) -> DataFrame:
    """(dataset, table_id, cand_id, body): ``k`` descriptions of each table, sampled from the generator.

    ``tables`` (dataset, table_id, prompt, words): what a description may say are
    the table's ``words``; a column ``k``, if there, tells how many each table gets, and words in a
    column ``said`` open each of its descriptions. The seed of a draw follows from the table and the
    candidate alone, so partitioning does not matter. A table without words gets
    empty descriptions. ``weights`` have the size of ``cfg`` and go with the plan.
    """

    def run(frames):
        hashes = _Hashes()
        for frame in frames:
            for start in range(0, len(frame), DRAWN_AT_ONCE):
                yield _described(frame.iloc[start : start + DRAWN_AT_ONCE], weights, cfg, n, seed, hashes)

    wanted = tables if "k" in tables.columns else tables.withColumn("k", F.lit(k))
    wanted = wanted if "said" in tables.columns else wanted.withColumn("said", F.array().cast("array<string>"))
    # a description is long work on few bytes, so tables are dealt to all cores
    spread = wanted.select("dataset", "table_id", "prompt", "words", "k", "said").repartition(tables.sparkSession.sparkContext.defaultParallelism, "dataset", "table_id")
    return spread.mapInPandas(run, "dataset string, table_id long, cand_id int, body string")


@dataclass(frozen=True)
class Voice:
    """A generator as one of many: its weights, the configuration they have the size of, and how many words it draws."""

    weights: np.ndarray
    cfg: TrainConfig = TrainConfig()
    n: int = 30


def describe(asked: DataFrame, voices: dict[str, Voice], seed: int = 42) -> DataFrame:
    """(dataset, table_id, voice, cand_id, body): ``generate`` by many generators in one pass.

    ``asked`` (dataset, table_id, voice, prompt, words, k, said) has a row a table and generator;
    the generators have a fixed size and go with the plan. A draw does not depend on what else is asked.
    """
    spark = asked.sparkSession
    shared = spark.sparkContext.broadcast(voices)

    def run(frames):
        hashes = _Hashes()
        for frame in frames:
            for name, own in frame.groupby("voice", sort=False):
                voice = shared.value[name]
                for start in range(0, len(own), DRAWN_AT_ONCE):
                    out = _described(own.iloc[start : start + DRAWN_AT_ONCE], voice.weights, voice.cfg, voice.n, seed, hashes)
                    yield out.assign(voice=name)[["dataset", "table_id", "voice", "cand_id", "body"]]

    tasks = 2 * spark.sparkContext.defaultParallelism
    spread = asked.select("dataset", "table_id", "voice", "prompt", "words", "k", "said").repartition(tasks, "dataset", "table_id", "voice")
    return spread.mapInPandas(run, "dataset string, table_id long, voice string, cand_id int, body string")


def likelihoods(pairs: DataFrame, weights: np.ndarray, cfg: TrainConfig = TrainConfig(), prior: int = 0) -> DataFrame:
    """(dataset, table_id, win, win_ref, lose, lose_ref): the log likelihoods of each pair's texts, trained and frozen."""

    def run(frames):
        base = base_weights(cfg, prior)
        for frame in frames:
            xs = np.stack([features(p, cfg.features) for p in frame["prompt"]]) if len(frame) else np.zeros((0, cfg.features))
            of = lambda w, column: log_likelihoods(w, xs, np.stack([choices(t, cfg.vocabulary) for t in frame[column]])) if len(frame) else []
            yield frame[["dataset", "table_id"]].assign(win=of(weights, "chosen"), win_ref=of(base, "chosen"), lose=of(weights, "rejected"), lose_ref=of(base, "rejected"))

    return pairs.select("dataset", "table_id", "prompt", "chosen", "rejected").mapInPandas(run, "dataset string, table_id long, win double, win_ref double, lose double, lose_ref double")


def trained_weights(a, b, cfg: TrainConfig = TrainConfig(), prior: int = 0) -> np.ndarray:
    """The generator's weights from an adapter row; the frozen ones without one."""
    base = base_weights(cfg, prior)
    return base if a is None else LowRank(base, np.reshape(a, (cfg.rank, cfg.features)), np.reshape(b, (cfg.vocabulary, cfg.rank)), cfg.alpha / cfg.rank).weights()


def sample(logits: np.ndarray, temperature: float = 0.5, top_p: float = 0.9, top_k: int = 50, seed: int | np.random.Generator = 42) -> int:
    """One choice: the best ``top_k``, of those the head of mass ``top_p``; temperature 0 takes the best."""
    if temperature == 0:
        return int(np.argmax(logits))
    order = np.argsort(-logits, kind="stable")[:top_k]
    p = np.exp((logits[order] - logits[order[0]]) / temperature)
    p /= p.sum()
    head = int(np.searchsorted(np.cumsum(p), top_p)) + 1
    p = p[:head] / p[:head].sum()
    at = np.searchsorted(np.cumsum(p), np.random.default_rng(seed).random(), side="right")
    return int(order[min(at, head - 1)])


def export_jsonl(pairs: DataFrame, path: str) -> None:
    """(prompt, chosen, rejected, held_out) as JSON lines, one folder a fold."""
    pairs.select("prompt", "chosen", "rejected", "held_out").write.partitionBy("held_out").json(path)
