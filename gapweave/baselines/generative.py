"""The generative meta-model's stand-in: gap masks from a position-dependent two-state Markov chain, or a tiny adversarial pair."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import SEEDS, unit


def transition_counts(wins: DataFrame, w: int) -> DataFrame:
    """(pos, prev, cur, n): how often slot pos is cur (1 missing) after prev; prev is 2 before the first slot."""
    gone = F.transform("x", lambda v: v.isNull().cast("int"))
    cells = wins.select(gone.alias("g")).select(F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: F.struct(F.when(i == 0, 2).otherwise(F.try_element_at("g", i)).alias("prev"), F.element_at("g", i + 1).alias("cur")))).alias("pos", "s"))
    return cells.groupBy("pos", F.col("s.prev").alias("prev"), F.col("s.cur").alias("cur")).agg(F.count("*").alias("n"))


def chain(counts: DataFrame, w: int) -> np.ndarray:
    """P(missing at pos | prev), add-one smoothed: (w, 3)."""
    n = np.ones((w, 3, 2))
    for r in counts.collect():  # at most 6 w rows
        n[r.pos, r.prev, r.cur] += r.n
    return n[:, :, 1] / n.sum(axis=2)


def generated(chain_: np.ndarray, *ids: Column | str, seed: int = SEEDS["generate"]) -> Column:
    """An array of 0/1 (1 missing) drawn from the chain."""
    w = len(chain_)
    table = F.array(*[F.array(*[F.lit(float(p)) for p in row]) for row in chain_])

    def step(acc, i):
        p = F.element_at(F.element_at(table, i + 1), F.when(i == 0, 3).otherwise(F.element_at(acc, -1) + 1))
        return F.concat(acc, F.array((unit(seed, *ids, i) < p).cast("int")))

    return F.slice(F.aggregate(F.sequence(F.lit(0), F.lit(w - 1)), F.array(F.lit(0)), step), F.lit(2), F.lit(w))


def _sigmoid(t: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(t, -30, 30)))


def train_generator(masks: np.ndarray, seed: int = 0, rounds: int = 300, hidden: int = 16, rate: float = 0.05) -> tuple[np.ndarray, np.ndarray]:
    """A tiny generator of masks (1 missing) trained against a logistic critic on pairwise features of real ones: its weights."""
    rng = np.random.default_rng(seed)
    w = masks.shape[1]
    a, b = rng.normal(0, 0.5, (hidden, w)), np.log((masks.mean(axis=0) + 0.02) / (1.02 - masks.mean(axis=0)))
    critic = np.zeros(2 * w - 1)
    look = lambda m: np.hstack([m, m[:, 1:] * m[:, :-1]])
    for _ in range(rounds):
        real = look(masks[rng.integers(0, len(masks), 64)].astype(float))
        noise = rng.normal(size=(64, hidden))
        p = _sigmoid(noise @ a + b)
        fake = look(p)
        critic += rate * (real.T @ (1 - _sigmoid(real @ critic)) - fake.T @ _sigmoid(fake @ critic)) / 64 - 0.01 * critic
        pull = (1 - _sigmoid(fake @ critic))[:, None]
        own, neighbour = critic[:w], critic[w:]
        grad = own[None] + np.hstack([np.zeros((64, 1)), p[:, :-1] * neighbour]) + np.hstack([p[:, 1:] * neighbour, np.zeros((64, 1))])
        flow = pull * grad * p * (1 - p)
        a += rate * noise.T @ flow / 64
        b = b + rate * flow.mean(axis=0)
    return a, b


def sample_masks(generator: tuple[np.ndarray, np.ndarray], u: np.ndarray) -> np.ndarray:
    """Masks (True missing) from uniform draws, a row a mask: as many as the generator has hidden units, then one a slot."""
    a, b = generator
    noise = (u[:, : len(a)] - 0.5) * np.sqrt(12.0)  # mean 0, variance 1
    return u[:, len(a) :] < _sigmoid(noise @ a + b)


def adversarial_masks(masks: np.ndarray, n: int, seed: int = 0, rounds: int = 300, hidden: int = 16, rate: float = 0.05) -> np.ndarray:
    """n masks (1 missing) from a generator trained on ``masks``."""
    generator = train_generator(masks, seed, rounds, hidden, rate)
    return sample_masks(generator, np.random.default_rng(seed + 1).random((n, hidden + masks.shape[1]))).astype(int)
