"""Fits over more windows than one group may hold: sums of every window, merged, for any learner that has them."""

from __future__ import annotations

import pickle
import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..baselines.generative import sample_masks
from ..functions.hashing import draw, draw_py
from ..learners.core import LEARNERS

#: Windows that a map handles at once.
CHUNK = 512
#: Windows, by hash, from which is taken what a learner tunes before it sees the others (a kernel's width, a lag).
TUNING = 2000


@dataclass(frozen=True)
class Job:
    """One model over all windows: slots are hidden at random at ``rate``, or as ``generator`` (its parameters) draws them."""

    learner: str
    rate: float
    seed: int
    generator: tuple | None = None


def arrays(column, w: int) -> np.ndarray:
    return np.array([np.array(v, dtype=float) for v in column]).reshape(-1, w)


def window_draws(seed: int, series: list, wins: list, n: int) -> np.ndarray:
    """(windows, n) uniform draws, a window's own: the same in every batch and partition."""
    return np.array([np.random.default_rng(draw_py(seed, s, k)).random(n) for s, k in zip(series, wins, strict=True)]).reshape(-1, n)


def hidden_slots(job: Job, series: list, wins: list, w: int) -> np.ndarray:
    """Which slots of each window the job hides; at least one."""
    if job.generator is None:
        u = window_draws(job.seed + 1, series, wins, w)
        hidden = u < job.rate
    else:
        u = window_draws(job.seed + 1, series, wins, len(job.generator[0]) + w)
        hidden = sample_masks(job.generator, u)
        u = u[:, -w:]
    none = np.flatnonzero(~hidden.any(axis=1))
    hidden[none, u[none].argmin(axis=1)] = True
    return hidden


def _added(parts: list[dict]) -> dict:
    return {k: np.sum([p[k] for p in parts], axis=0) for k in parts[0]}


def fit_everywhere(train: DataFrame, w: int, jobs: dict[int, Job]) -> dict[int, tuple[dict, int, float]]:
    """(params, windows, milliseconds of all workers) of each job, from every row of ``train`` (series_id, win, z complete).

    A row a task, job and shard is shuffled, and one row a job reaches the driver.
    """
    if not jobs:
        return {}
    total = train.count()
    drawn = train if total <= TUNING else train.where(draw(917, "series_id", "win") < TUNING / total * float(1 << 32))
    some = sorted(drawn.select("series_id", "win", "z").collect())  # about TUNING rows
    series, wins, z = [r.series_id for r in some], [r.win for r in some], arrays([r.z for r in some], w)
    if not len(z):
        return {}
    prepared = {}
    for i, job in jobs.items():
        hidden = hidden_slots(job, series, wins, w)
        prepared[i] = LEARNERS[job.learner].prepare(np.where(hidden, np.nan, z), z, job.seed)

    def partial(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        totals: dict[int, list] = {}
        for pdf in batches:
            for begin in range(0, len(pdf), CHUNK):
                part = pdf.iloc[begin : begin + CHUNK]
                z, series, wins = arrays(part["z"], w), part["series_id"].tolist(), part["win"].tolist()
                shown: dict[tuple, np.ndarray] = {}
                for i, job in jobs.items():
                    started = time.perf_counter()
                    key = (job.rate, job.seed, None if job.generator is None else i)
                    if key not in shown:
                        shown[key] = hidden_slots(job, series, wins, w)
                    seeds = [draw_py(job.seed + 2, s, k) for s, k in zip(series, wins, strict=True)] if job.learner == "linear_diffusion" else []
                    sums = LEARNERS[job.learner].sums(prepared[i], np.where(shown[key], np.nan, z), z, seeds)
                    old = totals.get(i)
                    spent = (time.perf_counter() - started) * 1000
                    totals[i] = [_added([old[0], sums]), old[1] + len(z), old[2] + spent] if old else [sums, len(z), spent]
        task = TaskContext.get().partitionId()
        yield pd.DataFrame([(i, task % 16, n, ms, pickle.dumps(t)) for i, (t, n, ms) in totals.items()], columns=["job", "part", "n", "ms", "sums"])

    def merge(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["part", "n"])
        made = None
        for blob in pdf["sums"]:
            made = pickle.loads(blob) if made is None else _added([made, pickle.loads(blob)])
        return pd.DataFrame([(int(pdf["job"].iloc[0]), int(pdf["part"].iloc[0]), int(pdf["n"].sum()), float(pdf["ms"].sum()), pickle.dumps(made))], columns=["job", "part", "n", "ms", "sums"])

    schema = "job int, part int, n long, ms double, sums binary"
    sums = train.select("series_id", "win", "z").mapInPandas(partial, schema).groupBy("job", "part").applyInPandas(merge, schema).groupBy("job").applyInPandas(merge, schema)
    return {r.job: (LEARNERS[jobs[r.job].learner].from_sums(prepared[r.job], pickle.loads(r.sums)), r.n, r.ms) for r in sums.orderBy(F.col("job")).collect()}
