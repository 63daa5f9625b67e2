"""Fits of many models over rows that no task holds together: each task adds up sums by key, and the sums are merged."""

from __future__ import annotations

import pickle
import time
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame

SUMS = "key int, part int, n long, ms double, sums binary"
_MIX = (np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))


def added(parts: list[dict]) -> dict:
    return {k: np.sum([p[k] for p in parts], axis=0) for k in parts[0]}


def uniforms(seed: int, ids: np.ndarray, n: int) -> np.ndarray:
    """(rows, n) draws in [0, 1) from a seed and 64-bit ids, a row's own: the same in every batch and partition."""
    with np.errstate(over="ignore"):
        steps = (np.arange(1, n + 1, dtype=np.uint64) + np.uint64(seed % (1 << 32)) * np.uint64(1 << 20)) * np.uint64(0x9E3779B97F4A7C15)
        x = _mixed(_mixed(ids.astype(np.int64).view(np.uint64))[:, None] + steps[None])
    return (x >> np.uint64(11)) / float(1 << 53)


def _mixed(x: np.ndarray) -> np.ndarray:
    for shift, factor in zip((30, 27), _MIX, strict=True):
        x = (x ^ (x >> np.uint64(shift))) * factor
    return x ^ (x >> np.uint64(31))


def merged_sums(rows: DataFrame, sums_of: Callable[[pd.DataFrame], Iterator[tuple[int, int, dict]]]) -> dict[int, tuple[dict, int, float]]:
    """key -> (sums, rows, milliseconds of all workers); ``sums_of`` yields (key, rows, sums) of a batch.

    A row a task, key and shard is shuffled, and one row a key reaches the driver.
    """

    def partial(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        totals: dict[int, tuple] = {}
        for pdf in batches:
            began = time.perf_counter()
            for key, n, sums in sums_of(pdf) if len(pdf) else ():
                old, now = totals.get(key), time.perf_counter()
                spent, began = (now - began) * 1000, now
                totals[key] = (added([old[0], sums]), old[1] + n, old[2] + spent) if old else (sums, n, spent)
        task = TaskContext.get().partitionId()
        yield pd.DataFrame([(k, task % 16, n, ms, pickle.dumps(t)) for k, (t, n, ms) in totals.items()], columns=["key", "part", "n", "ms", "sums"])

    def merge(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf, made = pdf.sort_values(["part", "n"]), None
        for blob in pdf["sums"]:
            made = pickle.loads(blob) if made is None else added([made, pickle.loads(blob)])
        return pd.DataFrame([(int(pdf["key"].iloc[0]), int(pdf["part"].iloc[0]), int(pdf["n"].sum()), float(pdf["ms"].sum()), pickle.dumps(made))], columns=["key", "part", "n", "ms", "sums"])

    out = rows.mapInPandas(partial, SUMS).groupBy("key", "part").applyInPandas(merge, SUMS).groupBy("key").applyInPandas(merge, SUMS)
    return {r.key: (pickle.loads(r.sums), r.n, r.ms) for r in out.collect()}
