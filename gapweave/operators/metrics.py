"""Accuracy and cost measures."""

from __future__ import annotations

import time
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def errors(df: DataFrame, by: list[str], predicted: str = "pred", truth: str = "truth") -> DataFrame:
    """mse, mae, rmse, bias, r2 and n over hidden slots, pooled; one row per slot in ``df``."""
    e = F.col(predicted) - F.col(truth)
    g = df.groupBy(*by).agg(F.avg(e * e).alias("mse"), F.avg(F.abs(e)).alias("mae"), F.avg(e).alias("bias"), F.var_pop(truth).alias("variance"), F.count(e).alias("n"))
    return g.withColumns({"rmse": F.sqrt("mse"), "r2": 1 - F.col("mse") / F.when(F.col("variance") > 0, F.col("variance"))})


def reduction_pct(ours: Column, other: Column) -> Column:
    return 100 * (1 - ours / F.when(other != 0, other))


def win_grid(scores: DataFrame, ours: str, other: str, by: list[str], digits: int = 4) -> DataFrame:
    """Strict wins, losses and ties (equal at ``digits``) of one strategy against another."""
    cells = scores.where(F.col("strategy").isin(ours, other)).groupBy("dataset", "learner", "gap_kind", "rate").pivot("strategy", [ours, other]).agg(F.round(F.first("mse"), digits))
    a, b = F.col(ours), F.col(other)
    cells = cells.where(a.isNotNull() & b.isNotNull())
    return cells.groupBy(*by).agg(F.sum((a < b).cast("int")).alias("wins"), F.sum((a > b).cast("int")).alias("losses"), F.sum((a == b).cast("int")).alias("ties"), F.exp(F.avg(F.ln(F.when((a > 0) & (b > 0), b / a)))).alias("mean_ratio"))


class Timer:
    """Wall milliseconds by stage."""

    def __init__(self) -> None:
        self.rows: list[tuple[str, float]] = []

    @contextmanager
    def stage(self, name: str):
        began = time.perf_counter()
        yield
        self.rows.append((name, (time.perf_counter() - began) * 1000))

    def table(self, spark) -> DataFrame:
        return spark.createDataFrame(self.rows, "stage string, ms double")


def operation_counts(n_complete: int, n_incomplete: int, k: int, w: int, iterations: int, schedule: int, runs: int) -> dict[str, int]:
    """What the complexity formulas count: distances, warping cells, fits."""
    return {"kmeans_distances": iterations * k * n_complete, "dbi_cells": n_complete * w + k * k * w, "dtw_cells": n_incomplete * k * w * w, "mask_fits": k * schedule * (runs + 1)}
