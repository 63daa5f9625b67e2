"""Gap-aware dynamic time warping, vectorised over windows and centroids at once."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


def gap_dtw(x: np.ndarray, y: np.ndarray, band: int | None = None, rule: str = "strict", correction: str = "inflate", root: bool = True) -> np.ndarray:
    """Distances of broadcast batches: x (..., n) and y (..., m), NaN marking gaps.

    A cell costs the squared difference, or nothing where either side is a gap. Both sequences may always advance
    together; one alone only where the departing and the entered cell are fully observed (``strict``) or the entered
    one is (``entered``). The cost is then inflated (or deflated) by all over observed samples, and rooted. NaN where
    nothing at all is observed.
    """
    n, m = x.shape[-1], y.shape[-1]
    shape = np.broadcast_shapes(x.shape[:-1], y.shape[:-1])
    seen_x, seen_y = ~np.isnan(x), ~np.isnan(y)
    above = [np.full(shape, np.inf) for _ in range(m + 1)]
    above[0] = np.zeros(shape)
    for i in range(n):
        row = [np.full(shape, np.inf)]
        for j in range(m):
            if band is not None and abs(i - j) > band:
                row.append(np.full(shape, np.inf))
                continue
            both = seen_x[..., i] & seen_y[..., j]
            cost = np.where(both, (np.nan_to_num(x[..., i]) - np.nan_to_num(y[..., j])) ** 2, 0.0)
            best = above[j]  # both advance
            if j:  # y alone
                legal = both if rule == "entered" else both & seen_y[..., j - 1]
                best = np.minimum(best, np.where(legal, row[j], np.inf))
            if i:  # x alone
                legal = both if rule == "entered" else both & seen_x[..., i - 1]
                best = np.minimum(best, np.where(legal, above[j + 1], np.inf))
            row.append(np.broadcast_to(cost + best, shape))
        above = row
        above[0] = np.full(shape, np.inf)
    total = above[m]
    observed = seen_x.sum(axis=-1) + seen_y.sum(axis=-1)
    with np.errstate(divide="ignore", invalid="ignore"):
        if correction != "none":
            share = (n + m) / np.broadcast_to(observed, shape)
            total = total * share if correction == "inflate" else total / share
            total = np.where(observed == 0, np.nan, total)
        return np.sqrt(total) if root else total


def gap_euclid(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The diagonal path only, with the same correction."""
    both = ~(np.isnan(x) | np.isnan(y))
    cost = np.where(both, (np.nan_to_num(x) - np.nan_to_num(y)) ** 2, 0.0).sum(axis=-1)
    observed = (~np.isnan(x)).sum(axis=-1) + (~np.isnan(y)).sum(axis=-1)
    return np.sqrt(cost * (x.shape[-1] + y.shape[-1]) / np.where(observed == 0, np.nan, observed))


def distances_to(z: str | Column, centroids: np.ndarray, band: int | None = None, **options) -> Column:
    """``array<double>``: the warping distance of an array column to every centroid, in Arrow batches."""

    @F.pandas_udf("array<double>")
    def measure(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            if not len(batch):
                yield pd.Series([], dtype=object)
                continue
            x = np.array([np.array(v, dtype=float) for v in batch])
            yield pd.Series(list(gap_dtw(x[:, None, :], centroids[None, :, :], band=band, **options)))

    return measure(z)


def euclid_to(z: str | Column, centroids: np.ndarray) -> Column:
    """``array<double>``: the diagonal distance to every centroid, in JVM expressions."""
    z = F.col(z) if isinstance(z, str) else z
    w = centroids.shape[1]
    n = F.size(F.filter(z, lambda v: v.isNotNull()))
    out = []
    for c in centroids:
        cost = F.aggregate(F.zip_with(z, F.array(*[F.lit(float(v)) for v in c]), lambda a, b: F.coalesce((a - b) * (a - b), F.lit(0.0))), F.lit(0.0), lambda s, v: s + v)
        out.append(F.sqrt(cost * F.lit(2.0 * w) / (n + w)))
    return F.array(*out)


def nearest(distances: str | Column) -> Column:
    """(dist, cluster) of the nearest centroid; ties to the lowest cluster."""
    return F.array_min(F.transform(distances, lambda d, k: F.struct(d.alias("dist"), k.alias("cluster"))))


def ranked(distances: str | Column) -> Column:
    """All (dist, cluster), nearest first."""
    return F.array_sort(F.transform(distances, lambda d, k: F.struct(d.alias("dist"), k.alias("cluster"))))
